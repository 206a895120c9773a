"""Cases of the findings of round 2."""

from collections import Counter
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__  # noqa: F401  (registers the queries)
from bigtopics.operators import baselines, clicks, counts, dedup, measures, predict, retrieval, sampling
from bigtopics.plans import queries, training
from bigtopics.sources import corpora

FOLDER = "/root/testdata/sf0.001"


def labelled(spark, docs=40, topics=4, words=30):
    rng = np.random.default_rng(3)
    rows = [(d, p, int(rng.integers(words)), int(rng.integers(topics))) for d in range(docs) for p in range(int(rng.integers(3, 9)))]
    return spark.createDataFrame(rows, "doc_id bigint, pos bigint, word_id bigint, z int")


def test_f25_no_plan_of_the_click_model_has_a_function_of_the_jvm(spark):
    shown = spark.createDataFrame([(k, float(k % 2), [f"w={k % 7}", "hit" if k % 2 else "miss"]) for k in range(200)], "doc_id bigint, label double, feats array<string>")
    fitted = clicks.fit_click_model(shown)
    scores = clicks.score_clicks(fitted, shown)
    assert "UDF" not in scores._jdf.queryExecution().executedPlan().toString()  # trained models of Spark score by such functions
    assert measures.auc(scores).first().auc == 1.0
    assert np.count_nonzero(fitted[2]) <= 2


def test_f26_word_shares_by_place_equal_sums_over_all_words(spark):
    z = labelled(spark)
    theta, phi, psi = counts.count_doc_topic(z), counts.count_word_topic(z), counts.count_topic(z)
    alpha, dims = counts.flat_alpha(psi, 0.1), 7
    got = {r.doc_id: np.array(r.topics) for r in clicks.likelihood_vectors(theta, phi, psi, alpha, 0.01, 30, dims=dims, scale=1.0).collect()}
    assert len(got) == 40 and all(abs(x.sum() - 1) < 1e-9 for x in got.values())  # all 30 words, also those outside the query's topics
    full = {}
    for r in retrieval.word_likelihood(theta, phi, psi, alpha, 0.01, 30).collect():
        full.setdefault(r.doc_id, {})[r.word_id] = r.p
    whole = [d for d, x in full.items() if len(x) == 30]
    for d in whole:
        want = np.bincount([w % dims for w in full[d]], list(full[d].values()), dims)
        assert np.allclose(got[d], want)
    assert whole


@pytest.mark.parametrize("name", "buffer_curve curve_gap diagonal_schedule dilution exp_pipeline pipeline_grid schedule_conflicts speedup_table".split())
def test_f27_to_f34_read_a_given_table(spark, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        queries.QUERIES[name](spark, "/root/testdata/none").collect()


def test_f14_f23_similar_topics_of_many_words_equal_all_pairs(spark):
    rng = np.random.default_rng(5)
    rows = [(int(w), t, int(rng.integers(1, 9))) for t in range(9) for w in rng.choice(400, 260, replace=False) + 40 * (t // 3)]
    phi = spark.createDataFrame(rows, "word_id bigint, topic int, n bigint")
    psi = phi.groupBy("topic").agg(F.sum("n").alias("n"))
    for tau in (1.15, 1.4):
        want = {(r.a, r.b): (r.l1, r.sim) for r in dedup.topic_l1(phi, psi).filter(F.col("l1") < tau).collect()}
        got = dedup.similar_topics(phi, psi, tau)
        assert "unboundedfollowing" not in got._jdf.queryExecution().toString()
        assert want and {(r.a, r.b): (r.l1, r.sim) for r in got.collect()} == want, tau
    assert dedup._verified(spark.createDataFrame([(0, 1)], "a int, b int"), dedup.word_shares(phi, psi)).count() == 1


def test_f1_word_sets_are_spelled_out_within_documents(spark):
    rng = np.random.default_rng(6)
    docs = [{f"w{x}" for x in rng.integers(0, 12, int(rng.integers(1, 8)))} for _ in range(300)]
    sets = spark.createDataFrame([(d, w) for d, s in enumerate(docs) for w in s], "doc_id bigint, word string")
    for size in (2, 3):
        want = Counter(c for s in docs for c in combinations(sorted(s), size))
        got = baselines.frequent_word_sets(sets, 9, size)
        assert {tuple(r)[:size]: r.support for r in got.collect()} == {k: n for k, n in want.items() if n >= 9}
        assert "doc_id" not in got._jdf.queryExecution().optimizedPlan().toString()  # no join by document


@pytest.mark.parametrize("kernel", ["buckets", "dense"])
def test_f9_labels_do_not_depend_on_the_pieces_a_kernel_takes(spark, kernel, monkeypatch):
    t, found = corpora.baskets(corpora.table(spark, FOLDER, "lineitem")), []
    for size in (1 << 16, 300):
        monkeypatch.setattr(training, "PIECE", size)
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "10000" if size > 300 else "190")
        s = training.Settings(topics=8, vocab_size=200, shards=2, kernel=kernel)
        g = training.GridTrainer(spark, s).start(t).train(1)
        r = training.ReplicatedTrainer(spark, s).start(t).train(1)
        found.append([sorted((x.doc_id, x.pos, x.z) for x in y.state.collect()) for y in (g, r)])
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert found[0] == found[1] and len(found[0][0]) == t.count()


def test_f9_pieces_hold_whole_documents_and_few_rows():
    docs = np.repeat(np.arange(50), 7)
    rows = {"g": docs // 20, "doc_id": docs, "kind": np.zeros(350, np.int64)}
    table = pa.table(rows).to_batches(max_chunksize=33)
    got = list(training._pieces(iter(table), ("g",), 40))
    assert max(len(x["g"]) for _, x in got) <= 40 + 33 and len(got) >= 6
    assert np.concatenate([x["doc_id"] for _, x in got]).tolist() == docs.tolist()
    ends = [(x["doc_id"][0], x["doc_id"][-1]) for _, x in got]
    assert all(a[1] != b[0] for a, b in zip(ends, ends[1:]))


def test_f4_rows_grow_in_place_and_one_machine_goes_by_pieces():
    rng, rows, want = np.random.default_rng(7), sampling.Rows(np.array([1]), np.array([3]), np.array([2]), 3), np.zeros((3, 9))
    want[1, 3] = 2
    for r, k in rng.integers(0, (3, 9), (200, 2)).tolist():
        rows.add(r, k, 1.0)
        want[r, k] += 1
    assert (rows.dense(9) == want).all()
    docs = np.repeat(np.arange(40), 5)
    cuts = sampling.document_pieces(docs, 12)
    assert cuts[0][0] == 0 and cuts[-1][1] == 200 and all(a[1] == b[0] and a[1] % 5 == 0 for a, b in zip(cuts, cuts[1:])) and len(cuts) > 5
    assert sampling.document_pieces(docs[::-1], 12) == [(0, 200)]


@pytest.mark.parametrize("pruned", [True, False])
@pytest.mark.parametrize("exclude_self", [True, False])
def test_f5_queries_solved_together_equal_queries_solved_alone(pruned, exclude_self):
    rng, k = np.random.default_rng(8), 6
    psi, alpha = rng.integers(20, 60, k).astype(float), rng.random(k)
    model = [(np.sort(rng.choice(k, int(rng.integers(0, 4)), replace=False)), rng.integers(1, 9, 4)) for _ in range(30)]
    asked = [rng.integers(0, 30, int(rng.integers(1, 6))).tolist() for _ in range(80)]
    best = rng.integers(-1, k, 30)
    f = pd.DataFrame({"doc_id": range(80), "best_topic": [[int(best[w]) for w in q] for q in asked], "topics": [[model[w][0] for w in q] for q in asked], "counts": [[model[w][1][: len(model[w][0])] for w in q] for q in asked]})
    row, topic, n = predict._solve_together(f, psi, alpha, 0.01, 30, 2, most=40, pruned=pruned, exclude_self=exclude_self)
    got = {}
    for r, t, x in zip(row.tolist(), topic.tolist(), n.tolist(), strict=True):
        got.setdefault(r, {})[t] = x
    for d, q in enumerate(asked):
        rows = [(model[w][0], model[w][1][: len(model[w][0])].astype(float)) for w in q]
        z, _ = predict.ascend(rows, np.array([best[w] if best[w] >= 0 else 2 for w in q]), psi, alpha, 0.01, 30, pruned=pruned, exclude_self=exclude_self)
        assert got[d] == dict(Counter(z.tolist())), d
