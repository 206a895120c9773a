"""The second round's queries against their SQL, and its methods against plain code."""

import numpy as np
import pytest
from oracle import database, differ
from pyspark.sql import functions as F

import __spark_entry__ as entry
from bigtopics.operators import counts, dedup, measures, pipeline_model, placement, predict
from bigtopics.plans import queries_more, training

FOLDER = "/root/testdata/sf0.001"
NAMES = "join_theta_pairs str_tokens agg_pivot_topic_lang udf_entropy udaf_auc udtf_packets state_bytes shard_fits stream_late_drop topic_features_top30".split()


@pytest.mark.parametrize("name", NAMES)
def test_equals_sql(spark, name):
    assert differ(entry.queries()[name](spark, FOLDER), database(FOLDER), entry.oracle_sql()[name]) is None


def model(spark):
    tokens = spark.createDataFrame([(d, p, (d * 7 + p * 3) % 10, (d + p) % 3) for d in range(30) for p in range(5)], "doc_id bigint, pos bigint, word_id bigint, z int")
    phi, psi = counts.count_word_topic(tokens), counts.count_topic(tokens)
    return tokens, phi, psi, [r.n for r in psi.orderBy("topic").collect()]


def test_queries_with_unknown_words_and_null_ids_are_answered(spark):
    _, phi, psi, totals = model(spark)
    best = predict.best_prior_topic(phi, psi, counts.flat_alpha(psi, 0.1), 0.01, 10)
    asked = spark.createDataFrame([(1, 0, 99), (1, 1, 98), (2, 0, 3), (2, 1, 99), (None, 0, 4), (-5, 0, 5)], "doc_id bigint, pos bigint, word_id bigint")
    q = predict.packed_queries(asked, phi, best)
    for how in ({"method": "pruned"}, {"method": "full"}, {"method": "sampling"}, {"trials": 3}):
        got = predict.predict(q, totals, [0.1] * 3, 0.01, 10, **how).groupBy("doc_id").agg(F.sum("n").alias("n")).collect()
        assert {r.doc_id: round(r.n, 6) for r in got} == {1: 2, 2: 2, None: 1, -5: 1}
    a, b = ({(r.doc_id, r.topic): r.n for r in predict.predict(q, totals, [0.1] * 3, 0.01, 10, method=m).collect()} for m in ("pruned", "full"))
    assert a == b


def test_held_out_likelihood_against_all_labellings(spark):
    from itertools import product
    from math import lgamma, log

    _, phi, psi, totals = model(spark)
    alpha = [0.4, 0.7, 0.2]
    asked = spark.createDataFrame([(1, 0, 3), (1, 1, 4), (1, 2, 3)], "doc_id bigint, pos bigint, word_id bigint")
    q = predict.packed_queries(asked, phi, predict.best_prior_topic(phi, psi, counts.flat_alpha(psi, 0.1), 0.01, 10))
    f = {(r.word_id, r.topic): r.n for r in phi.collect()}
    p = lambda w, k: (f.get((w, k), 0) + 0.01) / (totals[k] + 0.1)
    whole = 0.0
    for z in product(range(3), repeat=3):
        n = np.bincount(z, minlength=3)
        prior = np.exp(lgamma(sum(alpha)) - lgamma(3 + sum(alpha)) + sum(lgamma(x + a) - lgamma(a) for x, a in zip(n, alpha, strict=True)))
        whole += prior * np.prod([p(w, k) for w, k in zip((3, 4, 3), z, strict=True)])
    got = measures.heldout_log_likelihood(q, totals, alpha, 0.01, 10, temperatures=60, chains=80).first()
    assert got.n == 3 and abs(got.ll - log(whole)) < 0.1


def test_simulated_pipeline_is_slow_at_both_ends_and_resends_after_timeouts(spark):
    rows = pipeline_model.simulated_grid(spark, 400_000).collect()
    best = min(range(len(rows)), key=lambda k: rows[k].seconds)
    assert 0 < best < len(rows) - 1 and rows[0].factor > 1.01 and rows[-1].factor > 1.5
    slow = pipeline_model.Wire(workers=1, rate=1_000.0, timeout=0.5)
    assert pipeline_model.simulate(4_000, 100, 20, slow)[1] > 0 == pipeline_model.simulate(4_000, 100, 2, slow)[1]


def test_stream_of_baskets_is_predicted_like_a_batch(spark):
    got = {(r.doc_id, r.topic): r.n for r in queries_more.stream_predict(spark, FOLDER).collect()}
    _, _, phi, psi, alpha, v = queries_more._model(spark, FOLDER)
    q = predict.packed_queries(queries_more._tokens(spark, FOLDER), phi, predict.best_prior_topic(phi, psi, alpha, 0.01, v))
    want = predict.predict(q, [r.n for r in psi.orderBy("topic").collect()], [0.1] * 8, 0.01, v)
    assert got == {(r.doc_id, r.topic): r.n for r in want.collect()}


def test_min_hash_pairs_against_the_exact_join(spark):
    rng, rows = np.random.default_rng(4), []
    for t in range(30):
        for w in range(40):
            rows.append((int(t // 3 * 100 + w), t, int(rng.integers(1, 6))))
    phi = spark.createDataFrame(rows, "word_id bigint, topic int, n bigint")
    psi = phi.groupBy("topic").agg(F.sum("n").alias("n"))
    exact = {(r.a, r.b): r.l1 for r in dedup.similar_topics(phi, psi, 0.9).collect()}
    found = {(r.a, r.b): r.l1 for r in dedup.similar_topics_minhash(phi, psi, 0.9).collect()}
    assert exact and set(found) <= set(exact) and len(found) >= 0.9 * len(exact) and all(abs(exact[k] - x) < 1e-6 for k, x in found.items())


def test_limits_are_refused(spark):
    tokens, phi, *_ = model(spark)
    with pytest.raises(ValueError):
        training.ReplicatedTrainer(spark, training.Settings(topics=3, vocab_size=4)).start(tokens)
    with pytest.raises(ValueError):
        placement.check_shard_size(phi.withColumn("shard", F.lit(0)), 8)
