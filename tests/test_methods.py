"""Samplers, trainers, predictors, schedules and measures against brute force."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from bigtopics.operators import baselines, counts, dedup, measures, pipeline_model, placement, predict, sampling
from bigtopics.operators.retrieval import wand
from bigtopics.plans import training


def random_block(rng, docs=4, words=6, topics=3, n=30):
    d, w, z = rng.integers(0, docs, n), rng.integers(0, words, n), rng.integers(0, topics, n)
    return sampling.Block(d, w, z, *sampling.count_arrays(np.append(d, docs - 1), np.append(w, words - 1), np.append(z, 0), topics, words))


def test_bucket_and_dense_conditionals_agree():
    rng = np.random.default_rng(1)
    for _ in range(50):
        th, f, psi = rng.integers(0, 5, 4).astype(float), rng.integers(0, 5, 4).astype(float), rng.integers(5, 30, 4).astype(float)
        a, b, v = rng.random(4) + 0.01, 0.05, 20
        den = psi + b * v
        three = a * b / den + th * b / den + (a + th) * f / den
        assert np.allclose(three, sampling.dense_probabilities(th, f, psi, a, b, v))


@pytest.mark.parametrize("kernel", ["dense", "buckets"])
def test_sampler_reaches_the_exact_posterior(kernel):
    docs, words, k, v = np.array([0, 0, 1, 1]), np.array([0, 1, 1, 1]), 2, 2
    a, beta = np.array([0.5, 0.5]), 0.3
    exact = np.array([sampling.joint_ll(docs, words, np.array(z), k, v, a, beta) for z in itertools.product(range(k), repeat=4)])
    exact = np.exp(exact - exact.max())
    exact /= exact.sum()
    rng, z, seen = np.random.default_rng(3), np.zeros(4, int), np.zeros(16)
    for _ in range(12_000):
        z = sampling.KERNELS[kernel](sampling.Block(docs, words, z, *sampling.count_arrays(docs, words, z, k, v)), a, beta, v, rng.random(4))
        seen[int("".join(map(str, z)), 2)] += 1
    assert 0.5 * np.abs(seen / seen.sum() - exact).sum() < 0.03


def test_pruned_ascent_equals_full():
    rng = np.random.default_rng(5)
    for _ in range(100):
        k, v, beta = 6, 9, 0.05
        phi = rng.integers(0, 4, (v, k)) * (rng.random((v, k)) < 0.5)
        psi, alpha = phi.sum(0) + 1.0, rng.random(k) + 0.01
        words = rng.integers(0, v, 7)
        score = (phi + beta) / (psi + beta * v) * alpha
        best = score.argmax(1)[words]
        rows = [(np.flatnonzero(phi[w]), phi[w][phi[w] > 0].astype(float)) for w in words]
        z1, _ = predict.ascend(rows, best, psi, alpha, beta, v, pruned=True)
        z2, _ = predict.ascend(rows, best, psi, alpha, beta, v, pruned=False)
        assert (z1 == z2).all()


def test_annealed_likelihood_is_near_enumeration():
    rng = np.random.default_rng(2)
    p, alpha, words = rng.dirichlet(np.ones(4), 3).T, np.array([0.3, 0.5, 0.2]), np.array([0, 1, 1, 3, 2])
    assert abs(measures.heldout_ll_ais(words, p, alpha, temperatures=30, chains=150) - measures.exact_ll(words, p, alpha)) < 0.1


def test_weighted_placement_is_even():
    rng = np.random.default_rng(4)
    c = [(i, int(x)) for i, x in enumerate(rng.zipf(1.5, 500) % 1000 + 1)]
    loads = [0] * 7
    for w, s in placement.weighted_placement(c, 7):
        loads[s] += dict(c)[w]
    assert max(loads) - min(loads) <= max(x for _, x in c)


def test_free_schedule_never_conflicts_and_visits_all():
    rng = np.random.default_rng(6)
    costs = {(d, w): float(rng.integers(1, 20)) for d in range(5) for w in range(4)}
    events = placement.schedule_free(costs, 4, 1, 2)
    assert len(events) == 5 * 4 * 2
    for a, b in itertools.combinations(events, 2):
        assert a[3] >= b[4] or b[3] >= a[4] or (a[1] != b[1] and a[2] != b[2])


def test_nine_blocks_and_their_diagonals(spark):
    steps = {}
    for r in placement.schedule(spark, 3).collect():
        steps.setdefault(r.step, set()).add((r.doc_shard, r.word_shard))
    assert steps[0] == {(0, 0), (1, 1), (2, 2)} and all(len(x) == 3 for x in steps.values())


def test_pipeline_model_has_an_inner_optimum():
    t, kb, best = pipeline_model.tune_buffer(200_000, (1, 10, 100, 1000, 10_000, 200_000))
    assert 1 < kb < 200_000
    assert all(abs(pipeline_model.minutes(a, b) - m) / m < 0.08 for a, b, m in pipeline_model.PUBLISHED)


def test_weak_and_equals_exhaustive():
    rng = np.random.default_rng(8)
    for _ in range(60):
        lists, total = [], {}
        for _ in range(4):
            docs = np.sort(rng.choice(40, 15, replace=False))
            x = rng.integers(1, 5, 15) / 4
            lists.append((docs, x, float(x.max())))
            for d, s in zip(docs.tolist(), x.tolist(), strict=True):
                total[d] = total.get(d, 0) + s
        top, scored = wand(lists, 5)
        assert [(round(s, 6), d) for s, d in top] == [(round(s, 6), d) for d, s in sorted(total.items(), key=lambda x: (-x[1], x[0]))[:5]]
        assert scored <= len(total)


def planted(spark, topics=3, docs=60, length=12):
    rng = np.random.default_rng(9)
    rows = []
    for d in range(docs):
        t = d % topics
        rows += [(d, p, int(t * 5 + rng.integers(0, 5))) for p in range(length)]
    return spark.createDataFrame(rows, "doc_id bigint, pos bigint, word_id bigint")


@pytest.mark.parametrize("sync,configs", [("relaxed", 1), ("segment", 1), ("diagonal", 1), ("relaxed", 2)])
def test_grid_keeps_counts(spark, sync, configs):
    t = planted(spark)
    g = training.GridTrainer(spark, training.Settings(topics=3, vocab_size=15, shards=2, sync=sync, configs=configs, merge_every=2)).start(t).train(2)
    phi, psi = g.model()
    assert psi.agg(F.sum("n")).first()[0] == t.count() == phi.agg(F.sum("n")).first()[0]
    assert g.base.exceptAll(g.own_counts().groupBy("word_id", "word_shard", "topic").agg(F.sum("n").alias("n"))).isEmpty()


def test_resumed_equals_straight(spark):
    t, s = planted(spark), training.Settings(topics=3, vocab_size=15, shards=2)
    straight = training.GridTrainer(spark, s).start(t).train(2)
    saved = training.GridTrainer(spark, s).start(t).train(1).save()
    again = training.GridTrainer.load(spark, saved).train(1)
    cols = ["doc_id", "pos", "z"]
    assert straight.state.select(cols).exceptAll(again.state.select(cols)).isEmpty()


def test_sequential_finds_planted_topics(spark):
    rows = planted(spark).toPandas()
    z, trace = sampling.train_sequential(rows.doc_id.to_numpy(), rows.word_id.to_numpy(), 3, 15, iterations=30)
    own = rows.word_id.to_numpy() // 5
    purity = sum(np.bincount(own[z == k]).max(initial=0) for k in range(3)) / len(z)
    assert purity > 0.95 and trace[-1] > trace[0]


def test_full_copy_is_refused_when_too_large(spark):
    s = training.Settings(topics=10_000, vocab_size=1_000_000)
    with pytest.raises(baselines.ModelTooLarge):
        training.ReplicatedTrainer(spark, s).start(planted(spark))


def test_duplicated_topics_merge_back(spark):
    z = planted(spark).withColumn("z", (F.col("word_id") / 5).cast("int"))
    split = z.withColumn("z", F.when((F.col("z") == 0) & (F.col("pos") % 2 == 1), 3).otherwise(F.col("z")))
    phi, psi = counts.count_word_topic(split), counts.count_topic(split)
    pairs = dedup.similar_topics(phi, psi, 1.0)
    assert [(r.a, r.b) for r in pairs.collect()] == [(0, 3)]
    merged = dedup.merge_topics(phi, dedup.cluster_topics(psi, pairs))
    assert merged.exceptAll(counts.count_word_topic(z)).isEmpty()
    assert {r.cluster for r in dedup.leader_clusters(psi, pairs).collect()} == {0, 1, 2}
