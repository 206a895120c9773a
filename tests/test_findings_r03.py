"""Cases of the findings of round 3."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bigtopics.jvm.sampler import sampler
from bigtopics.operators import clicks, sampling
from bigtopics.plans import experiments, training


@pytest.mark.parametrize("topics", [4, 130])
def test_f7_pieces_in_the_jvm_give_the_labels_of_the_kernel(spark, topics):
    rng, v, n = np.random.default_rng(2), 50, 600
    docs = np.repeat(np.arange(100), 6)
    words, z, u, a = rng.integers(0, v, n), rng.integers(0, topics, n), sampling.block_uniforms(7, 1, (0,), n), rng.random(topics)
    theta, phi, psi = sampling.count_arrays(docs, words, z, topics, v)
    want = sampling.sample_buckets(sampling.Block(docs, words, z, sampling.Table(theta), sampling.Rows.of(phi), psi.copy()), a, 0.01, v, u)
    s = sampler(spark, a, 0.01, v)
    s.open(psi.tobytes())
    w, k = np.nonzero(phi)
    s.model(w.astype("<i4").tobytes(), k.astype("<i4").tobytes(), phi[w, k].tobytes())
    s.draws(sampling.block_key(7, 1, (0,)).tobytes())
    got = s.piece(*(x.astype("<i4").tobytes() for x in (np.bincount(docs), words, z)))
    assert (np.frombuffer(got, "<i4") == want).all() and (want != z).any()


def test_f7_the_one_machine_trainer_has_the_same_trace_with_a_session(spark):
    rng = np.random.default_rng(3)
    docs, words = np.repeat(np.arange(80), 5), rng.integers(0, 40, 400)
    (a, x), (b, y) = (sampling.train_sequential(docs, words, 6, 40, iterations=3, spark=s) for s in (None, spark))
    assert (a == b).all() and x == y


@pytest.mark.parametrize("more", [{}, {"sync": "diagonal"}, {"configs": 2, "merge_every": 2}])
def test_f1_to_f11_blocks_are_sampled_by_the_jvm_with_the_labels_of_the_kernel(spark, more, monkeypatch):
    rng = np.random.default_rng(4)
    rows = [(int(d), p, int(w)) for d in range(60) for p, w in enumerate(rng.integers(0, 30, 5))]
    tokens = spark.createDataFrame(rows, "doc_id bigint, pos bigint, word_id bigint")
    g = training.GridTrainer(spark, training.Settings(topics=5, vocab_size=30, shards=2, **more)).start(tokens)
    want, state = {}, g.state.toPandas().sort_values(["doc_id", "pos"])
    total = np.bincount(state.z, minlength=5).astype(float)
    theta = {d: np.bincount(x.z, minlength=5) for d, x in state.groupby("doc_id")}
    if not more:  # each block by the kernel, from counts at the start
        for shard, x in state.groupby("word_shard"):
            words, w = np.unique(x.word_id, return_inverse=True)
            ids, d = np.unique(x.doc_id, return_inverse=True)
            phi = np.bincount(w * 5 + x.z, minlength=len(words) * 5).reshape(-1, 5).astype(float)
            b = sampling.Block(d, w, x.z.to_numpy().astype(int), sampling.Table(np.array([theta[i] for i in ids], float)), sampling.Rows.of(phi), total.copy())
            new = sampling.sample_buckets(b, np.full(5, 0.1), 0.01, 30, sampling.block_uniforms(7, 0, (0, int(shard)), len(x)))
            want |= dict(zip(zip(x.doc_id, x.pos, strict=True), new.tolist(), strict=True))
    monkeypatch.setattr(training, "_sampler", None)
    g.step()
    got = {(r.doc_id, r.pos): r.z for r in g.state.collect()}
    old = dict(zip(zip(state.doc_id, state.pos, strict=True), state.z, strict=True))
    assert len(got) == 300 and g.log[0]["changed"] == sum(got[x] != old[x] for x in got) > 0
    assert not want or got == want


def test_f1_to_f11_a_merged_model_is_the_counts_of_all_labels(spark):
    tokens = spark.createDataFrame([(d, p, (d * 3 + p) % 11) for d in range(30) for p in range(4)], "doc_id bigint, pos bigint, word_id bigint")
    g = training.GridTrainer(spark, training.Settings(topics=3, vocab_size=11, shards=2)).start(tokens).train(1)
    want = {(r.word_id, r.z): r.n for r in g.state.groupBy("word_id", "z").agg(F.count("*").alias("n")).collect()}
    assert {(r.word_id, r.topic): r.n for r in g.models().collect()} == want


def test_f12_the_click_model_has_all_words_and_all_labelled_documents(spark, tmp_path, monkeypatch):
    text = ["good day here", "bad day there", "day of one kind", "other words alone", "1 2 3"]
    rows = [(i, f"{text[i % 4]} only{'abcdefghijklmnopqrstuvwxyz'[i % 26]}x" if i != 7 else text[4], "en", "web", 20) for i in range(60)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, int(i % 4 == 1)) for i in range(60)], "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    seen, real = [], clicks.likelihood_vectors

    def spy(theta, phi, psi, alpha, beta, v, **more):
        out = real(theta, phi, psi, alpha, beta, v, **more)
        seen.append((v, phi.select("word_id").distinct().count(), {r.doc_id for r in out.collect()}))
        return out

    monkeypatch.setattr(clicks, "likelihood_vectors", spy)
    got = experiments.exp_click_gain(spark, str(tmp_path), ks=(2,), iterations=1).collect()
    words = {w.lower() for r in rows for w in r[1].split() if w.isalpha()}
    assert len(got) == 2 and seen == [(len(words), len(words), set(range(60)))]
