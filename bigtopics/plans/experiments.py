"""The experiment workloads on the given tables: each returns its measured rows.

Sizes follow the machine: topic counts and iterations are parameters, and times
are of the session they run in.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rand import uniform
from ..operators import baselines, clicks, counts, dedup, measures, predict, prepare, retrieval, sampling
from ..sources import corpora
from ..sources.files import settle
from . import training
from .queries import _t, query
from .queries_use import whole_passages


def clean_tokens(spark: SparkSession, d: str, min_tf: int = 5) -> tuple[DataFrame, int]:
    """The cleaned sentence corpus as integer tokens, and its vocabulary size."""
    # texts are split once: the cleaning steps read the words several times
    s = settle(corpora.query_id(corpora.sentences(_t(spark, d, "documents"))).select("query_id", "words"), "sentences")
    clean, _ = prepare.prepare_corpus(s, min_tf=min_tf)
    t = prepare.explode_words(settle(clean, "clean")).withColumnRenamed("query_id", "doc_id")
    vocab = settle(prepare.build_vocab(prepare.word_counts(t)), "vocab")
    return settle(prepare.encode(t, vocab), "tokens"), vocab.count()


def trained(spark, tokens, vocab_size, topics, iterations, **more) -> training.GridTrainer:
    return training.GridTrainer(spark, training.Settings(topics=topics, vocab_size=vocab_size, shards=4, **more)).start(tokens).train(iterations)


@query()
def exp_pmi_by_topics(spark, d, ks=(4, 16, 64), iterations=3):
    """Mean PMI of the topics for growing numbers of topics."""
    tokens, v = clean_tokens(spark, d)
    out = []
    for k in ks:
        phi, _ = trained(spark, tokens, v, k, iterations).model()
        r = measures.topic_pmi(settle(phi, "phi"), tokens).agg(F.round(F.avg("pmi"), 4).alias("m"), F.count(F.lit(1)).alias("n")).first()
        out.append((k, r.n, r.m))
    return spark.createDataFrame(out, "topics bigint, scored bigint, mean_pmi double")


@query()
def exp_predictors(spark, d, topics=16, iterations=3):
    """Queries a second and perplexity of the greedy predictor (pruned and full) and the sampler, on held-out queries."""
    tokens, v = clean_tokens(spark, d)
    part = uniform("doc_id")
    test = settle(tokens.filter(part < 0.1), "test")
    g = trained(spark, tokens.filter(part >= 0.1), v, topics, iterations)
    phi, psi = (settle(x, "model") for x in g.model())
    alpha = counts.flat_alpha(psi, 0.1)
    totals = [0] * topics
    for r in psi.collect():
        totals[r.topic] = r.n
    q = settle(predict.packed_queries(test, phi, predict.best_prior_topic(phi, psi, alpha, 0.01, v)), "queries")
    n, rows = q.count(), []
    for method in ("pruned", "full", "sampling"):
        begun = time.time()
        got = settle(predict.predict(q, totals, [0.1] * topics, 0.01, v, method=method), "predicted")
        seconds = time.time() - begun
        p = got.groupBy("doc_id").agg(F.sum("n").alias("len")).join(got, "doc_id")
        grid = got.select("doc_id").distinct().crossJoin(F.broadcast(psi.select("topic")))  # K rows
        theta = grid.join(p, ["doc_id", "topic"], "left").na.fill(0.0, ["n"])
        length = got.groupBy("doc_id").agg(F.sum("n").alias("l"))
        theta = theta.join(length, "doc_id").select("doc_id", "topic", ((F.col("n") + 0.1) / (F.col("l") + 0.1 * topics)).alias("p"))
        perp = measures.perplexity(test.join(phi.select("word_id").distinct(), "word_id", "left_semi"), theta, phi, psi, 0.01, v).first().perplexity
        rows.append((method, n, round(n / seconds, 1), perp))
    return spark.createDataFrame(rows, "method string, queries bigint, per_second double, perplexity double")


@query()
def exp_predictor_rate(spark, d, ks=(16, 256, 4096)):
    """Queries a second of one core by each predictor for growing numbers of topics: kernel time alone, over all held-out baskets, by models trained on the others."""
    tokens = settle(corpora.baskets(_t(spark, d, "lineitem")), "tokens")
    test, seen = settle(tokens.filter(uniform("doc_id") < 0.1), "test"), settle(tokens.filter(uniform("doc_id") >= 0.1), "seen")
    v, rows = tokens.select("word_id").distinct().count(), []
    for k in ks:
        phi, psi = (settle(x, "model") for x in trained(spark, seen, v, k, 3).model())
        alpha, totals = counts.flat_alpha(psi, 0.1), [0] * k
        for r in psi.collect():
            totals[r.topic] = r.n
        q = settle(predict.packed_queries(test, phi, predict.best_prior_topic(phi, psi, alpha, 0.01, v)), "queries")
        for method in ("pruned", "full", "sampling"):
            t = predict.predict(q, totals, [0.1] * k, 0.01, v, method=method, timed=True).agg(F.sum("queries").alias("n"), F.sum("seconds").alias("s")).first()
            rows.append((k, method, t.n, round(t.n / t.s, 1)))
    return spark.createDataFrame(rows, "topics bigint, method string, queries bigint, per_second_core double")


@query()
def exp_iteration_time(spark, d, ks=(8, 64, 512)):
    """Seconds of an iteration for growing numbers of topics: the grid, and the rival until its full copy is refused."""
    tokens, v = clean_tokens(spark, d)
    rows = []
    for k in ks:
        rows.append((k, "grid", trained(spark, tokens, v, k, 1).log[-1]["seconds"]))
        try:
            r = training.ReplicatedTrainer(spark, training.Settings(topics=k, vocab_size=v, shards=4), max_model_bytes=16 << 20).start(tokens).train(1)
            rows.append((k, "replicated", r.log[-1]["seconds"]))
        except baselines.ModelTooLarge:
            rows.append((k, "replicated", None))
    return spark.createDataFrame(rows, "topics bigint, trainer string, seconds double")


@query()
def exp_likelihood_gap(spark, d, topics=8, iterations=4):
    """Joint log-likelihood after each iteration: grid in each mode against one machine, and the gap to it."""
    tokens = settle(corpora.baskets(_t(spark, d, "lineitem")), "tokens")  # read by the count, the reference and each mode
    vocab = settle(tokens.select("word_id").distinct(), "words")
    v = vocab.count()
    # the one-machine reference holds its corpus by definition
    ids, pos, words = (np.concatenate(c) for c in zip(*training.collect_columns(tokens.select("doc_id", "pos", "word_id")), strict=True))
    order = np.lexsort((pos, ids))
    docs, words = (np.unique(c[order], return_inverse=True)[1] for c in (ids, words))
    del ids, pos, order
    _, one = sampling.train_sequential(docs, words, topics, v, iterations=iterations, spark=spark)
    rows = [("sequential", i + 1, round(x, 2)) for i, x in enumerate(one)]
    for sync in ("relaxed", "segment", "diagonal"):
        g = training.GridTrainer(spark, training.Settings(topics=topics, vocab_size=v, shards=2, sync=sync)).start(tokens)
        for i in range(iterations):
            g.step()
            rows.append((sync, i + 1, round(counts.joint_log_likelihood(g.state, 0.1, 0.01, topics, v).first().ll, 2)))
    return spark.createDataFrame(rows, "trainer string, iter bigint, ll double")


@query()
def exp_dedup_quality(spark, d, topics=48, iterations=3, taus=(0.4, 0.8, 1.2, 1.6)):
    """Topics left for each threshold after training with too many topics and a learned prior."""
    tokens, v = clean_tokens(spark, d)
    g = trained(spark, tokens, v, topics, iterations, prior_from=2, prior_every=1)
    phi, psi = (settle(x, "model") for x in g.model())
    rows = []
    for tau in taus:
        pairs = settle(dedup.similar_topics(phi, psi, tau), "pairs")
        left = dedup.cluster_topics(psi, pairs).select("cluster").distinct().count()
        rows.append((tau, round(1 - tau / 2, 6), pairs.count(), left))
    return spark.createDataFrame(rows, "tau double, sim double, pairs bigint, topics_left bigint")


@query()
def exp_click_gain(spark, d, ks=(4, 8, 16, 32, 64), iterations=3):
    """Held-out AUC of the click model without and with P(word | query) of a topic model as features, and the relative gain: five numbers of topics, a 90/10 split."""
    t = prepare.tokenize(_t(spark, d, "documents"), "doc_id", "text")
    vocab = settle(prepare.build_vocab(prepare.word_counts(t)), "vocab")  # every word: the features are P(word | query) of all of them
    v = vocab.count()
    tokens = settle(prepare.encode(t, vocab), "tokens")
    labels = _t(spark, d, "labels").select("doc_id", F.col("toxic").cast("double").alias("label"))
    base = settle(clicks.click_features(_t(spark, d, "documents").join(labels, "doc_id")).select("doc_id", "label", "feats"), "shown")

    def score(df: DataFrame, extra: str | None = None) -> float:
        train, test = clicks.split_impressions(df)
        return measures.auc(clicks.score_clicks(clicks.fit_click_model(train, extra=extra), test)).first().auc

    first = score(base)
    rows = [(0, first, 0.0)]
    for k in ks:
        g = trained(spark, tokens, v, k, iterations)
        phi, psi = (settle(x, "model") for x in g.model())
        theta = base.select("doc_id").join(counts.count_doc_topic(g.state), "doc_id", "left")  # a document without words has the prior's vector
        shares = clicks.likelihood_vectors(theta, phi, psi, counts.flat_alpha(psi, 0.1), 0.01, v)
        a = score(settle(base.join(shares, "doc_id"), "both"), "topics")
        rows.append((k, a, round(measures.relative_gain(a, first), 4)))
    return spark.createDataFrame(rows, "topics bigint, auc double, gain double")


@query()
def exp_retrieval_by_topics(spark, d, ks=(8, 32, 128), iterations=3, top=10):
    """MAP of finding the documents that hold a passage: words alone, and words mixed with the top 30 topic words, both by Weak-AND."""
    t = prepare.tokenize(_t(spark, d, "documents"), "doc_id", "text")
    vocab = settle(prepare.build_vocab(prepare.word_counts(t).filter("df >= 2")), "vocab")
    v = vocab.count()
    tokens = settle(prepare.encode(t, vocab), "tokens")
    asked = prepare.encode(prepare.tokenize(_t(spark, d, "benchmark").withColumnRenamed("item_id", "doc_id"), "doc_id", "text"), vocab)
    docs, q = settle(retrieval.word_vectors(tokens), "docs"), settle(retrieval.word_vectors(asked, "tf"), "asked")
    qrels = settle(whole_passages(_t(spark, d, "benchmark"), _t(spark, d, "documents")), "qrels")
    rows = []

    def run(k: int, vectors: DataFrame) -> None:
        m = retrieval.mean_average_precision(retrieval.weak_and(vectors, docs, top), qrels).first()
        rows.append((k, m.queries, m["map"]))

    run(0, q)
    for k in ks:
        phi, psi = (settle(x, "model") for x in trained(spark, tokens, v, k, iterations).model())
        alpha = counts.flat_alpha(psi, 0.1)
        totals = [0] * k
        for r in psi.collect():
            totals[r.topic] = r.n
        packed = predict.packed_queries(asked, phi, predict.best_prior_topic(phi, psi, alpha, 0.01, v))
        theta = settle(predict.predict(packed, totals, [0.1] * k, 0.01, v), "theta")
        feats = retrieval.topic_features_blocks(theta, phi, psi, alpha, 0.01, v)
        run(k, retrieval.expand_query(q, feats, "mix", 0.2))
    return spark.createDataFrame(rows, "topics bigint, queries bigint, map double")
