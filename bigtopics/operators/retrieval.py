"""Topic words for queries, sparse vectors, inverted lists, exhaustive and Weak-AND ranking, precision."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.files import settle


def background(phi: DataFrame, psi: DataFrame, alpha: DataFrame, beta: float, vocab_size: int) -> DataFrame:
    """word_id, g = sum over topics of phi * alpha, smoothed: the part of P(v|d) that no query changes."""
    t = psi.select("topic", F.col("n").alias("total")).join(alpha, "topic").withColumn("r", F.col("alpha") / (F.col("total") + F.lit(beta * vocab_size)))
    flat = t.agg((F.sum("r") * beta).alias("g0"))
    own = phi.join(F.broadcast(t), "topic").groupBy("word_id").agg(F.sum(F.col("n") * F.col("r")).alias("g1"))
    return own.crossJoin(F.broadcast(flat)).select("word_id", (F.col("g0") + F.col("g1")).alias("g"))


def word_likelihood(theta: DataFrame, phi: DataFrame, psi: DataFrame, alpha: DataFrame, beta: float, vocab_size: int) -> DataFrame:
    """doc_id, word_id, p: P(word | query) for words in the supports of the query's topics."""
    den = psi.select("topic", (F.col("n") + F.lit(beta * vocab_size)).alias("den"))
    total = alpha.agg(F.sum("alpha").alias("a"))
    length = theta.groupBy("doc_id").agg(F.sum("n").alias("len"))
    th = theta.join(F.broadcast(den), "topic").select("doc_id", "topic", (F.col("n") / F.col("den")).alias("t"))
    flat = th.groupBy("doc_id").agg((F.sum("t") * beta).alias("flat"))
    near = th.join(phi, "topic").groupBy("doc_id", "word_id").agg(F.sum(F.col("n") * F.col("t")).alias("own"))
    g = background(phi, psi, alpha, beta, vocab_size)
    j = near.join(flat, "doc_id").join(g, "word_id").join(length, "doc_id").crossJoin(F.broadcast(total))
    return j.select("doc_id", "word_id", ((F.col("own") + F.col("flat") + F.col("g")) / (F.col("len") + F.col("a"))).alias("p"))


def topic_features(likelihood: DataFrame, top: int = 30, digits: int = 9) -> DataFrame:
    """The top words of each query; ties (after rounding) go to the smaller id."""
    w = Window.partitionBy("doc_id").orderBy(F.desc("p"), "word_id")
    return likelihood.withColumn("p", F.round("p", digits)).withColumn("rank", F.row_number().over(w).cast("bigint")).filter(F.col("rank") <= top)


def topic_features_blocks(theta: DataFrame, phi: DataFrame, psi: DataFrame, alpha: DataFrame, beta: float, vocab_size: int, *, top: int = 30, digits: int = 9, doc_block: int = 1 << 14, word_block: int = 1 << 16) -> DataFrame:
    """doc_id, word_id, p, rank: as topic_features of word_likelihood, without a row for each query and word.

    A task holds one block of words (their counts by topic) and one of queries (their topics), adds up one vector per
    query and passes on its best words alone; blocks grow in number, not in size.
    """
    den = psi.select("topic", (F.col("n") + F.lit(beta * vocab_size)).alias("den"))
    share = theta.join(F.broadcast(den), "topic")
    each = F.array_sort(F.collect_list(F.struct("topic", (F.col("n") / F.col("den")).alias("t"))))
    docs = share.groupBy("doc_id").agg(each.alias("x"), F.sum("n").alias("len")).crossJoin(F.broadcast(alpha.agg(F.sum("alpha").alias("a"))))
    docs = settle(docs.select("doc_id", F.col("x.topic").alias("topics"), F.col("x.t").alias("shares"), (F.col("len") + F.col("a")).alias("over")), "queries")
    model = settle(phi.groupBy("word_id").agg(F.collect_list("topic").alias("topics"), F.collect_list("n").alias("counts")).join(background(phi, psi, alpha, beta, vocab_size), "word_id"), "model")
    n_docs, n_words = (max(1, -(-df.count() // size)) for df, size in ((docs, doc_block), (model, word_block)))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    q = docs.withColumn("db", F.pmod(F.xxhash64("doc_id"), F.lit(n_docs)).cast("int")).withColumn("wb", every(n_words))
    m = model.withColumn("wb", F.pmod(F.xxhash64("word_id"), F.lit(n_words)).cast("int")).withColumn("db", every(n_docs))

    def best(key: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out: dict = {"doc_id": [], "word_id": [], "p": []}
        if len(a) and len(b):
            b = b.sort_values("word_id")
            words, g = b["word_id"].to_numpy(), b["g"].to_numpy()
            at = np.repeat(np.arange(len(b)), [len(x) for x in b["topics"]])
            topic, n = np.concatenate(b["topics"].to_list()), np.concatenate(b["counts"].to_list()).astype(float)
            order = np.argsort(topic, kind="stable")
            kinds, starts = np.unique(topic[order], return_index=True)
            rows = dict(zip(kinds.tolist(), zip(np.split(at[order], starts[1:]), np.split(n[order], starts[1:]), strict=True), strict=True))
            for doc, topics, shares, over in zip(a["doc_id"], a["topics"], a["shares"], a["over"], strict=True):
                own = np.zeros(len(words))
                for t, x in zip(topics, shares, strict=True):
                    if t in rows:
                        own[rows[t][0]] += rows[t][1] * x
                live = np.flatnonzero(own)
                p = np.round((own[live] + float(np.sum(shares)) * beta + g[live]) / over, digits)
                if len(p) > top:
                    live, p = live[p >= (cut := np.partition(p, -top)[-top])], p[p >= cut]
                first = np.argsort(-p, kind="stable")[:top]  # words ascend, so ties go to the smaller id
                out["doc_id"] += [doc] * len(first)
                out["word_id"] += words[live[first]].tolist()
                out["p"] += p[first].tolist()
        return pd.DataFrame(out)

    kind = phi.schema["word_id"].dataType.simpleString()
    got = q.groupBy("db", "wb").cogroup(m.groupBy("db", "wb")).applyInPandas(best, f"doc_id bigint, word_id {kind}, p double")
    return topic_features(got, top, digits)


def word_vectors(tokens: DataFrame, weighting: str = "tfidf") -> DataFrame:
    """doc_id, word_id, w: unit vectors of tf or tf * ln(D / df)."""
    tf = tokens.groupBy("doc_id", "word_id").agg(F.count(F.lit(1)).alias("tf"))
    if weighting == "tf":
        raw = tf.select("doc_id", "word_id", F.col("tf").cast("double").alias("x"))
    else:
        docs = tf.select("doc_id").distinct().agg(F.count(F.lit(1)).alias("d"))
        df = tf.groupBy("word_id").agg(F.count(F.lit(1)).alias("df")).crossJoin(F.broadcast(docs)).select("word_id", F.log(F.col("d") / F.col("df")).alias("idf"))
        raw = tf.join(df, "word_id").select("doc_id", "word_id", (F.col("tf") * F.col("idf")).alias("x"))
    norm = raw.groupBy("doc_id").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    return raw.join(norm, "doc_id").filter("norm > 0").select("doc_id", "word_id", (F.col("x") / F.col("norm")).alias("w"))


def cosine_sparse(queries: DataFrame, docs: DataFrame) -> DataFrame:
    """query_id, doc_id, score by a join on words; both sides are unit vectors."""
    q = queries.select(F.col("doc_id").alias("query_id"), "word_id", F.col("w").alias("qw"))
    return q.join(docs, "word_id").groupBy("query_id", "doc_id").agg(F.sum(F.col("qw") * F.col("w")).alias("score"))


def cosine_dense(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def build_postings(vectors: DataFrame) -> DataFrame:
    """word_id, docs (sorted by document), n, max_w."""
    return vectors.groupBy("word_id").agg(F.array_sort(F.collect_list(F.struct("doc_id", "w"))).alias("docs"), F.count(F.lit(1)).alias("n"), F.max("w").alias("max_w"))


def rank(scores: DataFrame, n: int, digits: int = 9) -> DataFrame:
    """The top n documents of each query: query_id, doc_id, score, rank; ties go to the smaller document."""
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return scores.withColumn("score", F.round("score", digits)).withColumn("rank", F.row_number().over(w).cast("bigint")).filter(F.col("rank") <= n)


def wand(lists: list[tuple[np.ndarray, np.ndarray, float]], k: int) -> tuple[list[tuple[float, int]], int]:
    """Top k (score, document) of weighted lists (documents, scores, largest score), and how many documents were scored in full."""
    at, heap, scored = [0] * len(lists), [], 0
    while True:
        live = sorted((int(lists[i][0][at[i]]), i) for i in range(len(lists)) if at[i] < len(lists[i][0]))
        bar, bound, pivot = (heap[0][0] if len(heap) == k else -1.0), 0.0, None
        for j, (_, i) in enumerate(live):
            bound += lists[i][2]
            if bound >= bar - 1e-9:  # equal bounds may still win by the smaller id
                pivot = j
                break
        if pivot is None:
            break
        doc = live[pivot][0]
        if live[0][0] == doc:
            score = 0.0
            for d, i in live:
                if d == doc:
                    score += float(lists[i][1][at[i]])
                    at[i] += 1
            scored += 1
            item = (round(score, 9), -doc)
            if len(heap) < k:
                heapq.heappush(heap, item)
            elif item > heap[0]:
                heapq.heapreplace(heap, item)
        else:
            for d, i in live[:pivot]:
                if d < doc:
                    at[i] += int(np.searchsorted(lists[i][0][at[i] :], doc))
    return [(s, -d) for s, d in sorted(heap, reverse=True)], scored


def weak_and(queries: DataFrame, vectors: DataFrame, k: int, shards: int = 8) -> DataFrame:
    """query_id, doc_id, score, rank and scored (documents scored in full): Weak-AND in each document shard, then the best over shards."""
    q = queries.select(F.col("doc_id").alias("query_id"), "word_id", F.col("w").alias("qw"))
    parts = vectors.withColumn("shard", F.pmod(F.xxhash64("doc_id"), F.lit(shards)))
    lists = parts.join(q, "word_id").select("query_id", "shard", "word_id", "doc_id", (F.col("w") * F.col("qw")).alias("x"))

    def best(f: pd.DataFrame) -> pd.DataFrame:
        own = [(g["doc_id"].to_numpy(), g["x"].to_numpy(), float(g["x"].max())) for _, g in f.sort_values(["word_id", "doc_id"]).groupby("word_id", sort=False)]
        top, scored = wand(own, k)
        return pd.DataFrame({"query_id": f["query_id"].iloc[0], "doc_id": [d for _, d in top], "score": [s for s, _ in top], "scored": scored})

    got = lists.groupBy("query_id", "shard").applyInPandas(best, "query_id bigint, doc_id bigint, score double, scored bigint")
    return rank(got, k)


def as_lists(vectors: DataFrame) -> DataFrame:
    """doc_id, words, w: a row per sparse vector."""
    return vectors.groupBy("doc_id").agg(F.collect_list(F.struct("word_id", "w")).alias("x")).select("doc_id", F.col("x.word_id").alias("words"), F.col("x.w").alias("w"))


def search_blocks(queries: DataFrame, docs: DataFrame, k: int, query_block: int = 512, doc_block: int = 4096, digits: int = 9) -> DataFrame:
    """query_id, doc_id, score, rank: for each query its top k of all other docs, every pair scored; ties go to the smaller document.

    Both sides are rows of doc_id, words, w.  A task multiplies one block of queries and one of documents, so blocks grow in number, not in size.
    """
    nq, nd = (max(1, -(-df.count() // size)) for df, size in ((queries, query_block), (docs, doc_block)))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    q = queries.withColumn("qb", F.pmod(F.xxhash64("doc_id"), F.lit(nq)).cast("int")).withColumn("db", every(nd))
    d = docs.withColumn("db", F.pmod(F.xxhash64("doc_id"), F.lit(nd)).cast("int")).withColumn("qb", every(nq))

    # names of its own: queries may come from docs, and a cogroup takes equal columns of both sides for one
    q = q.select("qb", "db", F.col("doc_id").alias("query_id"), F.col("words").alias("q_words"), F.col("w").alias("q_w"))

    def best(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        a = a.rename(columns={"query_id": "doc_id", "q_words": "words", "q_w": "w"})
        out: dict = {"query_id": [], "doc_id": [], "score": []}
        if len(a) and len(b):
            dims = np.unique(np.concatenate([np.asarray(x) for x in a["words"]]))

            def matrix(f: pd.DataFrame) -> np.ndarray:
                m = np.zeros((len(f), len(dims)))
                for i, (x, w) in enumerate(zip(f["words"], f["w"], strict=True)):
                    x, w = np.asarray(x), np.asarray(w)
                    at = np.minimum(np.searchsorted(dims, x), len(dims) - 1)
                    ok = dims[at] == x
                    m[i, at[ok]] = w[ok]
                return m

            b = b.sort_values("doc_id")
            ids, scores = b["doc_id"].to_numpy(), np.round(matrix(a) @ matrix(b).T, digits)
            for own, row in zip(a["doc_id"], scores, strict=True):
                order = np.argsort(-row, kind="stable")[: k + 1]
                order = order[ids[order] != own][:k]
                out["query_id"] += [own] * len(order)
                out["doc_id"] += ids[order].tolist()
                out["score"] += row[order].tolist()
        return pd.DataFrame(out)

    got = q.groupBy("qb", "db").cogroup(d.groupBy("qb", "db")).applyInPandas(best, "query_id bigint, doc_id bigint, score double")
    return rank(got, k, digits)


def expand_query(vectors: DataFrame, features: DataFrame, mode: str = "mix", weight: float = 0.5) -> DataFrame:
    """Query vectors with topic words: doc_id, word_id, w (unit length).  replace: topic words alone; mix: a weighted sum."""
    f = features.select("doc_id", "word_id", F.col("p").alias("x"))
    norm = f.groupBy("doc_id").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    unit = f.join(norm, "doc_id").select("doc_id", "word_id", (F.col("x") / F.col("norm")).alias("w"))
    if mode == "replace":
        return unit
    both = vectors.select("doc_id", "word_id", (F.col("w") * (1 - weight)).alias("w")).unionByName(unit.select("doc_id", "word_id", (F.col("w") * weight).alias("w")))
    s = both.groupBy("doc_id", "word_id").agg(F.sum("w").alias("w"))
    n = s.groupBy("doc_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return s.join(n, "doc_id").select("doc_id", "word_id", (F.col("w") / F.col("norm")).alias("w"))


def mean_average_precision(run: DataFrame, qrels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """queries, map: run (query_id, doc_id, rank) against qrels (query_id, doc_id, rel); queries without relevant documents are left out."""
    rel = qrels.filter(F.col("rel") >= threshold).select("query_id", "doc_id").distinct()
    n = rel.groupBy("query_id").agg(F.count(F.lit(1)).alias("relevant"))
    hits = run.join(rel, ["query_id", "doc_id"])
    at = F.row_number().over(Window.partitionBy("query_id").orderBy("rank"))
    ap = hits.withColumn("prec", at / F.col("rank")).groupBy("query_id").agg(F.sum("prec").alias("s"))
    return n.join(ap, "query_id", "left").agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg(F.coalesce("s", F.lit(0.0)) / F.col("relevant")), 6).alias("map"))
