"""Topics of unseen queries: pruned and full greedy ascent, several starts, and the sampling baseline.

A query meets its words' model rows by a join on word; per-topic vectors
(background and prior, length K) go along with the code.  Kernels see one packed
query at a time, so their cost does not depend on the corpus.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .placement import ranked_by_tf


def best_prior_topic(phi: DataFrame, psi: DataFrame, alpha: DataFrame, beta: float, vocab_size: int) -> DataFrame:
    """word_id, best_topic, best_score: the topic with the largest phi * alpha of each word; ties go to the smaller topic.

    Outside a word's support only the topic of the largest background score can win, so one candidate per word is added.
    """
    den = F.col("total") + F.lit(beta * vocab_size)
    topics = psi.select("topic", F.col("n").alias("total")).join(alpha, "topic")
    back = topics.select((F.lit(beta) / den * F.col("alpha")).alias("score"), "topic")
    seen = phi.join(F.broadcast(topics), "topic").select("word_id", "topic", ((F.col("n") + beta) / den * F.col("alpha")).alias("score"))
    both = seen.unionByName(_outside(phi, back))
    best = both.groupBy("word_id").agg(F.max(F.struct("score", (-F.col("topic")).alias("t"))).alias("b"))
    return best.select("word_id", (-F.col("b.t")).cast("int").alias("best_topic"), F.col("b.score").alias("best_score"))


def _outside(phi: DataFrame, back: DataFrame) -> DataFrame:
    """For each word the best background topic that is not in its support, from the K background scores in descending order."""
    order = back.agg(F.transform(F.sort_array(F.collect_list(F.struct("score", (-F.col("topic")).alias("t"))), asc=False), lambda x: F.struct((-x["t"]).cast("int").alias("topic"), x["score"].alias("score"))).alias("ranked"))
    support = phi.groupBy("word_id").agg(F.collect_set("topic").alias("own")).crossJoin(F.broadcast(order))  # one row of K entries
    first = F.get(F.filter(F.slice("ranked", F.lit(1), F.size("own") + 1), lambda x: ~F.array_contains("own", x["topic"])), F.lit(0))
    return support.withColumn("x", first).filter("x is not null").select("word_id", F.col("x.topic").alias("topic"), F.col("x.score").alias("score"))


def packed_rows(phi: DataFrame) -> DataFrame:
    """word_id, topics, counts: one row per word."""
    rows = phi.groupBy("word_id").agg(F.array_sort(F.collect_list(F.struct("topic", "n"))).alias("r"))
    return rows.select("word_id", F.transform("r", lambda x: x["topic"]).alias("topics"), F.transform("r", lambda x: x["n"]).alias("counts"))


def packed_queries(tokens: DataFrame, phi: DataFrame, r_best: DataFrame) -> DataFrame:
    """doc_id and, per place, the word's model row and best prior topic; a word that the model lacks has an empty row and topic -1."""
    model = packed_rows(phi).join(r_best.select("word_id", "best_topic"), "word_id")
    rows = tokens.join(model, "word_id", "left").withColumn("best_topic", F.coalesce("best_topic", F.lit(-1)))
    rows = rows.withColumn("topics", F.coalesce("topics", F.array().cast(model.schema["topics"].dataType))).withColumn("counts", F.coalesce("counts", F.array().cast(model.schema["counts"].dataType)))
    q = rows.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("pos", "word_id", "best_topic", "topics", "counts"))).alias("q"))
    return q.select("doc_id", *(F.col("q")[c].alias(c) for c in ("pos", "word_id", "best_topic", "topics", "counts")))


def ascend(rows: list[tuple[np.ndarray, np.ndarray]], best: np.ndarray, psi: np.ndarray, alpha: np.ndarray, beta: float, vocab_size: int, *, pruned: bool = True, start: np.ndarray | None = None, exclude_self: bool = True, max_sweeps: int = 20) -> tuple[np.ndarray, int]:
    """Labels by coordinate ascent and the number of sweeps.

    Pruned: candidates are the word's best prior topic and the query's own topics; the maximum is the same as over all.
    """
    z = np.array(best if start is None else start, np.int64)
    sweep_once = _sweep_pruned if pruned else _sweep_full
    theta = dict(zip(*(x.tolist() for x in np.unique(z, return_counts=True)), strict=True)) if pruned else np.bincount(z, minlength=len(psi)).astype(float)
    for sweep in range(1, max_sweeps + 1):
        if not sweep_once(rows, best, z, theta, psi, alpha, beta, beta * vocab_size, exclude_self):
            break
    return z, sweep


#: Topics up to which, and queries of a batch from which, queries of one length are solved together over full vectors.
_TOGETHER = 64


def ascend_together(best: np.ndarray, counts: np.ndarray, psi: np.ndarray, alpha: np.ndarray, beta: float, vocab_size: int, *, pruned: bool = True, start: np.ndarray | None = None, exclude_self: bool = True, max_sweeps: int = 20) -> np.ndarray:
    """The labels of ``ascend`` for many queries of one length: best and start are queries x places, counts queries x places x topics."""
    z, den, topics = (best if start is None else start).astype(np.int64), psi + beta * vocab_size, np.arange(len(psi))
    theta = (z[:, :, None] == topics).sum(1).astype(float)
    live = np.arange(len(z))
    for _ in range(max_sweeps):
        moved = np.zeros(len(live), bool)
        for i in range(z.shape[1]):
            old = z[live, i]
            theta[live, old] -= exclude_self
            own = theta[live]
            score = (counts[live, i] + beta) / den * (own + alpha)
            if pruned:
                score[(own <= 0) & (topics != best[live, i, None])] = -1.0
            new = score.argmax(1)  # the first of equals: the smallest topic
            theta[live, old] -= not exclude_self
            theta[live, new] += 1
            z[live, i] = new
            moved |= new != old
        live = live[moved]
        if not len(live):
            break
    return z


def _by_length(f: pd.DataFrame, topics: int, fallback: int, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Rows of f of one length, in slices of at most ``most`` counts: their places in f, best topics, counts (rows x places x topics) and sizes of the words' supports."""
    size = f["best_topic"].map(len).to_numpy()
    for length in np.unique(size[size > 0]).tolist():
        same, step = np.flatnonzero(size == length), max(1, most // (length * topics))
        for lo in range(0, len(same), step):
            rows = same[lo : lo + step]
            part = f.iloc[rows]
            best = np.stack([np.asarray(b, np.int64) for b in part["best_topic"]])
            ts, ns = ([x for q in part[c] for x in q] for c in ("topics", "counts"))
            held = np.array([len(t) for t in ts])
            cell = np.repeat(np.arange(len(ts)) * topics, held) + np.concatenate(ts).astype(np.int64)
            table = np.zeros(len(ts) * topics)
            table[cell] = np.concatenate(ns)
            yield rows, np.where(best < 0, fallback, best), table.reshape(len(rows), length, topics), held.reshape(best.shape)


def _in_order(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    at, topic, n = (np.concatenate([np.empty(0, t), *x]) for x, t in zip(zip(*parts, strict=True) if parts else ((), (), ()), (np.int64, np.int64, float), strict=True))
    order = np.argsort(at, kind="stable")
    return at[order], topic[order], n[order]


def _random_starts(counts: np.ndarray, best: np.ndarray, held: np.ndarray, rngs: list[np.random.Generator]) -> np.ndarray:
    """For each place a topic of the word's support by the query's own draws; the best prior topic for a word without one."""
    draws = np.array([[int(g.integers(h)) if h else -1 for h in own] for g, own in zip(rngs, held.tolist(), strict=True)])
    nth = np.argmax(np.cumsum(counts > 0, 2) == draws[:, :, None] + 1, 2)
    return np.where(draws < 0, best, nth)


def _solve_together(f: pd.DataFrame, psi: np.ndarray, alpha: np.ndarray, beta: float, vocab_size: int, fallback: int, most: int = 1 << 21, trials: int = 1, seed: int = 7, **options) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, topic and count (mean over trials) of the labels of all queries of a batch; queries of a length go in slices of at most ``most`` counts."""
    k, out = len(psi), []
    for rows, best, counts, held in _by_length(f, k, fallback, most):
        rngs = [_seeded(seed, d) for d in f["doc_id"].iloc[rows]] if trials > 1 else []
        z = [ascend_together(best, counts, psi, alpha, beta, vocab_size, start=_random_starts(counts, best, held, rngs) if t else None, **options) for t in range(trials)]
        code, times = np.unique(rows[:, None] * k + np.concatenate(z, 1), return_counts=True)
        out.append((code // k, code % k, times / trials))
    return _in_order(out)


def _sample_together(f: pd.DataFrame, psi: np.ndarray, alpha: np.ndarray, beta: float, vocab_size: int, fallback: int, most: int = 1 << 21, seed: int = 7, sweeps: int = 30, burn_in: int = 10) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, topic and mean count of ``sample_query`` for all queries of a batch, by the same draws of each query."""
    den, k, out = psi + beta * vocab_size, len(psi), []
    for rows, best, counts, _ in _by_length(f, k, fallback, most):
        d, n = best.shape
        p, every = (counts + beta) / den, np.arange(d)
        z, u = np.empty((d, n), np.int64), np.empty((d, sweeps, n))
        for i, doc in enumerate(f["doc_id"].iloc[rows]):
            rng = _seeded(seed, doc)
            z[i], u[i] = rng.integers(0, k, n), rng.random((sweeps, n))
        theta, total = np.bincount((every[:, None] * k + z).ravel(), minlength=d * k).reshape(d, k).astype(float), np.zeros((d, k))
        for s in range(sweeps):
            for i in range(n):
                theta[every, z[:, i]] -= 1
                c = np.cumsum(p[:, i] * (theta + alpha), 1)
                z[:, i] = np.minimum((c <= (u[:, s, i] * c[:, -1])[:, None]).sum(1), k - 1)
                theta[every, z[:, i]] += 1
            if s >= burn_in:
                total += theta
        total /= max(1, sweeps - burn_in)
        at, topic = np.nonzero(total)
        out.append((rows[at], topic, total[at, topic]))
    return _in_order(out)


def _seeded(seed: int, doc) -> np.random.Generator:
    """A query's own stream of draws, keyed by its id."""
    return np.random.Generator(np.random.Philox(np.random.SeedSequence([seed, 1 << 64 if doc is None or doc is pd.NA or doc != doc else int(doc) % (1 << 64)])))


def _sweep_full(rows: list[tuple[np.ndarray, np.ndarray]], best: np.ndarray, z: np.ndarray, theta: np.ndarray, psi: np.ndarray, alpha: np.ndarray, beta: float, vb: float, exclude_self: bool) -> bool:
    """Scores all topics for each place, in order; True if a label moved."""
    moved, den = False, psi + vb
    for i, (topics, counts) in enumerate(rows):
        old = z[i]
        theta[old] -= exclude_self
        f = np.zeros(len(psi))
        f[topics] = counts
        z[i] = int(np.argmax((f + beta) / den * (theta + alpha)))  # the first of equals: the smallest topic
        theta[old] -= not exclude_self
        theta[z[i]] += 1
        moved |= bool(z[i] != old)
    return moved


def _sweep_pruned(rows: list[tuple[np.ndarray, np.ndarray]], best: np.ndarray, z: np.ndarray, theta: dict[int, int], psi: np.ndarray, alpha: np.ndarray, beta: float, vb: float, exclude_self: bool) -> bool:
    """Scores the query's own topics and the word's best prior topic; nothing here grows with the number of topics."""
    moved = False
    for i, (topics, counts) in enumerate(rows):
        old = int(z[i])
        theta[old] -= exclude_self
        new, top = old, -1.0
        for k in sorted({*(k for k, n in theta.items() if n), int(best[i])}):
            at = int(topics.searchsorted(k))
            f = counts[at] if at < len(topics) and topics[at] == k else 0.0
            score = (f + beta) / (psi[k] + vb) * (theta.get(k, 0) + alpha[k])
            if score > top:  # of equals the smallest topic stays
                new, top = k, score
        theta[old] -= not exclude_self
        theta[new] = theta.get(new, 0) + 1
        z[i] = new
        moved |= new != old
    return moved


def sample_query(rows: list[tuple[np.ndarray, np.ndarray]], psi: np.ndarray, alpha: np.ndarray, beta: float, vocab_size: int, rng: np.random.Generator, *, sweeps: int = 30, burn_in: int = 10) -> np.ndarray:
    """Mean topic counts of a query over Gibbs sweeps with a fixed model."""
    den, n = psi + beta * vocab_size, len(rows)
    p = np.full((n, len(psi)), beta)
    for i, (t, c) in enumerate(rows):
        p[i, t] += c
    p /= den
    z = rng.integers(0, len(psi), n)
    theta, total = np.bincount(z, minlength=len(psi)).astype(float), np.zeros(len(psi))
    for s in range(sweeps):
        u = rng.random(n)
        for i in range(n):
            theta[z[i]] -= 1
            c = np.cumsum(p[i] * (theta + alpha))
            z[i] = min(int(np.searchsorted(c, u[i] * c[-1], "right")), len(c) - 1)
            theta[z[i]] += 1
        if s >= burn_in:
            total += theta
    return total / max(1, sweeps - burn_in)


def predict(queries: DataFrame, psi: list[float], alpha: list[float], beta: float, vocab_size: int, *, method: str = "pruned", trials: int = 1, seed: int = 7, timed: bool = False, **options) -> DataFrame:
    """doc_id, topic, n: topic counts of packed queries (mean over trials or sweeps).

    method: pruned, full (greedy ascent) or sampling.  timed: instead a row per
    batch, queries and the seconds its kernel took on its core.
    """
    totals, prior = np.array(psi, float), np.array(alpha, float)
    fallback = int(np.argmax(prior / (totals + beta * vocab_size))) if len(totals) else 0  # of words that the model lacks

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        if method == "sampling" or (len(totals) <= _TOGETHER and len(f) >= _TOGETHER):
            if method == "sampling":
                row, topic, share = _sample_together(f, totals, prior, beta, vocab_size, fallback, seed=seed, **options)
            else:
                row, topic, share = _solve_together(f, totals, prior, beta, vocab_size, fallback, trials=trials, seed=seed, pruned=method == "pruned", **options)
            return pd.DataFrame({"doc_id": f["doc_id"].astype("Int64").iloc[row].reset_index(drop=True), "topic": topic.astype(np.int32), "n": share})
        docs, at, n = [pd.array([], dtype="Int64")], [np.empty(0, np.int32)], [np.empty(0)]
        for doc, best, topics, counts in zip(f["doc_id"], f["best_topic"], f["topics"], f["counts"], strict=True):
            rows = [(np.asarray(t, np.int64), np.asarray(c, float)) for t, c in zip(topics, counts, strict=True)]
            best = np.where(np.asarray(best) < 0, fallback, np.asarray(best))
            if trials > 1:
                rng = _seeded(seed, doc)
            labels = []
            for t in range(trials):
                start = None if t == 0 else np.array([r[0][int(rng.integers(len(r[0])))] if len(r[0]) else b for r, b in zip(rows, best, strict=True)])
                labels.append(ascend(rows, best, totals, prior, beta, vocab_size, pruned=method == "pruned", start=start, **options)[0])
            found, times = np.unique(np.concatenate(labels), return_counts=True)
            docs.append(pd.array([None if doc is None or doc != doc else int(doc)] * len(found), dtype="Int64"))
            at.append(found.astype(np.int32))
            n.append(times / trials)
        return pd.DataFrame({"doc_id": pd.concat([pd.Series(x) for x in docs], ignore_index=True), "topic": np.concatenate(at), "n": np.concatenate(n)})

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            begun = time.perf_counter()
            done = solve(f)
            yield pd.DataFrame({"queries": [len(f)], "seconds": [time.perf_counter() - begun]}) if timed else done

    return queries.mapInPandas(run, "queries bigint, seconds double" if timed else "doc_id bigint, topic int, n double")


def trial_average(trials: DataFrame) -> DataFrame:
    """doc_id, topic, p from doc_id, trial, topic, p; a topic absent from a trial counts as 0."""
    n = trials.groupBy("doc_id").agg(F.count_distinct("trial").alias("t"))
    return trials.groupBy("doc_id", "topic").agg(F.sum("p").alias("s")).join(n, "doc_id").select("doc_id", "topic", F.round(F.col("s") / F.col("t"), 9).alias("p"))


def cache_curve(vocab: DataFrame, budgets: list[int], row_bytes: int = 64) -> DataFrame:
    """budget, pinned words, hit_ratio: the most frequent words that fit, and the share of look-ups they answer."""
    ranked = ranked_by_tf(vocab)
    total = vocab.agg(F.sum("tf").alias("all"))
    b = vocab.sparkSession.createDataFrame([(x,) for x in budgets], "budget bigint")
    fits = ranked.join(F.broadcast(b), (F.col("rank") + 1) * row_bytes <= F.col("budget"))
    got = fits.groupBy("budget").agg(F.count(F.lit(1)).alias("pinned"), F.sum("tf").alias("hits"))
    return b.join(got, "budget", "left").crossJoin(F.broadcast(total)).select("budget", F.coalesce("pinned", F.lit(0)).cast("bigint").alias("pinned"), F.round(F.coalesce("hits", F.lit(0)) / F.col("all"), 6).alias("hit_ratio"))
