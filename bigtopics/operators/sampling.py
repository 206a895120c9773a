"""Gibbs samplers: the conditional of one token, a relational sweep, and array kernels for blocks of tokens."""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from dataclasses import dataclass
from itertools import accumulate
from operator import mul

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.rand import uniform
from ..jvm.sampler import sampler


def bucket_masses(tokens_z: DataFrame, theta: DataFrame, phi: DataFrame, psi: DataFrame, alpha: float, beta: float, vocab_size: int) -> DataFrame:
    """Prior, document and word mass of each token's conditional, its own label left out: doc_id, pos, prior_mass, doc_mass, word_mass.

    The three add up to the dense conditional's total (A.1); only the token's own topic differs from cached sums.
    """
    vb = beta * vocab_size
    tot = F.broadcast(psi.select("topic", F.col("n").alias("total")))
    base = F.broadcast(psi.agg(F.sum(F.lit(alpha * beta) / (F.col("n") + vb)).alias("s_all")))
    own = tokens_z.join(tot, tokens_z["z"] == tot["topic"]).select(tokens_z["*"], F.col("total").alias("own_total"))
    s = own.crossJoin(base).withColumn("prior_mass", F.col("s_all") - F.lit(alpha * beta) / (F.col("own_total") + vb) + F.lit(alpha * beta) / (F.col("own_total") - 1 + vb))
    minus = lambda c: F.col(c) - F.when(F.col("topic") == F.col("z"), 1).otherwise(0)
    th = theta.select("doc_id", "topic", F.col("n").alias("th"))
    d = s.join(th, "doc_id").join(tot, "topic").groupBy("doc_id", "pos", "word_id", "z", "prior_mass").agg(F.sum(minus("th") * beta / (minus("total") + vb)).alias("doc_mass"))
    w = d.join(phi.select("word_id", "topic", F.col("n").alias("f")), "word_id").join(th, ["doc_id", "topic"], "left").na.fill(0, ["th"]).join(tot, "topic")
    mass = (F.lit(alpha) + minus("th")) * minus("f") / (minus("total") + vb)
    return w.groupBy("doc_id", "pos", "prior_mass", "doc_mass").agg(F.sum(mass).alias("word_mass"))


def snapshot_sweep(tokens_z: DataFrame, theta: DataFrame, phi: DataFrame, psi: DataFrame, topics: int, alpha: float, beta: float, vocab_size: int, iteration: int = 1, seed: int = 7) -> DataFrame:
    """One sweep against counts frozen at its start: new z of each token, drawn with portable uniforms.

    All topics are scored, so it suits small topic counts; kernels are the scale path.
    """
    vb = beta * vocab_size
    spread = tokens_z.withColumn("topic", F.explode(F.sequence(F.lit(0), F.lit(topics - 1))))
    same = F.when(F.col("topic") == F.col("z"), 1).otherwise(0)
    j = spread.join(theta.select("doc_id", "topic", F.col("n").alias("th")), ["doc_id", "topic"], "left").join(phi.select("word_id", "topic", F.col("n").alias("f")), ["word_id", "topic"], "left").join(F.broadcast(psi.select("topic", F.col("n").alias("total"))), "topic", "left").na.fill(0, ["th", "f", "total"])
    weight = (F.col("th") - same + alpha) * (F.col("f") - same + beta) / (F.col("total") - same + vb)
    per = Window.partitionBy("doc_id", "pos")
    run = j.select("doc_id", "pos", "word_id", "topic", F.sum(weight).over(per.orderBy("topic")).alias("upto"), F.sum(weight).over(per).alias("whole"))
    draw = uniform(iteration, "doc_id", "pos", seed=seed)
    return run.filter((F.col("upto") > draw * F.col("whole")) | (F.col("topic") == topics - 1)).groupBy("doc_id", "pos", "word_id").agg(F.min("topic").alias("z"))


# --- kernels ----------------------------------------------------------------------------------------


class Rows:
    """Sparse rows of counts: each row's topics, ascending, and their counts (entries that fell to zero may stay).

    All rows lie in one array of topics and one of counts; a row that outgrows its
    place moves to the end with twice the room.
    """

    def __init__(self, row: np.ndarray, topic: np.ndarray, n: np.ndarray, rows: int):
        order = np.lexsort((topic, row))
        size = np.bincount(row, minlength=rows)[:rows]
        self.size, self.room = size.tolist(), size.tolist()
        self.at = (np.cumsum(size) - size).tolist()
        self.end = len(row)
        self.topic, self.n = topic[order].astype(np.int64), n[order].astype(float)

    @classmethod
    def of(cls, table: np.ndarray | Rows) -> Rows:
        if isinstance(table, Rows):
            return table
        row, topic = np.nonzero(table)
        return cls(row, topic, table[row, topic], len(table))

    def dense(self, topics: int) -> np.ndarray:
        out = np.zeros((len(self.size), topics))
        for r in range(len(self.size)):
            t, n = self.row(r)
            out[r, t] = n
        return out

    def row(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        """Topics and counts of a row, as views."""
        lo = self.at[r]
        hi = lo + self.size[r]
        return self.topic[lo:hi], self.n[lo:hi]

    def add(self, r: int, k: int, by: float) -> None:
        lo, size = self.at[r], self.size[r]
        t = self.topic[lo : lo + size]
        i = int(t.searchsorted(k))
        if i < size and t[i] == k:
            self.n[lo + i] += by
            return
        if size == self.room[r]:
            lo = self._move(r)
        for x, new in ((self.topic, k), (self.n, by)):
            x[lo + i + 1 : lo + size + 1] = x[lo + i : lo + size].copy()
            x[lo + i] = new
        self.size[r] = size + 1

    def _move(self, r: int) -> int:
        lo, size, room = self.at[r], self.size[r], max(2, 2 * self.room[r])
        if self.end + room > len(self.topic):
            more = max(room, len(self.topic) // 2, 64)
            self.topic, self.n = (np.concatenate([x, np.zeros(more, x.dtype)]) for x in (self.topic, self.n))
        new = self.end
        for x in (self.topic, self.n):
            x[new : new + size] = x[lo : lo + size]
        self.at[r], self.room[r], self.end = new, room, new + room
        return new


class Table(Rows):
    """The same over a full table of rows x topics, changed in place: for few topics or a full copy of a model."""

    def __init__(self, table: np.ndarray):
        self.table, self.every = table, np.arange(table.shape[1])

    def dense(self, topics: int) -> np.ndarray:
        return self.table

    def row(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        return self.every, self.table[r]

    def add(self, r: int, k: int, by: float) -> None:
        self.table[r, k] += by


class Lists(Table):
    """The same over Python lists, made of another table's rows when first used: for few topics, where calls on small arrays cost more than the sums."""

    def __init__(self, source: np.ndarray | Rows, topics: int):
        self.source, self.topics, self.lists = source, topics, {}

    @staticmethod
    def suits(rows: int, topics: int) -> bool:
        """Whether all rows as lists stay within some 50 MB."""
        return topics <= 96 and rows * (topics + 16) <= 1 << 22

    def dense(self, topics: int) -> np.ndarray:
        out = np.array(self.source.dense(topics) if isinstance(self.source, Rows) else self.source, float)
        for r, x in self.lists.items():
            out[r] = x
        return out

    def row(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        return np.arange(self.topics), np.array(self.list(r), float)

    def add(self, r: int, k: int, by: float) -> None:
        self.list(r)[k] += int(by)

    def list(self, r: int) -> list[int]:
        got = self.lists.get(r)
        if got is None:
            got = self.lists[r] = [0] * self.topics
            if isinstance(self.source, Rows):
                t, n = self.source.row(r)
                for k, x in zip(t.tolist(), n.astype(np.int64).tolist(), strict=True):
                    got[k] = x
            else:
                got[:] = self.source[r].astype(np.int64).tolist()
        return got


@dataclass
class Block:
    """Tokens of a block, in order of (doc, pos), with local counts that already hold them."""

    docs: np.ndarray  # local document of each token
    words: np.ndarray  # local word of each token
    z: np.ndarray
    theta: np.ndarray | Rows  # documents x topics
    phi: np.ndarray | Rows  # words x topics
    psi: np.ndarray


def dense_probabilities(theta_d: np.ndarray, phi_w: np.ndarray, psi: np.ndarray, alpha: np.ndarray, beta: float, vocab_size: int) -> np.ndarray:
    """Unnormalised conditional over topics, own token already taken out."""
    return (theta_d + alpha) * (phi_w + beta) / (psi + beta * vocab_size)


def sample_dense(b: Block, alpha: np.ndarray, beta: float, vocab_size: int, u: np.ndarray) -> np.ndarray:
    """New labels by the dense conditional with counts updated at once."""
    z = b.z.copy()
    theta, phi = (x.dense(len(alpha)) if isinstance(x, Rows) else x for x in (b.theta, b.phi))
    for i in range(len(z)):
        d, w, k = b.docs[i], b.words[i], z[i]
        theta[d, k] -= 1
        phi[w, k] -= 1
        b.psi[k] -= 1
        c = np.cumsum(dense_probabilities(theta[d], phi[w], b.psi, alpha, beta, vocab_size))
        k = min(int(np.searchsorted(c, u[i] * c[-1], "right")), len(c) - 1)
        z[i] = k
        theta[d, k] += 1
        phi[w, k] += 1
        b.psi[k] += 1
    return z


def sample_buckets(b: Block, alpha: np.ndarray, beta: float, vocab_size: int, u: np.ndarray) -> np.ndarray:
    """The same draw by three masses: word, document, prior; the first two visit the topics of the word and of the document alone.

    Memory is that of the non-zero counts and of one document's vector over topics; all topics are visited only when the prior's mass is hit.
    """
    if isinstance(b.phi, Lists):
        return _sample_lists(b, alpha, beta, vocab_size, u)
    z, vb, psi = b.z.copy(), beta * vocab_size, b.psi
    theta, phi = Rows.of(b.theta), Rows.of(b.phi)
    here, mine = -1, np.zeros(len(alpha))
    prior = float((alpha * beta / (psi + vb)).sum())
    for i in range(len(z)):
        d, w, k = b.docs[i], b.words[i], z[i]
        if d != here:
            if here >= 0:
                mine[theta.row(here)[0]] = 0.0
            own, n = theta.row(d)
            mine[own] = n
            here = d
        prior -= alpha[k] * beta / (psi[k] + vb)
        theta.add(d, k, -1.0)
        phi.add(w, k, -1.0)
        mine[k] -= 1
        psi[k] -= 1
        prior += alpha[k] * beta / (psi[k] + vb)
        (kw, nw), (kd, nd) = phi.row(w), theta.row(d)
        mw = (alpha[kw] + mine[kw]) * nw / (psi[kw] + vb)
        md = nd * beta / (psi[kd] + vb)
        sw, sd = float(mw.sum()), float(md.sum())
        x = u[i] * (sw + sd + prior)
        if x < sw:
            at, c = kw, np.cumsum(mw)
        elif x < sw + sd:
            at, c, x = kd, np.cumsum(md), x - sw
        else:
            at, c, x = np.arange(len(alpha)), np.cumsum(alpha * beta / (psi + vb)), x - sw - sd
        k = int(at[min(int(np.searchsorted(c, x, "right")), len(c) - 1)])
        z[i] = k
        prior -= alpha[k] * beta / (psi[k] + vb)
        theta.add(d, k, 1.0)
        phi.add(w, k, 1.0)
        mine[k] += 1
        psi[k] += 1
        prior += alpha[k] * beta / (psi[k] + vb)
    return z


def _sample_lists(b: Block, alpha: np.ndarray, beta: float, vocab_size: int, u: np.ndarray) -> np.ndarray:
    """``sample_buckets`` over lists of few topics: the same three masses and draws.  Document counts are read and not written back."""
    vb, topics, a = beta * vocab_size, len(alpha), alpha.tolist()
    psi, theta, phi, z = b.psi.tolist(), Lists(b.theta.table if isinstance(b.theta, Table) and not isinstance(b.theta, Lists) else b.theta, topics), b.phi, []
    share = [1 / (n + vb) for n in psi]
    ab = [x * beta for x in a]
    prior, here = sum(map(mul, ab, share)), None
    for d, w, k, x in zip(b.docs.tolist(), b.words.tolist(), b.z.tolist(), u.tolist(), strict=True):
        if d != here:
            here, mine = d, theta.list(d)
            near = [(p + n) * q for p, n, q in zip(a, mine, share, strict=True)]  # prior and document counts by topic totals
        row = phi.lists.get(w) or phi.list(w)
        row[k] -= 1
        mine[k] -= 1
        psi[k] -= 1
        q = 1 / (psi[k] + vb)
        prior += ab[k] * (q - share[k])
        share[k] = q
        near[k] = (a[k] + mine[k]) * q
        c = list(accumulate(map(mul, near, row)))
        sw, sd = c[-1], beta * sum(map(mul, mine, share))
        x *= sw + sd + prior
        if x >= sw:
            x -= sw
            if x < sd:
                c = list(accumulate(n * q * beta for n, q in zip(mine, share, strict=True)))
            else:
                x -= sd
                c = list(accumulate(map(mul, ab, share)))
        k = bisect_right(c, x)
        if k == topics:  # by rounding: the last topic with mass
            k = bisect_left(c, c[-1])
        z.append(k)
        row[k] += 1
        mine[k] += 1
        psi[k] += 1
        q = 1 / (psi[k] + vb)
        prior += ab[k] * (q - share[k])
        share[k] = q
        near[k] = (a[k] + mine[k]) * q
    b.psi[:] = psi
    return np.array(z, b.z.dtype)


KERNELS = {"dense": sample_dense, "buckets": sample_buckets}


def block_draws(seed: int, iteration: int, key: tuple[int, ...]) -> np.random.Generator:
    """Draws of a block: a counter-based stream keyed by logical ids, so a retried task repeats itself."""
    return np.random.Generator(np.random.Philox(key=block_key(seed, iteration, key)))


def block_key(seed: int, iteration: int, key: tuple[int, ...]) -> np.ndarray:
    return np.random.SeedSequence([seed, iteration, *(k + 1 for k in key)]).generate_state(2, np.uint64)


def block_uniforms(seed: int, iteration: int, key: tuple[int, ...], n: int) -> np.ndarray:
    return block_draws(seed, iteration, key).random(n)


def document_pieces(docs: np.ndarray, size: int = 1 << 16) -> list[tuple[int, int]]:
    """Ranges of tokens of whole documents, of at least ``size`` tokens but for the last; one range if documents are scattered."""
    if (np.diff(docs) < 0).any():
        return [(0, len(docs))]
    ends = np.flatnonzero(np.diff(docs, append=docs[-1:] + 1)) + 1
    cuts = [0]
    for e in ends[np.searchsorted(ends, np.arange(size, len(docs), size))].tolist() if len(docs) else []:
        if e >= cuts[-1] + size:
            cuts.append(e)
    return [(lo, hi) for lo, hi in zip(cuts, [*cuts[1:], len(docs)], strict=True) if hi > lo]


def train_sequential(docs: np.ndarray, words: np.ndarray, topics: int, vocab_size: int, *, alpha: float = 0.1, beta: float = 0.01, iterations: int = 50, kernel: str = "buckets", seed: int = 7, spark: SparkSession | None = None) -> tuple[np.ndarray, list[float]]:
    """One machine's trainer, the reference answer: labels and the joint log-likelihood after each iteration.

    It holds the corpus, the model and the document counts of one piece.  With a session the
    pieces are sampled in the driver's JVM, which then holds the model; the labels are the same.
    """
    rng = np.random.default_rng(seed)
    z = rng.integers(0, topics, len(docs))
    a, trace, pieces = np.full(topics, alpha), [], document_pieces(docs)
    if spark is not None and kernel == "buckets" and (np.diff(docs) >= 0).all():
        return _train_in_jvm(spark, docs, words, z, a, beta, vocab_size, iterations, seed, pieces)
    for it in range(iterations):
        phi, psi = (np.bincount(x, minlength=m).astype(float) for x, m in ((words * topics + z, vocab_size * topics), (z, topics)))
        phi = phi.reshape(-1, topics)
        phi, u, new = Lists(phi, topics) if kernel == "buckets" and Lists.suits(vocab_size, topics) else Table(phi), block_uniforms(seed, it, (0,), len(z)), z.copy()
        for lo, hi in pieces:
            own, d = np.unique(docs[lo:hi], return_inverse=True)
            theta = np.bincount(d * topics + z[lo:hi], minlength=len(own) * topics).reshape(-1, topics).astype(float)
            new[lo:hi] = KERNELS[kernel](Block(d, words[lo:hi], z[lo:hi], theta, phi, psi), a, beta, vocab_size, u[lo:hi])
        z = new
        trace.append(joint_ll(docs, words, z, topics, vocab_size, a, beta))
    return z, trace


def _train_in_jvm(spark: SparkSession, docs: np.ndarray, words: np.ndarray, z: np.ndarray, a: np.ndarray, beta: float, vocab_size: int, iterations: int, seed: int, pieces: list[tuple[int, int]]) -> tuple[np.ndarray, list[float]]:
    s, topics, trace = sampler(spark, a, beta, vocab_size), len(a), []
    s.open(np.bincount(z, minlength=topics).astype("<f8").tobytes())
    packed = lambda x, lo, hi, t="<i4": x[lo:hi].astype(t).tobytes()
    own, n = np.unique(words * topics + z, return_counts=True)
    for lo in range(0, len(own), 1 << 16):
        w, k = np.divmod(own[lo : lo + (1 << 16)], topics)
        s.model(w.astype("<i4").tobytes(), k.astype("<i4").tobytes(), packed(n, lo, lo + (1 << 16), "<f8"))
    del own, n
    for it in range(iterations):
        s.draws(block_key(seed, it, (0,)).astype("<u8").tobytes())
        new = np.empty_like(z)
        for lo, hi in pieces:
            ends = np.flatnonzero(np.diff(docs[lo:hi], append=docs[hi - 1] + 1)) + 1
            got = s.piece(np.diff(ends, prepend=0).astype("<i4").tobytes(), packed(words, lo, hi), packed(z, lo, hi))
            new[lo:hi] = np.frombuffer(got, "<i4")
        z = new
        trace.append(joint_ll(docs, words, z, topics, vocab_size, a, beta))
    return z, trace


def count_arrays(docs: np.ndarray, words: np.ndarray, z: np.ndarray, topics: int, vocab_size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    theta = np.bincount(docs * topics + z, minlength=(int(docs.max(initial=-1)) + 1) * topics).reshape(-1, topics).astype(float)
    phi = np.bincount(words * topics + z, minlength=vocab_size * topics).reshape(-1, topics).astype(float)
    return theta, phi, np.bincount(z, minlength=topics).astype(float)


def _lg(n: np.ndarray, a: float) -> float:
    """Sum of lgamma(n + a) - lgamma(a) over whole counts; equal counts are summed once."""
    from math import lgamma

    times = np.bincount(n)
    return float(sum(times[c] * (lgamma(c + a) - lgamma(a)) for c in np.flatnonzero(times).tolist() if c))


def joint_ll(docs: np.ndarray, words: np.ndarray, z: np.ndarray, topics: int, vocab_size: int, alpha: np.ndarray, beta: float) -> float:
    """Collapsed joint log-likelihood from arrays, topic by topic."""
    out = -_lg(np.bincount(docs), float(alpha.sum())) - _lg(np.bincount(z, minlength=topics), beta * vocab_size)
    for k in range(topics):
        mine = z == k
        out += _lg(np.bincount(docs[mine]), float(alpha[k])) + _lg(np.bincount(words[mine]), beta)
    return out
