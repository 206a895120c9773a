"""Trainers: the grid of model and data shards with its synchronisation modes, and the replicated rival."""

from __future__ import annotations

import json
import time
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.accumulators import Accumulator
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, IntegerType, LongType, StructField, StructType

from ..functions.rand import uniform
from ..jvm.sampler import packer, sampled, sampler, unpacker
from ..operators.baselines import ModelTooLarge
from ..operators.counts import count_doc_topic, count_topic, count_word_topic
from ..operators.placement import diagonal, doc_shard, word_shard
from ..operators.prior import length_histogram, optimise_alpha, topic_doc_histogram
from ..operators.sampling import KERNELS, Block, Lists, Rows, Table, block_draws, block_key
from ..sources.files import scratch, settle


@dataclass
class Settings:
    """topics, shards (M), configurations (C) and when things happen.

    sync: relaxed (all blocks of a sweep in one job against one snapshot),
    segment (a job per diagonal, totals refreshed after all), diagonal (totals
    refreshed after each).
    """

    topics: int = 8
    vocab_size: int = 0
    alpha: float = 0.1
    beta: float = 0.01
    shards: int = 4
    configs: int = 1
    merge_every: int = 1
    sync: str = "relaxed"
    kernel: str = "buckets"
    seed: int = 7
    prior_from: int | None = None
    prior_every: int = 5


_TAGGED = "kind int, cfg bigint, doc_id bigint, pos bigint, word_id bigint, z int, topic int, n bigint, doc_shard bigint, word_shard bigint"
_STATE = "cfg bigint, doc_id bigint, pos bigint, word_id bigint, z int, doc_shard bigint, word_shard bigint"
_STATE_ARROW = pa.schema([(c, pa.int32() if c == "z" else pa.int64()) for c in (x.split()[0] for x in _STATE.split(", "))])
_STATE_WAS = pa.schema([*_STATE_ARROW, pa.field("was", pa.int32())])
_LABELLED = StructType([StructField(f.name, IntegerType() if f.type == pa.int32() else LongType()) for f in _STATE_WAS])
_PACKED = StructType([StructField("block", IntegerType()), StructField("doc_id", LongType()), StructField("data", BinaryType())])
#: Rows of whole documents that a kernel takes at once.
PIECE = 1 << 16


def _pieces(batches: Iterator[pa.RecordBatch], key: tuple[str, ...], size: int) -> Iterator[tuple[tuple[int, ...], dict[str, np.ndarray]]]:
    """The key and next rows of the group at hand, of rows sorted by key, word counts first, then by document.

    A document is never cut; word counts (kind 2) may be.
    """
    held: list[dict[str, np.ndarray]] = []
    n, now = 0, None
    joined = lambda: {c: np.concatenate([x[c] for x in held]) for c in held[0]}
    for b in batches:
        if not b.num_rows:
            continue
        x = {c: b.column(c).fill_null(0).to_numpy(zero_copy_only=False) for c in b.schema.names}  # a column without meaning for its kind is null
        cut = np.zeros(b.num_rows - 1, bool)
        for k in key:
            cut |= x[k][1:] != x[k][:-1]
        ends = [*(np.flatnonzero(cut) + 1).tolist(), b.num_rows]
        for lo, hi in zip([0, *ends], ends, strict=False):
            own = tuple(int(x[k][lo]) for k in key)
            if n and own != now:
                yield now, joined()
                held, n = [], 0
            now, n = own, n + hi - lo
            held.append({c: v[lo:hi] for c, v in x.items()})
        if n >= size:
            rows = joined()
            docs, model = rows["doc_id"], rows["kind"] == 2
            other = np.flatnonzero((docs != docs[-1]) | model)
            at = n if model[-1] else int(other[-1]) + 1 if len(other) else 0
            if at:
                yield now, {c: v[:at] for c, v in rows.items()}
            held, n = [{c: v[at:].copy() for c, v in rows.items()}] if at < n else [], n - at
    if n:
        yield now, joined()


def _sampler(s: Settings, psi: dict[int, np.ndarray], alpha: np.ndarray, iteration: int, key: tuple[str, ...], spent=None):
    """The function of a partition of blocks: rows of word counts (kind 2), then tokens (0) and document counts (1) of each document in, labelled tokens out.

    A block's word counts and one piece of its documents are held at once; counts and draws go on from piece to piece.
    spent: an accumulator of the seconds inside it, or None.
    """
    beta, vocab, kernel, seed, size = s.beta, s.vocab_size, s.kernel, s.seed, PIECE

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now = None
        for group, x in _pieces(batches, key, size):
            begun = time.perf_counter()
            if group != now:
                now, model, phi = group, [], None
                draws = block_draws(seed, iteration, group)
                total = psi[int(x["cfg"][0])].copy()
            m = x["kind"] == 2
            if m.any():
                model.append([x[c][m] for c in ("word_id", "topic", "n")])
            t = np.flatnonzero(x["kind"] == 0)
            if not len(t):
                continue
            t = t[np.lexsort((x["pos"][t], x["doc_id"][t]))]
            if phi is None:
                w, k, n = (np.concatenate(c) for c in zip(*model, strict=True))
                words, w = np.unique(w, return_inverse=True)
                phi, model = Rows(w, k.astype(np.int64), n, len(words)), []
                if kernel == "dense":
                    phi = phi.dense(len(alpha))
                elif Lists.suits(len(words), len(alpha)):
                    phi = Lists(phi, len(alpha))
            docs, d_at = np.unique(x["doc_id"][t], return_inverse=True)
            w_at = np.searchsorted(words, x["word_id"][t])
            c = np.flatnonzero(x["kind"] == 1)
            theta = Rows(np.searchsorted(docs, x["doc_id"][c]), x["topic"][c].astype(np.int64), x["n"][c], len(docs))
            b = Block(d_at, w_at, x["z"][t].astype(int), theta.dense(len(alpha)) if kernel == "dense" else theta, phi, total)
            new = KERNELS[kernel](b, alpha, beta, vocab, draws.random(len(t)))
            if spent is not None:
                spent.add(time.perf_counter() - begun)
            yield _labelled(x, t, new, _STATE_WAS)

    return run


def _labelled(x: dict[str, np.ndarray], t: np.ndarray, z: np.ndarray, schema: pa.Schema = _STATE_ARROW) -> pa.RecordBatch:
    old = {"was": x["z"][t].astype(np.int32), "z": z.astype(np.int32)}
    return pa.RecordBatch.from_arrays([pa.array(old[f.name] if f.name in old else x[f.name][t], f.type) for f in schema], schema=schema)


def collect_columns(df: DataFrame) -> Iterator[list[np.ndarray]]:
    """The whole-number columns of df, a batch at a time: the driver never holds all rows as objects."""
    names = df.columns

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([np.asarray(b.column(c)).astype(np.int64).tobytes()], pa.binary()) for c in names], names)

    for r in df.mapInArrow(pack, ", ".join(f"{c} binary" for c in names)).toLocalIterator():
        yield [np.frombuffer(c, np.int64) for c in r]


@dataclass
class GridTrainer:
    """Distributed Gibbs: word shards x document shards, C configurations merged every few iterations."""

    spark: SparkSession
    settings: Settings
    state: DataFrame | None = None
    base: DataFrame | None = None  # model at the last merge
    base_own: DataFrame | None = None  # each configuration's own counts then
    alpha: list[float] = field(default_factory=list)
    iteration: int = 0
    log: list[dict] = field(default_factory=list)
    kernel_seconds: Accumulator | None = None  # if set, seconds inside block kernels are added to it
    _merged: bool = False  # no label has changed since the last merge

    def start(self, tokens: DataFrame) -> GridTrainer:
        s = self.settings
        z = F.floor(uniform(0, "doc_id", "pos", seed=s.seed) * s.topics).cast("int")
        cfg = F.floor(uniform(F.lit("cfg"), "doc_id", seed=s.seed) * s.configs).cast("bigint")
        self.state = settle(tokens.select(cfg.alias("cfg"), "doc_id", "pos", "word_id", z.alias("z"), doc_shard(s.shards, s.seed).alias("doc_shard"), word_shard(s.shards, s.seed).alias("word_shard")), "state")
        self.alpha = [s.alpha] * s.topics
        self.merge()
        return self

    def own_counts(self) -> DataFrame:
        return self.state.groupBy("cfg", "word_id", "word_shard", F.col("z").alias("topic")).agg(F.count(F.lit(1)).alias("n"))

    def merge(self) -> None:
        """All configurations agree on the sum of all labels: base model plus every configuration's changes."""
        own = settle(self.own_counts(), "own")
        self.base_own = own
        one = self.settings.configs == 1
        self.base = own.drop("cfg") if one else settle(own.groupBy("word_id", "word_shard", "topic").agg(F.sum("n").alias("n")), "base")
        self._merged = True

    def models(self) -> DataFrame:
        """cfg, word_id, word_shard, topic, n: what each configuration sees, the merged model and its own changes since."""
        if self.settings.configs == 1:  # its own counts alone
            return self.base_own if self._merged else self.own_counts()
        cfgs = self.spark.range(self.settings.configs).withColumnRenamed("id", "cfg")
        parts = self.base.crossJoin(F.broadcast(cfgs)).select("cfg", "word_id", "word_shard", "topic", "n")
        if self._merged:
            return parts
        parts = parts.unionByName(self.own_counts()).unionByName(self.base_own.withColumn("n", -F.col("n")))
        return parts.groupBy("cfg", "word_id", "word_shard", "topic").agg(F.sum("n").alias("n")).filter("n <> 0")

    def _totals(self, models: DataFrame) -> dict[int, np.ndarray]:
        psi = {c: np.zeros(self.settings.topics) for c in range(self.settings.configs)}
        for r in models.groupBy("cfg", "topic").agg(F.sum("n").alias("n")).collect():  # C * K numbers
            psi[r.cfg][r.topic] = r.n
        return psi

    def _sweep(self, now, models: DataFrame, psi: dict, key: tuple[str, ...]) -> DataFrame:
        """The tokens for which ``now`` holds with new labels, and the old ones as ``was``, as a written table."""
        s, todo = self.settings, self.state.filter(now)
        if s.kernel != "buckets":
            none = lambda t: F.lit(None).cast(t)
            names = [x.split()[0] for x in _TAGGED.split(", ")]
            tokens = todo.select(F.lit(0).alias("kind"), "cfg", "doc_id", "pos", "word_id", "z", none("int").alias("topic"), none("bigint").alias("n"), "doc_shard", "word_shard")
            blocks = todo.select("cfg", "doc_shard", "word_shard").distinct() if "doc_shard" in key else todo.select("cfg", F.lit(0).cast("bigint").alias("doc_shard"), "word_shard").distinct()
            model = models.join(F.broadcast(blocks), ["cfg", "word_shard"]).select(F.lit(2).alias("kind"), "cfg", none("bigint").alias("doc_id"), none("bigint").alias("pos"), "word_id", none("int").alias("z"), "topic", "n", "doc_shard", "word_shard")
            here = todo.select("cfg", "doc_id", "doc_shard", "word_shard").distinct()
            docs = here.join(count_doc_topic(self.state), "doc_id").select(F.lit(1).alias("kind"), "cfg", "doc_id", none("bigint").alias("pos"), none("bigint").alias("word_id"), none("int").alias("z"), "topic", "n", "doc_shard", "word_shard")
            rows = tokens.select(*names).unionByName(docs.select(*names)).unionByName(model.select(*names))
            laid = rows.repartition(*key).sortWithinPartitions(*key, F.col("kind") != 2, "doc_id", "pos")
            return settle(laid.mapInArrow(_sampler(s, psi, np.array(self.alpha), self.iteration, key, self.kernel_seconds), f"{_STATE}, was int"), "state")
        # tokens go through documents, which hand all their labels to each block; a block is a task of its own
        by_doc = self.state.select("cfg", "doc_id", "pos", "word_id", "z", "doc_shard", "word_shard", now.alias("now")).repartition("doc_id").sortWithinPartitions("doc_id", "pos")
        docs = sampled(by_doc, packer(self.spark, s.shards, True), _PACKED)
        counts = sampled(models.select("cfg", "word_shard", "word_id", "topic", "n"), packer(self.spark, s.shards, False), _PACKED)
        laid = counts.unionByName(docs).repartitionById(s.configs * s.shards, "block").sortWithinPartitions("doc_id")
        f = sampler(self.spark, np.array(self.alpha), s.beta, s.vocab_size)
        f.blocks("doc_shard" in key)
        for c in range(s.configs):
            f.total(c, psi[c].astype("<f8").tobytes())
            for w in range(s.shards):
                for d in range(s.shards if "doc_shard" in key else 1):
                    f.key(c, d, w, block_key(s.seed, self.iteration, (c, d, w) if "doc_shard" in key else (c, w)).astype("<u8").tobytes())
        spent = None
        if self.kernel_seconds is not None:
            spent = self.spark.sparkContext._jsc.sc().doubleAccumulator()
            f.timed(spent)
        # blocks are few: what they label is written by as many tasks as its size asks for
        done = settle(sampled(sampled(laid, f, _PACKED).repartition("doc_id"), unpacker(self.spark), _LABELLED), "state")
        if spent is not None:
            self.kernel_seconds.add(float(spent.value()))
        return done

    def step(self) -> None:
        """One iteration over all blocks, then the prior and the merge if they are due."""
        s, begun = self.settings, time.time()
        columns, changed = self.state.columns, 0
        if s.sync == "relaxed":
            models = self.models()
            done = self._sweep(F.lit(True), models, self._totals(models), ("cfg", "word_shard"))
            changed, self.state, self._merged = done.filter("z <> was").count(), done.select(columns), False
        else:
            psi = self._totals(self.models())
            for d in range(s.shards):
                models = self.models()
                if s.sync == "diagonal":
                    models = models if self._merged else settle(models, "models")
                    psi = self._totals(models)
                now = diagonal(F.col("doc_shard"), F.col("word_shard"), s.shards) == d
                done = self._sweep(now, models, psi, ("cfg", "doc_shard", "word_shard"))
                changed += done.filter("z <> was").count()
                self.state, self._merged = settle(done.select(columns).unionByName(self.state.filter(~now)), "state"), False
        self.iteration += 1
        if self.iteration % s.merge_every == 0:
            self.merge()
        if s.prior_from is not None and self.iteration >= s.prior_from and (self.iteration - s.prior_from) % s.prior_every == 0:
            theta = count_doc_topic(self.state)
            self.alpha = optimise_alpha(self.alpha, topic_doc_histogram(theta), length_histogram(self.state), sweeps=2)
        self.log.append({"iter": self.iteration, "seconds": round(time.time() - begun, 3), "changed": changed})

    def train(self, iterations: int) -> GridTrainer:
        for _ in range(iterations):
            self.step()
        return self

    def model(self) -> tuple[DataFrame, DataFrame]:
        """phi and psi of all labels."""
        return count_word_topic(self.state), count_topic(self.state)

    def save(self, folder: str | None = None) -> str:
        """State and a manifest; each configuration has its own partition, so one can be restarted alone."""
        folder = folder or scratch(self.spark, "checkpoint")
        self.state.write.partitionBy("cfg").parquet(f"{folder}/state")
        self.base.write.parquet(f"{folder}/base")
        self.base_own.write.parquet(f"{folder}/own")
        manifest = {"settings": asdict(self.settings), "alpha": self.alpha, "iteration": self.iteration}
        self.spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.text(f"{folder}/manifest")
        return folder

    @classmethod
    def load(cls, spark: SparkSession, folder: str) -> GridTrainer:
        m = json.loads(spark.read.text(f"{folder}/manifest").first().value)
        state = spark.read.parquet(f"{folder}/state").select(F.col("cfg").cast("bigint"), "doc_id", "pos", "word_id", "z", "doc_shard", "word_shard")
        return cls(spark, Settings(**m["settings"]), state, spark.read.parquet(f"{folder}/base"), spark.read.parquet(f"{folder}/own"), m["alpha"], m["iteration"])


@dataclass
class ReplicatedTrainer:
    """The rival: every worker holds the whole model, samples its documents, and changes are summed after each iteration."""

    spark: SparkSession
    settings: Settings
    max_model_bytes: int = 256 << 20
    state: DataFrame | None = None
    iteration: int = 0
    log: list[dict] = field(default_factory=list)
    _first: int = 0  # smallest word id

    def start(self, tokens: DataFrame) -> ReplicatedTrainer:
        s = self.settings
        need = 8 * s.vocab_size * s.topics
        if need > self.max_model_bytes:
            raise ModelTooLarge(f"a dense copy of {s.vocab_size} x {s.topics} counts takes {need} bytes; the limit is {self.max_model_bytes}")
        most = tokens.agg(F.min("word_id").alias("lo"), F.max("word_id").alias("hi")).first()
        if most.hi is not None and not 0 <= most.lo <= most.hi <= s.vocab_size:
            raise ValueError(f"word ids must lie in 0..{s.vocab_size}; found {most.lo}..{most.hi}: build a vocabulary first")
        self._first = 1 if most.hi == s.vocab_size else 0  # ids from 1 are as dense as ids from 0
        if self._first and most.lo < 1:
            raise ValueError(f"{s.vocab_size} words cannot have ids 0..{s.vocab_size}")
        z = F.floor(uniform(0, "doc_id", "pos", seed=s.seed) * s.topics).cast("int")
        self.state = settle(tokens.select(F.lit(0).cast("bigint").alias("cfg"), "doc_id", "pos", "word_id", z.alias("z"), doc_shard(s.shards, s.seed).alias("doc_shard"), F.lit(0).cast("bigint").alias("word_shard")), "state")
        return self

    def step(self) -> None:
        s, begun = self.settings, time.time()
        model, first = np.zeros((s.vocab_size, s.topics), np.int64), self._first  # size checked in start()
        for w, k, n in collect_columns(settle(count_word_topic(self.state), "model")):
            model[w - first, k] = n
        shared, it, alpha = self.spark.sparkContext.broadcast(model), self.iteration, np.full(s.topics, s.alpha)
        beta, vocab, kernel, seed, topics, size = s.beta, s.vocab_size, s.kernel, s.seed, s.topics, PIECE

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            now = None
            for group, x in _pieces(batches, ("doc_shard",), size):
                if group != now:
                    now, draws = group, block_draws(seed, it, group)
                    few = kernel == "buckets" and Lists.suits(len(shared.value), topics)
                    phi = Lists(shared.value, topics) if few else Table(shared.value.astype(float))
                    total = shared.value.sum(0).astype(float)
                docs, d_at = np.unique(x["doc_id"], return_inverse=True)
                z = x["z"].astype(int)
                theta = np.bincount(d_at * topics + z, minlength=len(docs) * topics).reshape(-1, topics).astype(float)
                b = Block(d_at, x["word_id"] - first, z, Table(theta), phi, total)
                yield _labelled(x, np.arange(len(z)), KERNELS[kernel](b, alpha, beta, vocab, draws.random(len(z))))

        laid = self.state.withColumn("kind", F.lit(0)).repartition("doc_shard").sortWithinPartitions("doc_shard", "doc_id", "pos")
        self.state = settle(laid.mapInArrow(run, _STATE), "state")
        shared.destroy()
        self.iteration += 1
        self.log.append({"iter": self.iteration, "seconds": round(time.time() - begun, 3)})

    def train(self, iterations: int) -> ReplicatedTrainer:
        for _ in range(iterations):
            self.step()
        return self


def apply_diffs(old: DataFrame, responses: DataFrame) -> DataFrame:
    """Labels after changed ones are written over the old copy: doc_id, pos, word_id, z."""
    new = responses.select("doc_id", "pos", F.col("z").alias("new_z"))
    return old.join(new, ["doc_id", "pos"], "left").select("doc_id", "pos", "word_id", F.coalesce("new_z", "z").alias("z"))


def merge_models(base: DataFrame, deltas: DataFrame) -> DataFrame:
    """word_id, topic, n: a base model plus the changes of all configurations; zero entries are left out."""
    return base.select("word_id", "topic", "n").unionByName(deltas.select("word_id", "topic", "n")).groupBy("word_id", "topic").agg(F.sum("n").alias("n")).filter("n <> 0")


def merge_totals(psi: DataFrame, deltas: DataFrame) -> DataFrame:
    return psi.select("topic", "n").unionByName(deltas.select("topic", "n")).groupBy("topic").agg(F.sum("n").alias("n"))
