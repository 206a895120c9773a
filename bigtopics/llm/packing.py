"""Harmonic packing of token ids into sequences of a fixed capacity.

A document gives its whole sequences first and then one tail shorter than a
sequence.  A tail of length L is of class ``capacity // L``, and a bin of class k
holds k whole tails, which always fit.  Ranks within a class come from counts by
(class, bucket) and their running sums, so each (class, bucket) is filled by
itself and no class meets in one task.

What a bin leaves free is filled by a few tails set apart by a hash, and by those
that don't make a whole bin of their class, less than one bin each.  These are
laid end to end on the line of all gaps of ``grain`` ids or more, and cut where a
gap ends; what is left of them goes into sequences of its own.  Long tails are
set apart first; how many follows from the counts: the fewest whose ids fill the
gaps of the others.  So only these are cut, and a sequence is full but for less
than ``grain`` ids.

Defined cases: a null text is empty and has the end id alone; null and repeated
ids are documents of their own; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import settle, temporary, text_of
from .tokens import encoded

LONG = 2  # tails of these classes are set apart first
RANGES = 1024  # parts of a line whose sums the driver adds up
_PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def pieces(docs: DataFrame, tokenizer: str, *, id_col: str, text_col: str, capacity: int) -> DataFrame:
    """A row per whole sequence and tail: doc_id, start, length, ids_crc32, doc_tokens, ids (bytes; null for a whole sequence)."""
    names = [x.split()[0] for x in _PIECE.split(", ")]
    schema = pa.schema([*((n, pa.int64()) for n in names), ("ids", pa.binary())])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, ids, many in encoded(batches, tokenizer, "text"):
            raw = memoryview(ids.astype("<u4").tobytes())
            rows, at = [], 0
            for doc_id, n in zip(batch.column("id").to_pylist(), many.tolist(), strict=True):
                for begin in range(0, n, capacity):
                    size = min(capacity, n - begin)
                    own = raw[4 * (at + begin) : 4 * (at + begin + size)]
                    rows.append((doc_id, begin, size, zlib.crc32(own), n, None if size == capacity else bytes(own)))
                at += n
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return docs.select(F.col(id_col).cast("long").alias("id"), text_of(text_col).alias("text")).mapInArrow(cut, f"{_PIECE}, ids binary")


@dataclass
class Plan:
    """Which tails are set apart, and where the ranks of each class go."""

    apart_from: tuple[int, int]  # long tails of this bucket and above fill gaps, and other tails of that
    bases: list[tuple[int, int, int]]  # class, bucket, rank of its first tail
    classes: list[tuple[int, int, int, int]]  # class, pieces a bin, ranks that make whole bins, first sequence
    sequences: int

    @classmethod
    def of(cls, counts: dict[tuple[int, int], tuple[int, int]], capacity: int, buckets: int) -> Plan:
        """counts: (class, bucket): (pieces, their ids); class 0 holds whole sequences."""
        if not counts:
            return cls((buckets, buckets), [], [], 0)
        kinds = sorted({k for k, _ in counts})
        n, size = np.zeros((len(kinds), buckets), np.int64), np.zeros((len(kinds), buckets), np.int64)
        for (k, b), (pieces_, ids) in counts.items():
            n[kinds.index(k), b], size[kinds.index(k), b] = pieces_, ids
        per, tail, long = (np.array(x) for x in ([max(k, 1) for k in kinds], [k > 0 for k in kinds], [0 < k <= LONG for k in kinds]))
        # long tails go first: they fit their classes worst, and one fills many gaps
        for step in range(2 * buckets + 1):
            apart = (max(buckets - step, 0), min(2 * buckets - step, buckets))
            kept_here = np.where(long[:, None], np.arange(buckets) < apart[0], (np.arange(buckets) < apart[1]) | ~tail[:, None])
            kept = np.where(kept_here, n, 0)
            ids = np.where(kept_here, size, 0).sum(1)
            if cls._gaps(kept.sum(1)[tail], ids[tail], per[tail], capacity) <= (size.sum(1) - ids).sum():
                break
        whole = kept.sum(1) // per
        first = np.cumsum(whole) - whole
        before = np.cumsum(kept, 1) - kept
        bases = [(k, b, int(before[i, b])) for i, k in enumerate(kinds) for b in np.flatnonzero(kept[i]).tolist()]
        return cls(apart, bases, [(k, int(per[i]), int(whole[i] * per[i]), int(first[i])) for i, k in enumerate(kinds)], int(whole.sum()))

    @staticmethod
    def _gaps(n: np.ndarray, ids: np.ndarray, per: np.ndarray, capacity: int) -> float:
        """Ids that whole bins leave free, less those of the pieces that make none (at their class's mean)."""
        whole = n // per
        loose = (n - whole * per) * ids / np.maximum(n, 1)
        return float((whole * capacity - (ids - loose)).sum() - loose.sum())


def _laid(rows: DataFrame, part: Column, order: str, size: str) -> tuple[DataFrame, int]:
    """rows with ``begin``: they are laid end to end on a line, ordered by part and, in it, by ``order``; and the line's length.

    At most RANGES sums reach the driver and go back by broadcast.
    """
    rows = rows.withColumn("part", part.cast("int"))
    base, total = [], 0
    for r in sorted(rows.groupBy("part").agg(F.sum(size).alias("s")).collect(), key=lambda r: r.part):
        base.append((r.part, total))
        total += r.s
    sums = rows.sparkSession.createDataFrame(base, "part int, base long")
    upto = F.sum(size).over(Window.partitionBy("part").orderBy(order))
    return rows.join(F.broadcast(sums), "part").withColumn("begin", F.col("base") + upto - F.col(size)).drop("part", "base"), total


def _sliced(rows: DataFrame) -> DataFrame:
    """The pieces of rows with ids, from, size: their checksums are taken from the ids."""
    out = [x.split()[0] for x in _PIECE.split(", ")]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lo, n = (np.asarray(batch.column(c)).astype(np.int64) for c in ("from", "size"))
            crc = [zlib.crc32(raw.as_buffer()[4 * a : 4 * (a + k)]) for raw, a, k in zip(batch.column("ids"), lo.tolist(), n.tolist(), strict=True)]
            start = np.asarray(batch.column("start")).astype(np.int64) + lo
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(start), pa.array(n), pa.array(crc, pa.int64()), batch.column("doc_tokens"), batch.column("sequence_id"), batch.column("offset")], names=[*out, "sequence_id", "offset"])

    return rows.mapInArrow(cut, f"{_PIECE}, sequence_id long, offset long")


def pack(docs: DataFrame, tokenizer: str, *, id_col: str = "doc_id", text_col: str = "text", capacity: int = 4096, grain: int = 64, buckets: int = 256) -> DataFrame:
    """A row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    ``grain``: gaps of fewer ids stay empty.  The driver gets one count per
    (class, bucket), at most 2 * sqrt(capacity) * buckets rows, and 2 * RANGES sums.
    The tables written on the way are deleted at its end.
    """
    if not 1 <= grain <= capacity:
        raise ValueError("grain must be from 1 to capacity")
    with temporary(docs.sparkSession) as keep:
        return keep(_packed(docs, tokenizer, id_col, text_col, capacity, grain, buckets), "packed")


def _packed(docs: DataFrame, tokenizer: str, id_col: str, text_col: str, capacity: int, grain: int, buckets: int) -> DataFrame:
    spark = docs.sparkSession
    cut = settle(pieces(docs, tokenizer, id_col=id_col, text_col=text_col, capacity=capacity).withColumn("row", F.monotonically_increasing_id()), "pieces")
    kind = F.when(F.col("length") == capacity, 0).otherwise(F.floor(F.lit(capacity) / F.col("length"))).cast("int")
    cut = cut.withColumn("class", kind).withColumn("bucket", F.pmod(F.xxhash64("doc_id", "start", "length", "ids_crc32"), F.lit(buckets)).cast("int"))
    counts = {(r["class"], r.bucket): (r.n, r.ids) for r in cut.groupBy("class", "bucket").agg(F.count(F.lit(1)).alias("n"), F.sum("length").alias("ids")).collect()}
    plan = Plan.of(counts, capacity, buckets)
    bases = spark.createDataFrame(plan.bases, "class int, bucket int, base long")
    classes = spark.createDataFrame(plan.classes, "class int, per long, ranks long, first long")

    long, other = plan.apart_from
    apart = (F.col("class") > 0) & (F.col("bucket") >= F.when(F.col("class") <= LONG, long).otherwise(other))
    local = F.row_number().over(Window.partitionBy("class", "bucket").orderBy("row")) - 1
    ranked = cut.filter(~apart).drop("ids").withColumn("local", local).join(F.broadcast(bases), ["class", "bucket"]).join(F.broadcast(classes), "class")
    ranked = settle(ranked.withColumn("rank", F.col("base") + F.col("local")), "ranked")
    placed = ranked.filter("rank < ranks").withColumn("sequence_id", F.col("first") + F.expr("rank div per"))
    own = Window.partitionBy("sequence_id")
    placed = settle(placed.withColumn("offset", F.sum("length").over(own.orderBy("rank")) - F.col("length")).withColumn("used", F.sum("length").over(own)), "placed")

    # at most one bin of each class lacks tails: a number that does not grow with the data
    loose = ranked.filter("rank >= ranks").select("row")
    fillers = cut.filter(apart).unionByName(cut.join(F.broadcast(loose), "row")).select("row", "doc_id", "start", "length", "doc_tokens", "ids")
    fillers, ids = _laid(fillers, F.pmod(F.xxhash64("row"), F.lit(RANGES)), "row", "length")
    gaps = placed.filter(F.expr("rank % per = per - 1") & (capacity - F.col("used") >= grain)).select("sequence_id", "used", (capacity - F.col("used")).alias("free"))
    gaps, free = _laid(gaps, F.floor(F.col("sequence_id") * RANGES / max(plan.sequences, 1)), "sequence_id", "free")
    more = spark.range(max(0, -(-(ids - free) // capacity))).select((F.col("id") + plan.sequences).alias("sequence_id"), F.lit(0).cast("long").alias("used"), F.lit(capacity).cast("long").alias("free"), (F.col("id") * capacity + free).alias("begin"))
    line = gaps.unionByName(more)

    # both lie on one line; blocks of it join what may overlap, and a piece belongs to the block where it begins
    block = 4 * capacity
    touched = lambda size: F.explode(F.sequence(F.floor(F.col("begin") / block), F.floor((F.col("begin") + F.col(size) - 1) / block)))
    left = fillers.withColumn("block", touched("length")).withColumnRenamed("begin", "f")
    right = line.withColumn("block", touched("free")).withColumnRenamed("begin", "g")
    begin, end = F.greatest("f", "g"), F.least(F.col("f") + F.col("length"), F.col("g") + F.col("free"))
    met = left.join(right, "block").filter((begin < end) & (F.floor(begin / block) == F.col("block")))
    filled = _sliced(met.select("doc_id", "start", "doc_tokens", "ids", "sequence_id", (begin - F.col("f")).alias("from"), (end - begin).alias("size"), (F.col("used") + begin - F.col("g")).alias("offset")))
    return placed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset").unionByName(filled)
