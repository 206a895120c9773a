"""Line dedup by content-defined chunks of lines.

A rolling hash over the hashes of the last few lines chooses chunk ends, so an
inserted or deleted line shifts no boundary beyond its surroundings.  A chunk of
two or more lines that occurs again anywhere in the corpus is removed but for
its first occurrence (smallest id, then smallest place).

Boundaries hide repeats that start or end inside a chunk.  With ``runs`` the
chunks are anchors and the pairs of neighbouring lines are a second, finest
level: a line goes if a pair it belongs to occurs earlier, so every repeated run
of two or more lines goes, wherever its chunks end, and nothing else does.  A
repeated line that stands alone among other lines stays, and so does at least
one copy of every line.  Pairs inside a repeated chunk are read from its first
occurrence alone, since its other copies go as a whole.

Stages: (1) hashes of chunks (and pairs) of all texts, counted over the corpus;
(2) the text of those whose hash occurs twice or more, grouped by hash and bytes,
which is the byte comparison; (3) places to remove, joined to the documents.
Stage 2 is kept small by a Bloom filter of the repeated hashes: a fixed number of
bits a key up to a set bound, built by an aggregation, so what is broadcast is bounded; beyond it
the filter lets more through and the join decides as before.

Defined cases: a null text stays null and has no chunks; null ids come last when
the first occurrence is chosen; rows with the same id and text count as one
document, and each keeps what that keeps;
documents may become empty; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bloom import Bloom, build
from .common import give_back, key_of, settle, temporary


def chunk_ends(lines: list[bytes], *, window: int = 2, modulus: int = 4, most: int = 64) -> list[int]:
    """End (exclusive line number) of each chunk: where the rolling hash of the last ``window`` lines is 0 modulo ``modulus``, or after ``most`` lines."""
    import xxhash

    hashes = [xxhash.xxh64_intdigest(x) for x in lines]
    ends, begin = [], 0
    for k in range(len(lines)):
        rolled = 0
        for h in hashes[max(0, k - window + 1) : k + 1]:
            rolled = (rolled * 0x9E3779B97F4A7C15 + h) & 0xFFFFFFFFFFFFFFFF
        if (rolled >> 20) % modulus == 0 or k + 1 - begin >= most:
            ends.append(k + 1)
            begin = k + 1
    if begin < len(lines):
        ends.append(len(lines))
    return ends


def chunks_of(text: str, **how) -> list[tuple[int, int, bytes]]:
    """(first line, end line, bytes) of each chunk of two or more lines."""
    lines = text.encode("utf-8", "surrogatepass").split(b"\n")
    out, begin = [], 0
    for end in chunk_ends(lines, **how):
        if end - begin >= 2:
            out.append((begin, end, b"\n".join(lines[begin:end])))
        begin = end
    return out


def pair_hashes(lines: list[bytes]) -> np.ndarray:
    """A 64-bit hash of each pair of neighbouring lines."""
    import xxhash

    h = np.array([xxhash.xxh64_intdigest(x) for x in lines], np.uint64)
    return h[:-1] * np.uint64(0x9E3779B97F4A7C15) + h[1:]


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(*key_of(id_col, text_col), F.col(id_col).isNull().alias("none"), F.col(text_col).alias("text"))


def chunk_hashes(rows: DataFrame, runs: bool = False, **how) -> DataFrame:
    """A row per chunk and, with ``runs``, per pair: hash."""
    schema = pa.schema([("hash", pa.int64())])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in batches:
            texts = [t for t in batch.column(0).to_pylist() if t is not None]
            found = [np.array([xxhash.xxh64_intdigest(b) for t in texts for _, _, b in chunks_of(t, **how)], np.uint64)]
            if runs:
                found += [pair_hashes(t.encode("utf-8", "surrogatepass").split(b"\n")) for t in texts]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64))], schema=schema)
        give_back()

    return rows.select("text").mapInArrow(cut, "hash long")


_PLACES = "__bt_k1 long, __bt_k2 long, none boolean, first int, end int, pair boolean, hash long, body binary"
_SCHEMA = pa.schema([("__bt_k1", pa.int64()), ("__bt_k2", pa.int64()), ("none", pa.bool_()), ("first", pa.int32()), ("end", pa.int32()), ("pair", pa.bool_()), ("hash", pa.int64()), ("body", pa.binary())])


def _batch(out: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _SCHEMA, strict=True)], schema=_SCHEMA)


def _pairs(lines: list[bytes], begin: int, repeated: Bloom, inside: np.ndarray | None = None) -> Iterator[tuple]:
    """(first, end, pair, hash, body) of the pairs of lines that may be repeated; ``begin`` is the number of the first line, ``inside`` marks pairs to pass over."""
    h = pair_hashes(lines).view(np.int64)
    if len(h):
        ok = repeated.may_hold(h)
        for k in np.flatnonzero(ok if inside is None else ok & ~inside).tolist():
            yield begin + k, begin + k + 2, True, int(h[k]), lines[k] + b"\n" + lines[k + 1]


def repeated_chunks(rows: DataFrame, repeated: Bloom, runs: bool = False, **how) -> DataFrame:
    """A row per chunk that may be repeated: key, none (no id), first, end, pair, hash, body (bytes); with ``runs`` also per such pair outside these chunks."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in batches:
            out, hashes = [], []
            texts = [x for x in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True) if x[3] is not None]
            for n, (*_, t) in enumerate(texts):
                for a, b, body in chunks_of(t, **how):
                    out.append((n, a, b, body))
                    hashes.append(xxhash.xxh64_intdigest(body))
            h = np.array(hashes, np.uint64).view(np.int64)
            ok = np.flatnonzero(repeated.may_hold(h)).tolist() if out else []
            spans: dict[int, list] = {}
            for k in ok:
                spans.setdefault(out[k][0], []).append(out[k][1:3])
            found = [(*texts[n][:3], a, b, False, int(h[k]), body) for k in ok for n, a, b, body in [out[k]]]
            if runs:
                for n, (*key, t) in enumerate(texts):
                    lines = t.encode("utf-8", "surrogatepass").split(b"\n")
                    inside = np.zeros(len(lines) - 1, bool)
                    for a, b in spans.get(n, ()):
                        inside[a : b - 1] = True
                    found += [(*key, *x) for x in _pairs(lines, 0, repeated, inside)]
            if found:
                yield _batch(found)
        give_back()

    return rows.mapInArrow(cut, _PLACES)


def inner_pairs(kept: DataFrame, repeated: Bloom) -> DataFrame:
    """A row per pair of lines that may be repeated, inside chunks (key, none, first, body): as repeated_chunks."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [(*key, *x) for *key, first, body in zip(*(batch.column(k).to_pylist() for k in range(5)), strict=True) for x in _pairs(body.split(b"\n"), first, repeated)]
            if found:
                yield _batch(found)

    return kept.mapInArrow(cut, _PLACES)


def _groups(found: DataFrame) -> DataFrame:
    """h, b, n, kept (the first place) of each hash and bytes."""
    # equal bytes, not only equal hashes: the body is a grouping key; counts are combined before the shuffle
    groups = found.groupBy("hash", "body").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("none", "__bt_k1", "__bt_k2", "first")).alias("kept"))
    return groups.select(F.col("hash").alias("h"), F.col("body").alias("b"), "n", "kept")


def _hits(found: DataFrame, groups: DataFrame) -> DataFrame:
    """key, first, end of what occurs earlier."""
    hit = found.join(groups.filter("n > 1"), (F.col("hash") == F.col("h")) & (F.col("body") == F.col("b")))
    return hit.filter(~F.struct("none", "__bt_k1", "__bt_k2", "first").eqNullSafe(F.col("kept"))).select("__bt_k1", "__bt_k2", "first", "end")


def _merged(spans: Column) -> Column:
    """Spans that overlap or touch as one, in order."""
    lines = F.sort_array(F.array_distinct(F.flatten(F.transform(spans, lambda s: F.sequence(s["first"], s["end"] - 1)))))
    first = F.filter(lines, lambda x, i: F.coalesce(x - F.get(lines, i - 1) > 1, F.lit(True)))
    last = F.filter(lines, lambda x, i: F.coalesce(F.get(lines, i + 1) - x > 1, F.lit(True)))
    return F.zip_with(first, last, lambda a, b: F.struct(a.alias("first"), (b + 1).alias("end")))


def removals(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", bloom_bits: int | None = None, runs: bool = False, **how) -> DataFrame:
    """A row per document that loses lines: its key and __bt_spans, an array of struct(first, end) of line numbers."""
    rows = _rows(docs, id_col, text_col)
    many = settle(chunk_hashes(rows, runs, **how).groupBy("hash").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("hash"), "chunk-hashes")
    repeated = build(many, "hash", bloom_bits)
    found = settle(repeated_chunks(rows, repeated, runs, **how), "chunks")
    chunks = found.filter("not pair")
    # written, so that the joins below shuffle both sides and a hot chunk's partition can be split
    groups = settle(_groups(chunks) if runs else _groups(chunks).filter("n > 1"), "groups")
    hit = _hits(chunks, groups)
    if runs:
        inner = settle(inner_pairs(groups.select("kept.__bt_k1", "kept.__bt_k2", "kept.none", "kept.first", "b"), repeated), "inner-pairs")
        pairs = found.filter("pair").unionByName(inner)
        hit = hit.unionByName(_hits(pairs, settle(_groups(pairs).filter("n > 1"), "pair-groups")))
    out = hit.groupBy("__bt_k1", "__bt_k2").agg(F.sort_array(F.collect_set(F.struct("first", "end"))).alias("__bt_spans"))
    # named first, so that the merge reads a column and not the aggregate again
    return settle(out, "spans").withColumn("__bt_spans", _merged(F.col("__bt_spans"))) if runs else out


def _apply(docs: DataFrame, spans: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs with __bt_spans (null: nothing to remove) and __bt_clean, the text without those lines."""
    # a shuffled join at every size: the removals grow with the documents
    joined = docs.select("*", *key_of(id_col, text_col)).join(spans.hint("merge"), ["__bt_k1", "__bt_k2"], "left")
    lines = F.split(F.col(text_col), "\n", -1)
    # lines between the spans: from the end of one to the start of the next
    edges = lambda k: F.when(k == 0, 0).otherwise(F.get(F.col("__bt_spans"), k - 1)["end"])
    until = lambda k: F.coalesce(F.get(F.col("__bt_spans"), k)["first"], F.size("__bt_lines"))
    kept = F.flatten(F.transform(F.sequence(F.lit(0), F.size("__bt_spans")), lambda k: F.slice("__bt_lines", edges(k) + 1, until(k) - edges(k))))
    joined = joined.withColumn("__bt_lines", F.when(F.col("__bt_spans").isNotNull(), lines))
    return joined.withColumn("__bt_clean", F.when(F.col("__bt_spans").isNull(), F.col(text_col)).otherwise(F.array_join(kept, "\n")))


def dedupe_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", length_col: str | None = "n_chars", **options) -> DataFrame:
    """docs with the repeated chunks removed; ``length_col``, if docs has it, is set to the new number of code points."""
    with temporary(docs.sparkSession) as keep:
        spans = keep(removals(docs, id_col=id_col, text_col=text_col, **options), "removals")
    out = _apply(docs, spans, id_col, text_col)
    names = [F.col("__bt_clean").alias(c) if c == text_col else (F.when(F.col("__bt_spans").isNull(), F.col(c)).otherwise(F.length("__bt_clean")).cast(docs.schema[c].dataType).alias(c) if c == length_col else F.col(c)) for c in docs.columns]
    return out.select(*names)


def line_report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row per input row: id, text (cleaned), n_removed_chunks (with ``runs``: runs), n_removed_lines, n_chars (of the cleaned text)."""
    with temporary(docs.sparkSession) as keep:
        spans = keep(removals(docs, id_col=id_col, text_col=text_col, **options), "removals")
    out = _apply(docs.select(id_col, text_col), spans, id_col, text_col)
    lines = F.aggregate("__bt_spans", F.lit(0), lambda s, x: s + x["end"] - x["first"])
    return out.select(F.col(id_col), F.col("__bt_clean").alias("text"), F.coalesce(F.size("__bt_spans"), F.lit(0)).cast("bigint").alias("n_removed_chunks"), F.coalesce(lines, F.lit(0)).cast("bigint").alias("n_removed_lines"), F.length("__bt_clean").cast("bigint").alias("n_chars"))
