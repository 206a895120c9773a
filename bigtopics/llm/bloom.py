"""A Bloom filter over 64-bit keys, built by an aggregation; its bits follow the number of keys up to a stated bound."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_MIX = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)


class Bloom:
    """bits: a power of two.  A full filter lets everything through; it never loses a key."""

    def __init__(self, words: np.ndarray):
        self.words = words

    def _places(self, keys: np.ndarray) -> Iterator[np.ndarray]:
        return places(keys, len(self.words) * 64)

    def may_hold(self, keys: np.ndarray) -> np.ndarray:
        ok = np.ones(len(keys), bool)
        for at in self._places(keys):
            ok &= (self.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1
        return ok


def places(keys: np.ndarray, bits: int) -> Iterator[np.ndarray]:
    shift = np.uint64(64 - (bits.bit_length() - 1))
    for m in _MIX:
        mixed = keys.view(np.uint64) * np.uint64(m)
        yield ((mixed ^ (mixed >> np.uint64(29))) * np.uint64(m) >> shift).astype(np.int64)


MOST_BITS = 1 << 27  # 16 MB; beyond some 10^7 keys the filter lets more and more through


def bits_for(keys: int) -> int:
    """A power of two, 12 bits a key or more, from 2^16 to MOST_BITS."""
    return min(MOST_BITS, max(1 << 16, 1 << (12 * keys).bit_length()))


def build(keys: DataFrame, col: str, bits: int | None = None) -> Bloom:
    """keys: a written table, since it is counted first unless ``bits`` is given.  Each task sets its own words; equal words are combined by bit_or, so at most bits / 64 rows reach the driver."""
    bits = bits or bits_for(keys.count())

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = np.zeros(bits // 64, np.uint64)
        for batch in batches:
            keys = np.asarray(batch.column(0)).astype(np.int64)
            for at in places(keys, bits):
                np.bitwise_or.at(words, at >> 6, np.uint64(1) << (at & 63).astype(np.uint64))
        at = np.flatnonzero(words)
        for a in range(0, len(at), 50_000):
            part = at[a : a + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(words[part].view(np.int64))], names=["at", "word"])

    set_words = keys.select(F.col(col).cast("long")).mapInArrow(mark, "at long, word long").groupBy("at").agg(F.bit_or("word").alias("word"))
    words = np.zeros(bits // 64, np.uint64)
    got = set_words.toArrow()
    words[np.asarray(got.column("at")).astype(np.int64)] = np.asarray(got.column("word")).astype(np.int64).view(np.uint64)
    return Bloom(words)
