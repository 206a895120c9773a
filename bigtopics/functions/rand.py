"""Draws that depend on logical ids alone, so retries and repartitioning never change them."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(*parts: Column | str | int, seed: int = 7, fast: bool = False) -> Column:
    """A number in [0, 1) for the ids in parts.

    Portable form: eight hexadecimal digits of an MD5, equal in any SQL engine.
    Fast form: xxhash64.
    """
    cols = [p if isinstance(p, Column) else F.col(p) if isinstance(p, str) else F.lit(p) for p in parts]
    if fast:
        return F.pmod(F.xxhash64(F.lit(seed), *cols), F.lit(1 << 53)) / F.lit(float(1 << 53))
    text = F.concat_ws("|", F.lit(str(seed)), *(c.cast("string") for c in cols))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint") / F.lit(4294967296.0)
