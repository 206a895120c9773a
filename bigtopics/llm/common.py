"""What several operators of this package share.

Names that start with ``__bt_`` are private columns: no input table is
expected to have them, so a caller's extra columns never clash.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.files import scratch, settle, temporary

__all__ = ["SPACE", "WORD", "fresh_path", "give_back", "key_of", "settle", "table", "temporary", "text_of", "words_of"]

#: A word is a longest run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
SPACE = r"[\x20\x09-\x0D]+"


def fresh_path(spark: SparkSession, what: str) -> str:
    """A new path in the folder all executors see."""
    return scratch(spark, what)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(col: str = "text") -> Column:
    """The whole text; null counts as empty."""
    return F.coalesce(F.col(col), F.lit(""))


def words_of(text: Column) -> Column:
    """All words of a text, in order."""
    return F.regexp_extract_all(text, F.lit(f"({WORD})"), F.lit(1))


def give_back() -> None:
    """Returns freed memory of a Python worker to the system at the end of its task; workers live on."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def key_of(id_col: str, text_col: str) -> list[Column]:
    """Two columns, __bt_k1 and __bt_k2, that name a row by its id and text alone, so any two scans agree on them."""
    i = F.col(id_col).cast("long")
    return [F.coalesce(i, F.lit(0)).alias("__bt_k1"), F.xxhash64(i.isNull(), F.col(text_col).isNull(), F.col(text_col)).alias("__bt_k2")]
