"""Query logs and state tables as files: text, CSV, JSON lines, Parquet."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_OWN: list[str] = []


#: Folders of open ``temporary`` blocks, innermost last.
_OPEN: list[str] = []


@contextmanager
def temporary(spark: SparkSession) -> Iterator[Callable[[DataFrame, str], DataFrame]]:
    """What is settled inside the block goes into one folder that is deleted at its end.

    Yields a function that settles a result outside it.  Results must be settled
    by that function or be read before the block ends.
    """
    outside, folder = list(_OPEN), scratch(spark, "temporary")

    def keep(df: DataFrame, name: str) -> DataFrame:
        inside, _OPEN[:] = list(_OPEN), outside
        try:
            path = scratch(spark, name)
        finally:
            _OPEN[:] = inside
        _write(df, path)
        return spark.read.schema(df.schema).parquet(path)

    _OPEN.append(folder)
    try:
        yield keep
    finally:
        _OPEN[:] = outside
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the folder all executors share (spark.checkpoint.dir); a local one where that is unset, as in tests."""
    root = _OPEN[-1] if _OPEN else spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        if not _OWN:
            _OWN.append("file://" + tempfile.mkdtemp(prefix="bigtopics-"))
        root = _OWN[0]
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def _write(df: DataFrame, path: str) -> None:
    """Without the empty file that marks success: nothing reads a table before its write has returned, and on a local file system
    setting that file's mode starts a process, which for a moment counts the memory of the driver's JVM a second time.
    """
    df.write.option("mapreduce.fileoutputcommitter.marksuccessfuljobs", "false").parquet(path)


def settle(df: DataFrame, name: str) -> DataFrame:
    """Writes df and reads it back: cuts lineage between iterations and survives lost executors."""
    path = scratch(df.sparkSession, name)
    _write(df, path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """df written as json or csv and read again with its schema."""
    path = scratch(df.sparkSession, kind)
    if kind == "json":
        df.write.json(path)
        return df.sparkSession.read.schema(df.schema).json(path)
    if kind == "csv":
        df.write.option("header", True).option("escape", '"').csv(path)
        return df.sparkSession.read.schema(df.schema).option("header", True).option("escape", '"').csv(path)
    raise ValueError(f"no such format: {kind}")


def query_log(spark: SparkSession, path: str) -> DataFrame:
    """One query per line of a text file: query."""
    return spark.read.text(path).withColumnRenamed("value", "query")
