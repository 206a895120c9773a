"""Compiles the Java sources here in the driver's JVM and hands them to the executors as a jar."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

_LOADERS: dict[str, dict] = {}


def _loaders(spark: SparkSession) -> dict:
    """Class loaders of the compiled sources; their classes are added to the session's jars once."""
    sc = spark.sparkContext
    if sc.applicationId not in _LOADERS:
        jvm, loaders, code = sc._jvm, {}, {}
        for name in ("BlockSampler", "Packer", "Unpacker"):
            compiler = jvm.org.codehaus.janino.SimpleCompiler()
            compiler.setParentClassLoader(jvm.java.lang.Thread.currentThread().getContextClassLoader())
            compiler.cook(Path(__file__).with_name(f"{name}.java").read_text())
            code |= dict(compiler.getBytecodes())
            loaders[name] = compiler.getClassLoader()
        jar = os.path.join(os.path.realpath(tempfile.mkdtemp(prefix="bigtopics-")), "bigtopics-sampler.jar")
        with zipfile.ZipFile(jar, "w") as z:
            for name, x in code.items():
                z.writestr(name.replace(".", "/") + ".class", bytes(x))
        sc._jsc.addJar(jar)
        _LOADERS[sc.applicationId] = loaders
    return _LOADERS[sc.applicationId]


def _new(spark: SparkSession, name: str):
    """A new object of a compiled class in the driver's JVM."""
    sc = spark.sparkContext
    none = lambda kind: sc._gateway.new_array(kind, 0)
    return _loaders(spark)[name].loadClass(f"bigtopics.{name}").getDeclaredConstructor(none(sc._jvm.java.lang.Class)).newInstance(none(sc._jvm.java.lang.Object))


def sampler(spark: SparkSession, alpha: np.ndarray, beta: float, vocab_size: int):
    """A sampler: a function of partitions for ``sampled``, or one for pieces of documents."""
    s = _new(spark, "BlockSampler")
    s.prior(np.asarray(alpha, "<f8").tobytes(), float(beta), float(beta * vocab_size))
    return s


def packer(spark: SparkSession, shards: int, tokens: bool):
    """The function that packs tokens by document, or word counts."""
    p = _new(spark, "Packer")
    p.set(shards, tokens)
    return p


def unpacker(spark: SparkSession):
    """The function that makes tokens of labelled documents."""
    return _new(spark, "Unpacker")


def sampled(rows: DataFrame, function, schema: StructType) -> DataFrame:
    """rows through a compiled function, partition by partition."""
    spark = rows.sparkSession
    encoder = spark.sparkContext._jvm.org.apache.spark.sql.Encoders.row(spark._jsparkSession.parseDataType(schema.json()))
    return DataFrame(rows._jdf.mapPartitions(function, encoder), spark)
