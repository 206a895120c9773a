"""The asymmetric document prior: length and topic-count histograms and the fixed-point update."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def length_histogram(tokens: DataFrame) -> DataFrame:
    return tokens.groupBy("doc_id").agg(F.count(F.lit(1)).alias("len")).groupBy("len").agg(F.count(F.lit(1)).alias("n_docs"))


def topic_doc_histogram(theta: DataFrame) -> DataFrame:
    """topic, n, n_docs: in how many documents a topic has n tokens."""
    return theta.groupBy("topic", "n").agg(F.count(F.lit(1)).alias("n_docs"))


def _harmonic(a: Column, n: Column) -> Column:
    """1/a + 1/(a+1) + ... + 1/(a+n-1)"""
    return F.aggregate(F.sequence(F.lit(0).cast("bigint"), n - 1), F.lit(0.0), lambda s, j: s + 1 / (a + j))


def alpha_step(alpha: DataFrame, omega: DataFrame, len_hist: DataFrame, floor: float = 1e-6) -> DataFrame:
    """One fixed-point sweep: topic, alpha.  Work is the size of the histograms, not of the corpus."""
    total = alpha.agg(F.sum("alpha").alias("a"))
    below = len_hist.crossJoin(F.broadcast(total)).agg(F.sum(F.col("n_docs") * _harmonic(F.col("a"), F.col("len"))).alias("below"))
    above = omega.join(F.broadcast(alpha), "topic").groupBy("topic").agg(F.sum(F.col("n_docs") * _harmonic(F.col("alpha"), F.col("n"))).alias("above"))
    out = alpha.join(above, "topic", "left").crossJoin(F.broadcast(below))  # one row
    return out.select("topic", F.greatest(F.lit(floor), F.coalesce(F.col("alpha") * F.col("above") / F.col("below"), F.lit(floor))).alias("alpha"))


def optimise_alpha(alpha: list[float], omega: DataFrame, len_hist: DataFrame, *, sweeps: int = 5, floor: float = 1e-6) -> list[float]:
    """Several sweeps for a vector on the driver (length K); only the two histograms' sums are read back."""
    spark = omega.sparkSession
    for _ in range(sweeps):
        df = spark.createDataFrame(list(enumerate(alpha)), "topic int, alpha double")
        alpha = [r.alpha for r in alpha_step(df, omega, len_hist, floor).orderBy("topic").collect()]
    return alpha
