"""Connected components of a table of links, by turns of large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..sources.files import settle


def _least(links: DataFrame) -> DataFrame:
    """a, m: the smallest of each node and its neighbours; partial minima are combined before the shuffle.

    The key is an expression again, so the join deals it anew and the other side of a node with very many links can be split.
    """
    return links.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")).select(F.coalesce("a", F.lit(0)).alias("a"), "m")


def _large_star(links: DataFrame) -> DataFrame:
    """Each larger neighbour of a node is tied to the smallest of the node and its neighbours."""
    both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    return both.join(_least(both), "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()


def _small_star(links: DataFrame) -> DataFrame:
    """links: a > b.  A node and its smaller neighbours are tied to the smallest of them."""
    tied = links.join(_least(links), "a")
    own = F.struct(F.col("a").alias("a"), F.col("m").alias("b"))
    ends = F.when(F.col("b") == F.col("m"), F.array(own)).otherwise(F.array(own, F.struct(F.col("b").alias("a"), F.col("m").alias("b"))))
    return tied.select(F.explode(ends).alias("x")).select("x.a", "x.b").distinct()


def components(links: DataFrame) -> DataFrame:
    """links: a, b (long).  A row per linked node: node, label (the smallest node it reaches).

    Two rewritings alternate until nothing changes; both keep the components and
    pull nodes to smaller ones, so a path folds about in half each time.  Every
    turn is written, so lineage is cut; a node with very many links is a hot join
    key whose side comes from a written table and can be split.
    """
    now = settle(links.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    before = None
    while True:
        seen = Observation()
        # a forest of stars stays as it is, so equal sums before and after mean the end
        mark = F.xxhash64("a", "b")
        small = _small_star(_large_star(now)).observe(seen, F.count(F.lit(1)).alias("n"), F.bit_xor(mark).alias("x"), F.sum(mark.cast("decimal(20,0)")).alias("s"))
        now = settle(small, "stars")
        after = tuple(seen.get.get(k) for k in ("n", "x", "s"))
        if after == before or not after[0]:
            return now.select(F.col("a").alias("node"), F.col("b").alias("label")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())
        before = after
