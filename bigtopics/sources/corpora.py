"""Corpora of short texts on the given tables: each builder gives one row per query or document."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import strip_tags, words


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sentences(documents: DataFrame) -> DataFrame:
    """Query-like corpus: doc_id, sentence (place in the document), lang, words; pieces without words are left out."""
    # words are taken inside an outer explode: a filter on an expression, also one that Spark infers for an inner explode, evaluates it once more
    each = F.transform(F.split(F.coalesce("text", F.lit("")), r"[.\n]"), lambda piece: words(piece))
    parts = documents.select("doc_id", "lang", F.posexplode_outer(each).alias("sentence", "words"))
    return parts.select("doc_id", F.col("sentence").cast("bigint"), "lang", "words").filter(F.size("words") > 0)


def query_id(df: DataFrame) -> DataFrame:
    """Adds query_id = doc_id * 2^20 + sentence, which needs no shuffle."""
    return df.withColumn("query_id", F.col("doc_id") * (1 << 20) + F.col("sentence"))


def baskets(lineitem: DataFrame) -> DataFrame:
    """Integer-only queries: an order is a document, its parts are words: doc_id, pos, word_id."""
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    return lineitem.select(F.col("l_orderkey").alias("doc_id"), (F.row_number().over(order) - 1).cast("bigint").alias("pos"), F.col("l_partkey").alias("word_id"))


def coarse_baskets(lineitem: DataFrame, part: DataFrame, column: str = "p_brand") -> DataFrame:
    """Baskets over a tiny vocabulary: doc_id, pos, word."""
    names = part.select(F.col("p_partkey").alias("word_id"), F.col(column).alias("word"))
    return baskets(lineitem).join(names, "word_id").select("doc_id", "pos", "word")


def turns(conversations: DataFrame, role: str = "user") -> DataFrame:
    """Unseen queries: conv_id, turn, words."""
    return conversations.filter(F.col("role") == role).select("conv_id", "turn", words(F.col("text")).alias("words"))


def page_words(pages: DataFrame) -> DataFrame:
    """Landing pages: page_id, words of the text without tags."""
    return pages.select("page_id", words(strip_tags(F.col("html"))).alias("words"))


def event_bags(events: DataFrame, word: str = "event_type") -> DataFrame:
    """Sessions: user_id, pos in time order, word (event_type, or the k of the JSON props)."""
    value = F.col("event_type") if word == "event_type" else F.get_json_object("props", "$.k")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events.select("user_id", (F.row_number().over(order) - 1).cast("bigint").alias("pos"), value.alias("word"))
