"""Counts of labelled tokens, the multinomials they give, and the joint objective."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rand import uniform


def init_topics(tokens: DataFrame, topics: int, seed: int = 7) -> DataFrame:
    """tokens with a first label z drawn for (document, place)."""
    return tokens.withColumn("z", F.floor(uniform(0, "doc_id", "pos", seed=seed) * topics).cast("int"))


def count_doc_topic(tokens_z: DataFrame) -> DataFrame:
    return tokens_z.groupBy("doc_id", F.col("z").alias("topic")).agg(F.count(F.lit(1)).alias("n"))


def count_word_topic(tokens_z: DataFrame) -> DataFrame:
    return tokens_z.groupBy("word_id", F.col("z").alias("topic")).agg(F.count(F.lit(1)).alias("n"))


def count_topic(tokens_z: DataFrame) -> DataFrame:
    return tokens_z.groupBy(F.col("z").alias("topic")).agg(F.count(F.lit(1)).alias("n"))


def all_counts(tokens_z: DataFrame) -> DataFrame:
    """Document-topic, word-topic and topic counts in one pass: kind, id, topic, n."""
    t = tokens_z.select("doc_id", "word_id", F.col("z").alias("topic"))
    sets = t.groupingSets([[F.col("doc_id"), F.col("topic")], [F.col("word_id"), F.col("topic")], [F.col("topic")]], "doc_id", "word_id", "topic")
    out = sets.agg(F.count(F.lit(1)).alias("n"), F.grouping("doc_id").alias("gd"), F.grouping("word_id").alias("gw"))
    return out.select(F.when(F.col("gd") == 0, "theta").when(F.col("gw") == 0, "phi").otherwise("psi").alias("kind"), F.coalesce("doc_id", "word_id", F.lit(-1)).alias("id"), "topic", "n")


def flat_alpha(psi: DataFrame, alpha: float) -> DataFrame:
    return psi.select("topic", F.lit(float(alpha)).alias("alpha"))


def doc_topic_prob(theta: DataFrame, alpha: DataFrame) -> DataFrame:
    """doc_id, topic, p on the support; a topic outside it has alpha / (length + total)."""
    total = alpha.agg(F.sum("alpha").alias("total"))
    length = theta.groupBy("doc_id").agg(F.sum("n").alias("len"))
    joined = theta.join(length, "doc_id").join(F.broadcast(alpha), "topic").crossJoin(F.broadcast(total))
    return joined.select("doc_id", "topic", ((F.col("n") + F.col("alpha")) / (F.col("len") + F.col("total"))).alias("p"))


def word_topic_prob(phi: DataFrame, psi: DataFrame, beta: float, vocab_size: int) -> DataFrame:
    """word_id, topic, p on the support, and the topic's background for all other words."""
    den = F.col("total") + F.lit(beta * vocab_size)
    joined = phi.join(F.broadcast(psi.select("topic", F.col("n").alias("total"))), "topic")
    return joined.select("word_id", "topic", ((F.col("n") + beta) / den).alias("p"), (F.lit(beta) / den).alias("background"))


def _log_rising(a: Column, n: Column) -> Column:
    """log(a (a+1) ... (a+n-1)) as a sum over steps; callers group equal counts first."""
    return F.aggregate(F.sequence(F.lit(0).cast("bigint"), n - 1), F.lit(0.0), lambda s, j: s + F.log(a + j))


def joint_log_likelihood(tokens_z: DataFrame, alpha: float, beta: float, topics: int, vocab_size: int) -> DataFrame:
    """ll: log of the collapsed joint of words and labels, symmetric prior.  Equal counts are grouped, so each sum is done once."""
    def part(df: DataFrame, a: float, sign: int) -> DataFrame:
        return df.groupBy("n").agg(F.count(F.lit(1)).alias("m")).select((sign * F.col("m") * _log_rising(F.lit(a), F.col("n"))).alias("x"))

    theta, phi, psi = count_doc_topic(tokens_z), count_word_topic(tokens_z), count_topic(tokens_z)
    length = theta.groupBy("doc_id").agg(F.sum("n").alias("n"))
    parts = part(theta, alpha, 1).union(part(length, alpha * topics, -1)).union(part(phi, beta, 1)).union(part(psi, beta * vocab_size, -1))
    return parts.agg(F.round(F.sum("x"), 4).alias("ll"))


def model_footprint(phi: DataFrame, shards: int, topics: int) -> DataFrame:
    """Per word shard: words, entries, bytes of packed rows (8 an entry), bytes of a dense matrix (4 a cell)."""
    rows = phi.groupBy("word_id").agg(F.count(F.lit(1)).alias("entries"))
    per = rows.groupBy(F.pmod("word_id", F.lit(shards)).cast("bigint").alias("shard")).agg(F.count(F.lit(1)).alias("words"), F.sum("entries").alias("entries"))
    return per.select("shard", "words", "entries", (F.col("entries") * 8 + F.col("words") * 8).alias("bytes"), (F.col("words") * 4 * topics).alias("dense_bytes"))


def topic_shares(theta: DataFrame) -> DataFrame:
    """Entropy of each topic's spread over documents is a sign of generality: topic, entropy."""
    p = F.col("n") / F.sum("n").over(Window.partitionBy("topic"))
    return theta.withColumn("p", p).groupBy("topic").agg(F.round(-F.sum(F.col("p") * F.log("p")), 6).alias("entropy"))
