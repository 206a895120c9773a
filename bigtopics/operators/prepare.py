"""Corpus preparation: tokenise, rare and common words, duplicates, one-word queries, vocabulary, encoding."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rand import uniform
from ..functions.text import WORD_BREAK, words
from ..sources.files import settle


def tokenize(df: DataFrame, id_col: str, text_col: str, pattern: str = WORD_BREAK, lower: bool = True) -> DataFrame:
    """id, pos, word of each word."""
    return df.select(F.col(id_col), F.posexplode(words(F.col(text_col), pattern, lower)).alias("pos", "word")).withColumn("pos", F.col("pos").cast("bigint"))


def explode_words(queries: DataFrame, id_col: str = "query_id") -> DataFrame:
    return queries.select(id_col, F.posexplode("words").alias("pos", "word")).withColumn("pos", F.col("pos").cast("bigint"))


def word_counts(tokens: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """word, tf, df.  Occurrences are summed by (word, document) first, so a common word never meets in one task."""
    per = tokens.groupBy("word", id_col).agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy("word").agg(F.sum("n").alias("tf"), F.count(F.lit(1)).alias("df"))


def drop_rare(tokens: DataFrame, counts: DataFrame, *, min_tf: int = 0, min_df: int = 0) -> DataFrame:
    return tokens.join(counts.filter((F.col("tf") >= min_tf) & (F.col("df") >= min_df)).select("word"), "word", "left_semi")


def common_words(counts: DataFrame, *, top_n: int | None = None, max_df_ratio: float | None = None, docs: int | None = None, quantile: float | None = None) -> DataFrame:
    """The very common words: the top n by tf, those above a share of documents, or above a quantile of tf."""
    if top_n is not None:
        return counts.orderBy(F.desc("tf"), "word").limit(top_n).select("word")
    if max_df_ratio is not None:
        return counts.filter(F.col("df") > max_df_ratio * docs).select("word")
    cut = counts.agg(F.percentile_approx("tf", quantile, 100_000).alias("cut"))
    return counts.crossJoin(F.broadcast(cut)).filter("tf > cut").select("word")  # one row


def drop_common(tokens: DataFrame, common: DataFrame) -> DataFrame:
    return tokens.join(common, "word", "left_anti")


def dedupe_queries(queries: DataFrame, identity: str = "sequence", id_col: str = "query_id") -> DataFrame:
    """One query of each identity (raw text, word sequence, or word multiset): the one of smallest id."""
    text = {"raw": lambda: F.col("raw"), "sequence": lambda: F.array_join("words", " "), "bag": lambda: F.array_join(F.array_sort("words"), " ")}[identity]()
    others = [c for c in queries.columns if c != id_col]
    first = queries.withColumn("__key", F.md5(text.cast("binary"))).groupBy("__key").agg(F.min(F.struct(id_col, *others)).alias("q"))
    return first.select("q.*")


def drop_short(queries: DataFrame, min_words: int = 2, count: str = "tokens") -> DataFrame:
    size = F.size("words") if count == "tokens" else F.size(F.array_distinct("words"))
    return queries.filter(size >= min_words)


def rebuild(tokens: DataFrame, id_col: str = "query_id") -> DataFrame:
    """Queries from tokens: id, words in order."""
    return tokens.groupBy(id_col).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "word"))), lambda x: x["word"]).alias("words"))


def prepare_corpus(queries: DataFrame, *, min_tf: int = 2, top_n: int = 20, identity: str = "sequence", min_words: int = 2) -> tuple[DataFrame, DataFrame]:
    """The five cleaning steps in order; returns the clean queries and an audit row per step (step, queries, tokens)."""
    tokens = explode_words(queries)
    counts = settle(word_counts(tokens, "query_id"), "counts")  # read by two steps
    frequent = drop_rare(tokens, counts, min_tf=min_tf)
    usual = drop_common(frequent, common_words(counts, top_n=top_n))
    unique = dedupe_queries(rebuild(usual), identity)
    clean = drop_short(unique, min_words)

    def audit(step: int, name: str, df: DataFrame, packed: bool) -> DataFrame:
        q = F.count(F.lit(1)) if packed else F.count_distinct("query_id")
        n = F.coalesce(F.sum(F.size("words")), F.lit(0)) if packed else F.count(F.lit(1))
        return df.agg(q.alias("queries"), n.cast("bigint").alias("tokens")).select(F.lit(step).cast("bigint").alias("step"), F.lit(name).alias("name"), "queries", "tokens")

    steps = [audit(1, "tokenise", tokens, False), audit(2, "rare", frequent, False), audit(3, "common", usual, False), audit(4, "duplicates", unique, True), audit(5, "short", clean, True)]
    return clean, reduce(DataFrame.union, steps)


def build_vocab(counts: DataFrame, parts: int = 32) -> DataFrame:
    """word, word_id, tf, df: dense ids by descending tf, then word.

    Ids come from range-sorted partitions: rank within the partition plus the
    sizes of the partitions before it, so no single task sees all words.
    """
    ranged = settle(counts.repartitionByRange(parts, F.desc("tf"), "word").withColumn("__p", F.spark_partition_id()), "ranged")
    local = ranged.withColumn("__r", F.row_number().over(Window.partitionBy("__p").orderBy(F.desc("tf"), "word")))
    sizes = ranged.groupBy("__p").agg(F.count(F.lit(1)).alias("__n"))
    base = sizes.select("__p", (F.sum("__n").over(Window.orderBy("__p")) - F.col("__n")).alias("__b"))  # one row per partition
    return local.join(F.broadcast(base), "__p").select("word", (F.col("__r") - 1 + F.col("__b")).cast("bigint").alias("word_id"), "tf", "df")


def encode(tokens: DataFrame, vocab: DataFrame) -> DataFrame:
    """word replaced by word_id; words outside the vocabulary are dropped."""
    return tokens.join(vocab.select("word", "word_id"), "word").drop("word")


def pack(tokens: DataFrame, *, id_col: str = "doc_id", values: tuple[str, ...] = ("word_id", "z")) -> DataFrame:
    """One row per document with aligned arrays."""
    rows = F.array_sort(F.collect_list(F.struct("pos", *values)))
    out = tokens.groupBy(id_col).agg(rows.alias("r"))
    return out.select(id_col, *(F.col("r")[v].alias(v + "s") for v in values))


def unpack(packed: DataFrame, *, id_col: str = "doc_id", values: tuple[str, ...] = ("word_id", "z")) -> DataFrame:
    each = packed.select(id_col, F.posexplode(F.arrays_zip(*(F.col(v + "s") for v in values))).alias("pos", "x"))
    return each.select(id_col, F.col("pos").cast("bigint"), *(F.col("x." + v + "s").alias(v) for v in values))


def corpus_stats(tokens: DataFrame, id_col: str = "doc_id", word_col: str = "word_id") -> DataFrame:
    """docs, words, tokens, average length."""
    per = tokens.groupBy(id_col).agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("tokens"))
    kinds = tokens.select(word_col).distinct().agg(F.count(F.lit(1)).alias("words"))
    return per.crossJoin(kinds).select("docs", "words", "tokens", F.round(F.col("tokens") / F.col("docs"), 6).alias("avg_len"))  # one row each


def split_holdout(corpus: DataFrame, id_col: str, *, frac: float = 0.1, seed: int = 7, length_col: str | None = None, groups: int = 20) -> DataFrame:
    """Adds part (train or test) by a draw for each id; with length_col also grp, the length group (ntile)."""
    out = corpus.withColumn("part", F.when(uniform(id_col, seed=seed) < frac, "test").otherwise("train"))
    if length_col:
        # quantile cuts of the lengths, not a window over all rows
        per = corpus.groupBy(length_col).agg(F.count(F.lit(1)).alias("__n"))
        w = Window.orderBy(length_col).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        cum = per.withColumn("__c", F.sum("__n").over(w)).withColumn("__t", F.sum("__n").over(Window.partitionBy()))
        cuts = cum.select(length_col, F.least(F.lit(groups), F.floor((F.col("__c") - F.col("__n") / 2) * groups / F.col("__t")) + 1).cast("bigint").alias("grp"))
        out = out.join(cuts, length_col)
    return out
