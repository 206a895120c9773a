"""Mixing sources to target weights with a time-varying curriculum (DataFrame functions only).

1. Targets: every source gets its weight's share of all words, but at most
   ``max_repeats`` times its own words; what is cut goes to the others by
   weight.  That is a water level: one division over the sources sorted by
   cap / weight (integers up to that division).
2. Order: documents of a source are ordered by a hash.  Running word counts come
   from three steps that never gather a source in one task: counts by (source,
   hash bucket), running sums over buckets, running sums within a bucket.
3. Taking: a source's words are laid end to end, pass after pass; what lies
   before the target is taken, so the last document of the last pass may be
   taken in part (``boundary="cut"``) or is rounded (``boundary="whole"``).
4. Curriculum: over training time t in 0..1 a source's weight follows a line; its
   integral is the words asked of the source until t.  Inverting it gives each
   copy its position; output is range-sorted by it.

Defined cases: a null text has size 0; null is a source of its own, ranked last;
repeated rows are documents of their own; sources without words get target 0;
an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import settle, text_of, words_of

WEIGHTS = (5, 2, 1)
#: Slope of each weight class over training time, from -1 (fades to nothing) to 1 (starts from nothing).
SLOPES = (-0.5, 0.25, 0.75)


def source_targets(sizes: DataFrame, *, weights: tuple[int, ...] = WEIGHTS, max_repeats: int = 3) -> DataFrame:
    """One row per source: __bt_source, __bt_class, __bt_weight, __bt_source_size, __bt_target.

    sizes: __bt_source, __bt_size of each document.  Windows here run over one row per source.
    """
    by = sizes.groupBy("__bt_source").agg(F.sum("__bt_size").alias("__bt_source_size"))
    ranked = by.withColumn("__bt_class", (F.row_number().over(Window.orderBy(F.asc_nulls_last("__bt_source"))) - 1) % len(weights))
    ranked = ranked.withColumn("__bt_weight", F.get(F.array(*map(F.lit, weights)), F.col("__bt_class")).cast("bigint"))
    cap = max_repeats * F.col("__bt_source_size")
    order = Window.orderBy(F.asc("__bt_fill"), F.asc_nulls_last("__bt_source"))
    level = ranked.withColumn("__bt_cap", cap).withColumn("__bt_fill", F.col("__bt_cap") / F.col("__bt_weight"))
    level = level.select("*", F.coalesce(F.sum("__bt_cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__bt_before"), F.sum("__bt_weight").over(order.rowsBetween(0, Window.unboundedFollowing)).alias("__bt_rest"), F.sum("__bt_source_size").over(Window.partitionBy()).alias("__bt_all"))
    level = level.withColumn("__bt_level", (F.col("__bt_all") - F.col("__bt_before")) / F.col("__bt_rest"))
    # the first source that can hold its share sets the level for itself and all after it
    first = F.min(F.when(F.col("__bt_level") <= F.col("__bt_fill"), F.struct("__bt_fill", F.col("__bt_level").alias("at")))).over(Window.partitionBy())["at"]
    target = F.when(F.col("__bt_fill") < F.coalesce(first, F.lit(float("inf"))), F.col("__bt_cap").cast("double")).otherwise(first * F.col("__bt_weight"))
    return level.select("__bt_source", "__bt_class", "__bt_weight", "__bt_source_size", target.alias("__bt_target"))


def _keyed(docs: DataFrame, buckets: int, seed: int) -> DataFrame:
    """Adds __bt_key, the hash that orders documents, and __bt_bucket, its range."""
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.coalesce(F.col("__bt_id").cast("string"), F.lit("?"))).cast("binary"))
    df = docs.withColumn("__bt_key", key)
    return df.withColumn("__bt_bucket", F.floor(F.conv(F.substring("__bt_key", 1, 8), 16, 10).cast("bigint") * F.lit(buckets) / F.lit(2**32)).cast("int"))


def plan_mix(rows: DataFrame, sized: DataFrame, *, weights: tuple[int, ...] = WEIGHTS, max_repeats: int = 3, buckets: int = 1024, seed: int = 0) -> DataFrame:
    """Adds __bt_class, __bt_source_size, __bt_target, __bt_before (words of the source before this document) and __bt_taken to rows.

    rows: __bt_id, __bt_source, __bt_size and any other columns; sized: the same three columns alone, cheap to read again.
    """
    per = _keyed(sized, buckets, seed).groupBy("__bt_source", "__bt_bucket").agg(F.sum("__bt_size").alias("__bt_sum"))
    per = per.select("__bt_source", "__bt_bucket", F.coalesce(F.sum("__bt_sum").over(Window.partitionBy("__bt_source").orderBy("__bt_bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__bt_base"))
    facts = source_targets(sized, weights=weights, max_repeats=max_repeats)
    # one row per source and bucket: small beside the documents, joined without a hint
    per = per.toDF("__bt_s", "__bt_b", "__bt_base").join(facts.withColumnRenamed("__bt_source", "__bt_f"), F.col("__bt_s").eqNullSafe(F.col("__bt_f")))
    within = Window.partitionBy("__bt_source", "__bt_bucket").orderBy("__bt_key", "__bt_id", "__bt_size").rowsBetween(Window.unboundedPreceding, -1)
    local = _keyed(rows, buckets, seed).withColumn("__bt_local", F.coalesce(F.sum("__bt_size").over(within), F.lit(0)))
    joined = local.join(per, F.col("__bt_source").eqNullSafe(F.col("__bt_s")) & (F.col("__bt_bucket") == F.col("__bt_b")))
    goal = F.round("__bt_target").cast("bigint")
    start = F.col("__bt_base") + F.col("__bt_local")
    taken = sum((F.greatest(F.lit(0), F.least(F.col("__bt_size"), goal - p * F.col("__bt_source_size") - start)) for p in range(max_repeats)), F.lit(0).cast("bigint"))
    return joined.withColumn("__bt_before", start).withColumn("__bt_taken", taken)


def position_at(asked: Column, target: Column, slope: Column) -> Column:
    """Training time (0 to 1) at which a source has been asked for so many words.

    The weight is 1 + slope * (2t - 1); its integral (1 - slope) t + slope t^2 is inverted.
    """
    u = F.least(asked / target, F.lit(1.0))
    return F.when(slope == 0, u).otherwise((slope - 1 + F.sqrt((1 - slope) * (1 - slope) + 4 * slope * u)) / (2 * slope) + 0.0)


def _sized(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> list[Column]:
    return [F.col(id_col).alias("__bt_id"), F.col(source_col).cast("string").alias("__bt_source"), F.size(words_of(text_of(text_col))).cast("bigint").alias("__bt_size")]


def _placed(plan: DataFrame, slopes: tuple[float, ...]) -> DataFrame:
    slope = F.get(F.array(*(F.lit(float(s)) for s in slopes)), F.col("__bt_class") % len(slopes))
    return plan.withColumn("__bt_at", F.when(F.col("__bt_taken") > 0, position_at(F.col("__bt_before"), F.col("__bt_target"), slope)))


def mix_report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", slopes: tuple[float, ...] = SLOPES, **options) -> DataFrame:
    """One row per input row: id, size, source_size, target, taken, first_position (training time of its first copy), range-sorted by it."""
    sized = settle(docs.select(*_sized(docs, id_col, text_col, source_col)), "mix")
    plan = _placed(plan_mix(sized, sized, **options), slopes)
    return plan.orderBy(F.asc_nulls_last("__bt_at"), "__bt_id").select(F.col("__bt_id").alias(id_col), F.col("__bt_size").alias("size"), F.col("__bt_source_size").alias("source_size"), F.col("__bt_target").alias("target"), F.col("__bt_taken").alias("taken"), F.col("__bt_at").alias("first_position"))


def mix_documents(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", slopes: tuple[float, ...] = SLOPES, **options) -> DataFrame:
    """The mixed corpus in training order: each document as often as it is taken (whole copies, rounded), with the columns of docs."""
    columns = _sized(docs, id_col, text_col, source_col)
    plan = plan_mix(docs.select("*", *columns), settle(docs.select(*columns), "mix"), **options)
    slope = F.get(F.array(*(F.lit(float(s)) for s in slopes)), F.col("__bt_class") % len(slopes))
    copies = F.floor(F.col("__bt_taken") / F.greatest(F.col("__bt_size"), F.lit(1)) + 0.5).cast("int")
    each = plan.withColumn("__bt_copies", copies).filter("__bt_copies > 0").withColumn("__bt_pass", F.explode(F.sequence(F.lit(0), F.col("__bt_copies") - 1)))
    each = each.withColumn("__bt_at", position_at(F.col("__bt_before") + F.col("__bt_pass") * F.col("__bt_source_size"), F.col("__bt_target"), slope))
    return each.repartitionByRange("__bt_at", "__bt_key").sortWithinPartitions("__bt_at", "__bt_key").select(*docs.columns)
