"""Document fingerprints: Merkle trees over sentences, paragraphs and sections (DataFrame functions only).

Leaves are sentences of a paragraph (a line); the hash of a paragraph covers its
leaves' hashes, that of a section (paragraphs up to a blank line) its
paragraphs', and the root the sections'.  Roots test equality.  The fingerprint
carries root, section and leaf hashes, so differing sections, and in them
differing leaves, locate an edit, and the share of common leaves is a likeness.

``edited_report`` pairs each document with the next one in descending order of
id.  Ids are cut into ranges at quantiles; a range's rows and the first row of
the range below meet in one window, so texts are shuffled once and no window
spans the table.

Defined cases: a null text is empty, and has one leaf: the empty text; null ids
come last in the order; repeated ids are ordered by a hash of their text; a lone
document is its own next one; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_of

HEX = 16  # hexadecimal digits kept of the hash of a leaf or section


def _hash(text: Column) -> Column:
    return F.sha2(text, 256)


def _leaves_of(section: Column) -> Column:
    """Array (paragraphs) of arrays (leaves) of hashes."""
    return F.transform(F.split(section, "\n", -1), lambda p: F.transform(F.split(p, r"(?<=[.!?])\x20", -1), lambda x: F.substring(_hash(x), 1, HEX)))


def with_tree(df: DataFrame, text: str, name: str) -> DataFrame:
    """Adds {name}_leaves (all leaf hashes in order) and {name}_print, the fingerprint root/sections/leaves."""
    df = df.withColumn(f"{name}_tree", F.transform(F.split(text, r"\n[\x20\x09-\x0D]*\n", -1), lambda s: _leaves_of(s)))
    df = df.withColumn(f"{name}_sections", F.transform(f"{name}_tree", lambda s: F.substring(_hash(F.array_join(F.transform(s, lambda p: _hash(F.array_join(p, ""))), "")), 1, HEX)))
    df = df.withColumn(f"{name}_leaves", F.flatten(F.flatten(f"{name}_tree")))
    mark = F.concat_ws("/", _hash(F.array_join(f"{name}_sections", "")), F.array_join(f"{name}_sections", ","), F.array_join(f"{name}_leaves", ","))
    return df.withColumn(f"{name}_print", mark).drop(f"{name}_tree", f"{name}_sections")


def likeness(a: Column, b: Column) -> Column:
    """Share of common leaves of two arrays of leaf hashes (different ones count once), 0 to 1."""
    both = F.size(F.array_intersect(a, b))
    return (2 * both / (F.size(F.array_distinct(a)) + F.size(F.array_distinct(b)))).cast("double")


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_chars, fingerprint."""
    df = docs.select(F.col(id_col).alias("__bt_id"), text_of(text_col).alias("__bt_text"))
    out = with_tree(df, "__bt_text", "__bt_f")
    return out.select(F.col("__bt_id").alias(id_col), F.length("__bt_text").cast("bigint").alias("n_chars"), F.col("__bt_f_print").alias("fingerprint"))


def differing_leaves(a: Column, b: Column) -> Column:
    """Places (from 0) of the leaves of fingerprint a that b lacks; empty when the roots agree."""
    leaves = lambda f: F.split(F.element_at(F.split(f, "/"), 3), ",")
    root = lambda f: F.element_at(F.split(f, "/"), 1)
    missing = F.filter(F.transform(leaves(a), lambda x, i: F.when(~F.array_contains(leaves(b), x), i)), lambda i: i.isNotNull())
    return F.when(root(a) == root(b), F.expr("cast(array() as array<int>)")).otherwise(missing)


def _ranges(docs: DataFrame, id_col: str, ranges: int) -> tuple[list[int], list[tuple[int, int | None]]]:
    """Cuts between ranges of ids, and the (range, largest id) of each range that has rows; at most ``ranges`` + 1 values each."""
    ids = docs.select(F.col(id_col).cast("bigint").alias("id"))
    cuts = ids.agg(F.percentile_approx("id", [k / ranges for k in range(1, ranges)], 20 * ranges).alias("c")).first()["c"] or []
    cuts = sorted(set(cuts))
    tops = ids.groupBy(_range_of(F.col("id"), cuts).alias("r")).agg(F.max("id").alias("top")).collect()
    return cuts, sorted((r.r, r.top) for r in tops)


def _range_of(i: Column, cuts: list[int]) -> Column:
    """0 holds the largest ids; null ids are in the last range."""
    if not cuts:
        return F.when(i.isNull(), 1).otherwise(0)
    # binary search over a constant array, one step for each bit of its length
    table = F.array(*(F.lit(c).cast("bigint") for c in cuts))
    steps = F.array(*(F.lit(1 << k) for k in range(len(cuts).bit_length() - 1, -1, -1)))
    below = F.aggregate(steps, F.lit(0), lambda low, s: low + F.when(F.get(table, low + s - 1) < i, s).otherwise(0))
    return F.when(i.isNull(), len(cuts) + 1).otherwise(len(cuts) - below)


def edited_report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", ranges: int | None = None) -> DataFrame:
    """One row per input row: id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text has its last floor(n / 2) code points replaced by the first as many of the next document.
    ``ranges`` (default: 8 for each shuffle partition) bounds what the driver reads: one number for each.
    """
    spark = docs.sparkSession
    ranges = ranges or 8 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    cuts, tops = _ranges(docs, id_col, ranges)
    df = docs.select(F.col(id_col).cast("bigint").alias("__bt_id"), text_of(text_col).alias("__bt_text"), F.col(id_col).alias("__bt_own"))
    df = df.withColumn("__bt_range", _range_of(F.col("__bt_id"), cuts))
    # the first rows of a range also go to the range before it, and those of the first range to the last
    to, top = [None] * (len(cuts) + 2), [None] * (len(cuts) + 2)
    for k, (r, largest) in enumerate(tops):
        to[r], top[r] = tops[k - 1][0], largest
    look = lambda values, kind: F.get(F.array(*(F.lit(v).cast(kind) for v in values)), F.col("__bt_range"))
    first = F.when(F.col("__bt_id").eqNullSafe(look(top, "bigint")), look(to, "int"))
    own = F.struct(F.col("__bt_range").alias("r"), F.lit(0).alias("guest"))
    df = df.withColumn("__bt_to", F.explode(F.when(first.isNull(), F.array(own)).otherwise(F.array(own, F.struct(first.alias("r"), F.lit(1).alias("guest"))))))
    df = df.select("__bt_id", "__bt_own", "__bt_text", F.xxhash64("__bt_text").alias("__bt_tie"), F.col("__bt_to.r").alias("__bt_r"), F.col("__bt_to.guest").alias("__bt_guest"))
    order = Window.partitionBy("__bt_r").orderBy("__bt_guest", F.desc_nulls_last("__bt_id"), "__bt_tie")
    df = df.withColumn("__bt_next", F.lead("__bt_text").over(order)).filter("__bt_guest = 0")
    half = F.floor(F.length("__bt_text") / 2).cast("int")
    df = df.withColumn("__bt_edited", F.concat(F.substring(F.col("__bt_text"), F.lit(1), F.length("__bt_text") - half), F.substring(F.coalesce("__bt_next", "__bt_text"), F.lit(1), half)))
    df = with_tree(with_tree(df, "__bt_text", "__bt_a"), "__bt_edited", "__bt_b").withColumn("__bt_c_leaves", F.flatten(F.flatten(F.transform(F.split(F.coalesce("__bt_next", "__bt_text"), r"\n[\x20\x09-\x0D]*\n", -1), lambda s: _leaves_of(s)))))
    return df.select(
        F.col("__bt_own").alias(id_col), F.length("__bt_text").cast("bigint").alias("n_chars"), _hash(F.col("__bt_edited")).alias("edited_sha256"), F.col("__bt_a_print").alias("fingerprint"), F.col("__bt_b_print").alias("edited_fingerprint"),
        likeness(F.col("__bt_a_leaves"), F.col("__bt_b_leaves")).alias("near_edited"), likeness(F.col("__bt_a_leaves"), F.col("__bt_c_leaves")).alias("near_next"),
    )
