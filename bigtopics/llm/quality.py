"""Quality rules by distribution divergence (DataFrame functions only).

Every document gets two histograms: character classes and common words of its
language.  References are the mean histograms of each language over the whole
corpus, fitted twice: over all documents with enough words, and again over those
of them that pass by the first, so junk does not shape what it is held against.
A document with enough words is rejected if the Jensen-Shannon
distance of either histogram to its language's reference is too large; shorter
ones are judged by the base rule alone (which by default rejects them).

The limit for common words follows from the reference: it is the distance of a
document that has a twentieth of its language's share of common words, so one
without any is always beyond it.  It holds for languages with a list of their own.

Defined cases: a null text is empty (fails the base rule); a null or rare
language is held against the reference of all documents; repeated rows each get
their own result; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle, temporary, text_of, words_of

# Common words of the languages that have a list; others use the first.
COMMON = {
    "en": ("the", "of", "and", "to", "a", "in", "is", "that", "for", "it", "with", "on", "as", "are", "be", "this"),
    "fr": ("de", "la", "le", "et", "les", "des", "en", "un", "une", "du", "est", "pour", "que", "dans", "qui", "sur"),
    "de": ("der", "die", "und", "in", "den", "von", "zu", "das", "mit", "sich", "des", "auf", "für", "ist", "im", "dem"),
    "es": ("de", "la", "que", "el", "en", "y", "a", "los", "se", "del", "las", "un", "por", "con", "no", "una"),
}
N_COMMON = 16
#: The limit for common words is where a document has this part of its language's share of them.
COMMON_PART = 0.05
#: The limit is used where so many common words are expected at least; fewer may be absent by chance.
EXPECTED_COMMON = 5


def _only(col: str, kept: str) -> Column:
    """How many code points of col are of the class ``kept``; runs of all others go first, so there are few matches."""
    return F.length(F.regexp_replace(col, f"[^{kept}]+", ""))


def _histograms(docs: DataFrame, text_col: str, lang_col: str, keep: list[Column]) -> DataFrame:
    """keep, __bt_lang, __bt_text, __bt_words, __bt_rest (the text without lower-case letters), __bt_len, __bt_word_chars, and the shares __bt_chars and __bt_common.

    A common word is counted by what its removal takes from the common words set apart by two spaces; the last share is of all other words.
    """
    df = docs.select(*keep, F.col(lang_col).cast("string").alias("__bt_lang"), text_of(text_col).alias("__bt_text"))
    lists = F.create_map(*(x for k, v in COMMON.items() for x in (F.lit(k), F.array(*(F.lit(f" {w} ") for w in v)))))
    df = df.select("*", words_of(F.col("__bt_text")).alias("__bt_words"), F.regexp_replace("__bt_text", r"\p{Ll}+", "").alias("__bt_rest"), F.length("__bt_text").alias("__bt_len"))
    known = F.filter("__bt_words", lambda w: w.isin(*sorted({w for v in COMMON.values() for w in v})))
    df = df.select("*", F.length(F.array_join("__bt_words", "")).alias("__bt_word_chars"), F.concat(F.lit(" "), F.array_join(known, "  "), F.lit(" ")).alias("__bt_apart"), F.coalesce(F.try_element_at(lists, F.col("__bt_lang")), F.element_at(lists, F.lit("en"))).alias("__bt_list"))
    upper, digit, mark = (_only("__bt_rest", p) for p in (r"\p{Lu}", "0-9", r".,;:!?'()\"\-"))
    word = lambda k: F.get("__bt_list", F.lit(k))
    times = lambda k: (F.octet_length("__bt_apart") - F.octet_length(F.replace(F.col("__bt_apart"), word(k), F.lit("")))) / F.octet_length(word(k))
    df = df.select("*", F.array(F.col("__bt_len") - F.length("__bt_rest"), upper, digit, F.col("__bt_len") - F.col("__bt_word_chars"), mark).alias("__bt_c"), F.array(*map(times, range(N_COMMON))).alias("__bt_w"))
    total = lambda c, zero: F.aggregate(c, zero, lambda a, x: a + x)
    n, m = F.greatest(F.col("__bt_len"), F.lit(1)), F.greatest(F.size("__bt_words"), F.lit(1))
    chars = F.transform(F.concat("__bt_c", F.array(F.col("__bt_len") - total("__bt_c", F.lit(0)))), lambda x: x / n)
    common = F.transform(F.concat("__bt_w", F.array(m - total("__bt_w", F.lit(0.0)))), lambda x: x / m)
    return df.select("*", chars.alias("__bt_chars"), common.alias("__bt_common"))


def _repeated_at(df: DataFrame) -> DataFrame:
    """Adds __bt_at: places of the 3-word windows of __bt_words that occur twice or more, ascending (null or empty: none).

    Windows are compared by 64-bit hashes.  The two places after the last window hash fewer words and equal no window.
    """
    at = lambda a, k: F.get(F.col(a), k)
    df = df.select("*", F.when(F.size("__bt_words") >= 4, F.transform("__bt_words", lambda w, i: F.xxhash64(w, at("__bt_words", i + 1), at("__bt_words", i + 2)))).alias("__bt_grams"))
    df = df.select("*", F.when(F.size(F.array_distinct("__bt_grams")) < F.size("__bt_grams"), F.sort_array("__bt_grams")).alias("__bt_sorted"))
    df = df.select("*", F.array_distinct(F.filter("__bt_sorted", lambda h, i: h == at("__bt_sorted", i + 1))).alias("__bt_twice"))
    # few hashes that repeat are looked up one by one; many (a text of repeats) by sorting all places
    few = F.filter(F.transform("__bt_grams", lambda h, i: F.when(F.array_contains("__bt_twice", h), i)), lambda i: i.isNotNull())
    keyed = F.when(F.size("__bt_twice") > 64, F.sort_array(F.transform("__bt_grams", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    df = df.select("*", keyed.alias("__bt_keyed"))
    same = lambda z, k: F.coalesce(at("__bt_keyed", k)["h"] == z["h"], F.lit(False))
    many = F.sort_array(F.transform(F.filter("__bt_keyed", lambda z, k: same(z, k + 1) | F.when(k > 0, same(z, k - 1)).otherwise(False)), lambda z: z["i"]))
    return df.select("*", F.when(F.col("__bt_keyed").isNotNull(), many).when(F.size("__bt_twice") > 0, few).alias("__bt_at"))


def measure(docs: DataFrame, *, text_col: str = "text", lang_col: str = "lang", keep: list[Column]) -> DataFrame:
    """keep and all measures that need the document alone; each column is computed only if it is used."""
    df = _histograms(docs, text_col, lang_col, keep)
    names = [c for c in df.columns if not c.startswith("__bt_") or c == "__bt_id" or c.startswith("__bt_own_")]
    lines = F.filter(F.split("__bt_text", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    df = _repeated_at(df.select("*", lines.alias("__bt_lines")))
    covered = F.aggregate(F.sequence(F.lit(1), F.size("__bt_at")), F.lit(0), lambda s, k: s + F.coalesce(F.least(F.lit(3), F.get(F.col("__bt_at"), k) - F.get(F.col("__bt_at"), k - 1)), F.lit(3)))
    return df.select(
        *names, "__bt_lang", "__bt_chars", "__bt_common", F.size("__bt_words").cast("bigint").alias("__bt_n_words"), F.col("__bt_word_chars").cast("bigint").alias("__bt_word_chars"), _only("__bt_rest", "#*$%&|<>").cast("bigint").alias("__bt_n_symbols"),
        (F.size("__bt_lines") - F.size(F.array_distinct("__bt_lines"))).cast("bigint").alias("__bt_n_dup_lines"), F.when(F.size("__bt_at") > 0, covered).otherwise(0).cast("bigint").alias("__bt_n_repeat_words"),
    )


def fit_references(measured: DataFrame, *, min_words: int = 50, min_docs: int = 30) -> DataFrame:
    """Mean histograms of each language and of all documents (null language), over every document of min_words or more.

    Languages of fewer than min_docs documents have no row.
    """
    parts = [F.get("__bt_chars", F.lit(i)).alias(f"c{i}") for i in range(6)] + [F.get("__bt_common", F.lit(i)).alias(f"w{i}") for i in range(N_COMMON + 1)]
    flat = measured.filter(F.col("__bt_n_words") >= min_words).select("__bt_lang", *parts)
    names = flat.columns[1:]
    sums = flat.groupBy("__bt_lang").agg(F.count(F.lit(1)).alias("__bt_n"), *(F.sum(c).alias(c) for c in names))

    def pack(d: DataFrame, lang: Column) -> DataFrame:
        mean = lambda p: F.array(*(F.col(c) / F.col("__bt_n") for c in names if c[0] == p))
        out = d.select(lang.alias("__bt_lang"), mean("c").alias("__bt_ref_chars"), mean("w").alias("__bt_ref_common"))
        share = 1 - F.get("__bt_ref_common", F.lit(N_COMMON))
        few = F.transform("__bt_ref_common", lambda x, i: F.when(i < N_COMMON, x * COMMON_PART).otherwise(1 - share * COMMON_PART))
        return out.select("*", share.alias("__bt_ref_share"), js_distance(few, F.col("__bt_ref_common")).alias("__bt_ref_limit"))

    own = sums.filter((F.col("__bt_n") >= min_docs) & F.col("__bt_lang").isNotNull())
    whole = sums.agg(F.sum("__bt_n").alias("__bt_n"), *(F.sum(c).alias(c) for c in names)).filter("__bt_n > 0")
    return pack(own, F.col("__bt_lang")).unionByName(pack(whole, F.lit(None).cast("string")))


def js_distance(p: Column, q: Column) -> Column:
    """Jensen-Shannon distance (base 2, 0 to 1) of two arrays of shares."""
    term = lambda a, b: F.when(a > 0, a * F.log2(2 * a / (a + b))).otherwise(0.0)
    total = F.aggregate(F.zip_with(p, q, lambda a, b: term(a, b) + term(b, a)), F.lit(0.0), lambda s, x: s + x)
    return F.sqrt(F.greatest(total / 2, F.lit(0.0)))


def verdicts(measured: DataFrame, references: DataFrame, *, min_words: int = 50, max_js_chars: float = 0.30, max_js_common: float = 0.60) -> DataFrame:
    """measured with __bt_js_chars, __bt_js_common, __bt_base_failed and __bt_kept.

    The common-word limit is that of the language's reference, or max_js_common where that is less or the language has no list or reference of its own.
    """
    # no hint: Spark broadcasts the languages' rows while their written table is below its threshold, and shuffles beyond it
    own = references.filter("__bt_lang is not null")
    whole = F.broadcast(  # one row
        references.filter("__bt_lang is null").select(F.col("__bt_ref_chars").alias("__bt_all_chars"), F.col("__bt_ref_common").alias("__bt_all_common"), F.lit(1).alias("__bt_one")))
    df = measured.withColumn("__bt_one", F.lit(1)).join(own, "__bt_lang", "left").join(whole, "__bt_one", "left")
    distance = lambda a, own_ref, all_ref: F.coalesce(js_distance(F.col(a), F.coalesce(own_ref, all_ref)), F.lit(0.0))
    df = df.select("*", distance("__bt_chars", "__bt_ref_chars", "__bt_all_chars").alias("__bt_js_chars"), distance("__bt_common", "__bt_ref_common", "__bt_all_common").alias("__bt_js_common"))
    failed = (F.col("__bt_n_words") < 50) | (100 * F.col("__bt_n_repeat_words") > 50 * F.col("__bt_n_words"))
    listed = F.col("__bt_lang").isin(*COMMON) & (F.col("__bt_n_words") * F.col("__bt_ref_share") >= EXPECTED_COMMON)
    limit = F.least(F.lit(max_js_common), F.when(listed, F.col("__bt_ref_limit")))  # nulls are passed over
    passes = (F.col("__bt_n_words") < min_words) | ((F.col("__bt_js_chars") <= max_js_chars) & (F.col("__bt_js_common") <= limit))
    return df.select("*", failed.alias("__bt_base_failed"), (~failed & passes).alias("__bt_kept"))


def fitted(measured: DataFrame, **limits) -> DataFrame:
    """References of measured (a written table), fitted twice."""
    first = verdicts(measured, settle(fit_references(measured), "references"), **limits)
    return settle(fit_references(first.filter("__bt_kept")), "references")


def quality_report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **limits) -> DataFrame:
    """One row per input row with all measures and the verdict ``kept``."""
    measured = settle(measure(docs, text_col=text_col, lang_col=lang_col, keep=[F.col(id_col).alias("__bt_id")]), "quality")
    out = verdicts(measured, fitted(measured, **limits), **limits)
    shown = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
    return out.select(F.col("__bt_id").alias(id_col), *(F.col(f"__bt_{c}").alias(c) for c in shown), *(F.round(f"__bt_{c}", 9).alias(c) for c in ("js_chars", "js_common")))


def keep_good(docs: DataFrame, *, text_col: str = "text", lang_col: str = "lang", **limits) -> DataFrame:
    """The rows that pass, with their columns as they were.  Texts are read twice (references, verdicts), and neither written nor shuffled."""
    own, how = {c: f"__bt_own_{k}" for k, c in enumerate(docs.columns)}, {"text_col": text_col, "lang_col": lang_col}
    with temporary(docs.sparkSession) as keep:
        references = keep(fitted(settle(measure(docs, **how, keep=[]), "quality"), **limits), "references")
    judged = verdicts(measure(docs, **how, keep=[F.col(c).alias(n) for c, n in own.items()]), references, **limits)
    # the filter stays above the measures: pushed below, it would compute them once more for each use of a name
    fenced = judged.withColumn("__bt_fence", F.monotonically_increasing_id()).filter("__bt_kept and __bt_fence >= 0")
    return fenced.select(*(F.col(n).alias(c) for c, n in own.items()))
