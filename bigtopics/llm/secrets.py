"""Secret scan with corpus-wide ownership frequency (DataFrame functions only).

Candidates are found in every whole text by Java regular expressions.  The
secret part of each candidate is hashed, and hashes are aggregated over the
whole corpus by distinct owners, repositories and documents.  A hash seen with
many of any of these is a copied example, also inside one owner; one that is not,
stays with few owners and looks random is a live-looking credential.  A value
between the two (by default: two owners, few repositories and documents) is
undecided: neither count has it.  Candidates of the wide ``owned`` kind (long mixed-case
runs with digits) are reported only if the corpus says they are live-looking;
the base kinds are always reported.

Positions: ``split`` gives the pieces between the matches that
``regexp_extract_all`` gives, so a running sum of both lengths (in code points)
yields every start without a UDF.

Defined cases: a null or empty text has no spans; null ids are kept; a null
owner or repository counts as one unknown owner or repository; repeated rows
each get their own result; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle, text_of

# The base patterns.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"(AKIA[A-Z0-9]{12,})"  # a run of 16 or more: greedy runs that are shorter can't hold a longer match
HEX = r"([0-9a-f]{32,})"
#: Long runs that hold an upper-case letter, a lower-case letter and a digit.
OWNED = r"(?<![A-Za-z0-9+/_-])((?=[A-Za-z0-9+/_-]{20})(?=[A-Za-z+/_-]*[0-9])(?=[a-z0-9+/_-]*[A-Z])(?=[A-Z0-9+/_-]*[a-z])[A-Za-z0-9+/_-]+)"
KINDS = ("assign", "access", "hex", "owned")
PLACEHOLDER = r"(?i)example|sample|dummy|changeme|your|xxxx|placeholder|redacted|12345678"

_EMPTY = "array<struct<start:bigint,rank:int,end:bigint,value:string>>"


def _spans(text: Column, found: str, parts: str, value: str, rank: int, least: int) -> Column:
    """Spans of one kind from the matches, the pieces around them and the secret parts."""
    begin = F.aggregate(
        F.sequence(F.lit(0), F.size(found) - 1),
        F.struct(F.expr("cast(array() as array<bigint>)").alias("starts"), F.lit(0).cast("bigint").alias("at")),
        lambda acc, i: F.struct(
            F.concat(acc["starts"], F.array(acc["at"] + F.length(F.get(F.col(parts), i)))).alias("starts"),
            (acc["at"] + F.length(F.get(F.col(parts), i)) + F.length(F.get(F.col(found), i))).alias("at"),
        ),
        lambda acc: acc["starts"],
    )
    each = F.transform(
        F.arrays_zip(begin.alias("b"), F.col(found).alias("m"), F.col(value).alias("v")),
        lambda x: F.struct(x["b"].alias("start"), F.lit(rank).alias("rank"), (x["b"] + F.length(x["m"])).alias("end"), x["v"].alias("value")),
    )
    return F.when(F.size(found) > 0, F.filter(each, lambda x: F.length(x["value"]) >= least)).otherwise(F.expr(f"cast(array() as {_EMPTY})"))


def find_candidates(docs: DataFrame, *, text_col: str, keep: list[Column]) -> DataFrame:
    """Per row: ``keep`` and __bt_base, __bt_owned: arrays of struct(start, rank, end, value), in order of start."""
    df = docs.select(*keep, text_of(text_col).alias("__bt_text"))
    plain = {"access": ACCESS, "hex": HEX, "owned": OWNED}
    t = F.col("__bt_text")
    df = df.select("*", F.regexp_extract_all(t, F.lit(ASSIGN), F.lit(0)).alias("__bt_m_assign"), *(F.regexp_extract_all(t, F.lit(p), F.lit(1)).alias(f"__bt_m_{k}") for k, p in plain.items()))

    def if_any(kind: str, value: Column) -> Column:
        return F.when(F.size(f"__bt_m_{kind}") > 0, value)

    df = df.select("*", if_any("assign", F.regexp_extract_all(t, F.lit(ASSIGN), F.lit(2))).alias("__bt_v_assign"), *(if_any(k, F.split(t, p, -1)).alias(f"__bt_p_{k}") for k, p in {"assign": ASSIGN, **plain}.items()))
    spans = {k: _spans(t, f"__bt_m_{k}", f"__bt_p_{k}", "__bt_v_assign" if k == "assign" else f"__bt_m_{k}", r, 8 if k == "assign" else 1).alias(f"__bt_s_{k}") for r, k in enumerate(KINDS)}
    kept = [c for c in df.columns if not c.startswith("__bt_m_") and not c.startswith("__bt_p_") and c not in ("__bt_v_assign", "__bt_text")]
    df = df.select(*kept, *spans.values())
    base = F.sort_array(F.concat("__bt_s_assign", "__bt_s_access", "__bt_s_hex"))
    df = df.select(*kept, base.alias("__bt_base"), F.col("__bt_s_owned"))
    apart = F.filter("__bt_s_owned", lambda o: ~F.exists("__bt_base", lambda b: (b["start"] < o["end"]) & (b["end"] > o["start"])))
    return df.select(*kept, "__bt_base", apart.alias("__bt_owned"))


def ownership(candidates: DataFrame) -> DataFrame:
    """Distinct owners, repositories and documents of each __bt_hash; levels of map-side combined counts, so a hot hash never meets in one task."""
    once = candidates.select("__bt_row", "__bt_hash", "__bt_owner", "__bt_repo").distinct().groupBy("__bt_hash", "__bt_owner", "__bt_repo").agg(F.count(F.lit(1)).alias("__bt_n"))
    owners = once.groupBy("__bt_hash", "__bt_owner").agg(F.count(F.lit(1)).alias("__bt_repos"), F.sum("__bt_n").alias("__bt_n"))
    return owners.groupBy("__bt_hash").agg(F.count(F.lit(1)).alias("__bt_n_owners"), F.sum("__bt_repos").alias("__bt_n_repos"), F.sum("__bt_n").alias("__bt_n_seen"))


def _joined(spans: Column) -> Column:
    names = F.array(*(F.lit(k) for k in KINDS))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["rank"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def scan_secrets(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source", repo_cols: tuple[str, ...] = ("source", "lang"), shared_from: int = 3, shared_repos_from: int = 3, shared_docs_from: int = 10, owned_up_to: int = 1, live_distinct: int = 8) -> DataFrame:
    """One row per input row: spans of all kinds and how the corpus owns them.

    ``shared_from``: owners from which a value counts as a widely copied example.
    ``shared_repos_from``, ``shared_docs_from``: distinct repositories, or documents, from which it counts as one too, whatever its owners.
    ``owned_up_to``: owners up to which a value that is not widely copied counts as owner-specific.
    ``live_distinct``: least number of different characters in a live-looking value.
    Columns: id, n_assign, n_access, n_hex, base_sha256, spans, n_shared (base
    spans that are copied examples), n_live (spans that are owner-specific and
    live-looking), max_owners, max_repos, max_docs (the largest counts of any of
    its values; 0 without values).
    """
    owner = F.coalesce(F.col(owner_col).cast("string"), F.lit("?"))
    repo = F.concat_ws("/", *(F.coalesce(F.col(c).cast("string"), F.lit("?")) for c in repo_cols))
    keep = [F.monotonically_increasing_id().alias("__bt_row"), F.col(id_col).alias("__bt_id"), owner.alias("__bt_owner"), repo.alias("__bt_repo")]
    found = settle(find_candidates(docs, text_col=text_col, keep=keep), "secrets")
    each = found.select("__bt_row", "__bt_owner", "__bt_repo", F.explode(F.concat("__bt_base", "__bt_owned")).alias("__bt_x"))
    value = F.col("__bt_x.value")
    each = each.select("__bt_row", "__bt_owner", "__bt_repo", F.col("__bt_x.start").alias("__bt_start"), F.col("__bt_x.rank").alias("__bt_rank"), F.col("__bt_x.end").alias("__bt_end"), F.sha2(value, 256).alias("__bt_hash"), ((F.size(F.array_distinct(F.split(value, ""))) >= live_distinct) & ~value.rlike(PLACEHOLDER)).alias("__bt_looks_live"))
    shared = (F.col("__bt_n_owners") >= shared_from) | (F.col("__bt_n_repos") >= shared_repos_from) | (F.col("__bt_n_seen") >= shared_docs_from)
    owned = ~shared & (F.col("__bt_n_owners") <= owned_up_to)
    live = owned & F.col("__bt_looks_live")
    wide = F.col("__bt_rank") == len(KINDS) - 1
    # written, so that the join shuffles both sides and a hot value's partition can be split
    judged = each.join(settle(ownership(each), "owners"), "__bt_hash").groupBy("__bt_row").agg(
        F.count_if(shared & ~wide).alias("__bt_shared"),
        F.count_if(live).alias("__bt_live"),
        F.collect_list(F.when(wide & live, F.struct(F.col("__bt_start").alias("start"), F.col("__bt_rank").alias("rank"), F.col("__bt_end").alias("end")))).alias("__bt_added"),
        *(F.max(f"__bt_n_{k}").alias(f"__bt_max_{k}") for k in ("owners", "repos", "seen")),
    )
    bare = F.transform("__bt_base", lambda x: F.struct(x["start"].alias("start"), x["rank"].alias("rank"), x["end"].alias("end")))
    added = F.coalesce(F.col("__bt_added"), F.expr("cast(array() as array<struct<start:bigint,rank:int,end:bigint>>)"))
    count = lambda r: F.size(F.filter("__bt_base", lambda x: x["rank"] == r)).cast("bigint")
    return found.join(judged, "__bt_row", "left").select(
        F.col("__bt_id").alias(id_col), count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"),
        F.sha2(_joined(bare), 256).alias("base_sha256"), _joined(F.sort_array(F.concat(bare, added))).alias("spans"),
        F.coalesce("__bt_shared", F.lit(0)).cast("bigint").alias("n_shared"), F.coalesce("__bt_live", F.lit(0)).cast("bigint").alias("n_live"),
        *(F.coalesce(f"__bt_max_{k}", F.lit(0)).cast("bigint").alias(f"max_{name}") for k, name in (("owners", "owners"), ("repos", "repos"), ("seen", "docs"))),
    )
