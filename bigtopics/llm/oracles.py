"""DuckDB SQL for the queries that SQL can express: op1, op2, op6 and op9 (default parameters)."""

from __future__ import annotations

from .mixing import SLOPES, WEIGHTS
from .quality import COMMON, COMMON_PART, EXPECTED_COMMON

_WORD = r"[^\x20\x09-\x0D]+"
_MARKS = r""".,;:!?''()"\-"""
_LINES = "string_split({0}, chr(10))"


def _case(word: str) -> str:
    return "".join(f"[{c.lower()}{c.upper()}]" if c.isalpha() else c for c in word)


def secrets_sql() -> str:
    names = "|".join(_case(w) for w in ("password", "passwd", "secret", "token")) + "|" + _case("api") + "_?" + _case("key")
    assign = rf"""({names})["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)"""
    kinds = (("assign", assign, 2, "len >= 8"), ("access", "AKIA[A-Z0-9]+", 0, "len >= 16"), ("hex", "[0-9a-f]+", 0, "len >= 32"), ("owned", "[A-Za-z0-9+/_-]+", 0, "len >= 20 AND regexp_matches(value, '[0-9]') AND regexp_matches(value, '[A-Z]') AND regexp_matches(value, '[a-z]')"))

    def spans(rank: int, kind: str, pattern: str, group: int, keep: str) -> str:
        return f"""SELECT r, {rank} AS rank, '{kind}' AS kind, start, start + length(m) AS "end", value FROM (
  SELECT r, m, value, length(value) AS len, sum(length(piece) + coalesce(length(before), 0)) OVER (PARTITION BY r ORDER BY i) AS start FROM (
    SELECT r, i, ms[i] AS m, vs[i] AS value, pieces[i] AS piece, CASE WHEN i > 1 THEN ms[i - 1] END AS before FROM (
      SELECT r, ms, vs, pieces, unnest(range(1, len(ms) + 1)) AS i FROM (
        SELECT r, regexp_extract_all(t, '{pattern}') AS ms, regexp_extract_all(t, '{pattern}', {group}) AS vs, string_split_regex(t, '{pattern}') AS pieces FROM d)))) WHERE {keep}"""

    found = " UNION ALL ".join(spans(k, *x) for k, x in enumerate(kinds))
    return f"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, coalesce(source, '?') AS owner, coalesce(source, '?') || '/' || coalesce(lang, '?') AS repo FROM documents),
s AS ({found}),
e AS (SELECT * FROM s WHERE rank < 3 UNION ALL SELECT * FROM s AS o WHERE rank = 3 AND NOT EXISTS (SELECT 1 FROM s AS b WHERE b.r = o.r AND b.rank < 3 AND b.start < o."end" AND b."end" > o.start)),
own AS (SELECT value, count(DISTINCT owner) AS owners, count(DISTINCT repo) AS repos, count(DISTINCT r) AS docs FROM e JOIN d USING (r) GROUP BY value),
j AS (SELECT e.*, owners, repos, docs, (owners >= 3 OR repos >= 3 OR docs >= 10) AS shared,
  len(list_distinct(string_split(value, ''))) >= 8 AND NOT regexp_matches(lower(value), 'example|sample|dummy|changeme|your|xxxx|placeholder|redacted|12345678') AS looks FROM e JOIN own USING (value)),
v AS (SELECT *, (NOT shared AND owners <= 1 AND looks) AS live FROM j),
g AS (SELECT r, count(*) FILTER (rank = 0) AS n_assign, count(*) FILTER (rank = 1) AS n_access, count(*) FILTER (rank = 2) AS n_hex,
  string_agg(kind || ':' || start || ':' || "end", ',' ORDER BY start, rank, "end") FILTER (rank < 3) AS base,
  string_agg(kind || ':' || start || ':' || "end", ',' ORDER BY start, rank, "end") FILTER (rank < 3 OR live) AS spans,
  count(*) FILTER (shared AND rank < 3) AS n_shared, count(*) FILTER (live) AS n_live, max(owners) AS max_owners, max(repos) AS max_repos, max(docs) AS max_docs FROM v GROUP BY r)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans,
  coalesce(n_shared, 0) AS n_shared, coalesce(n_live, 0) AS n_live, coalesce(max_owners, 0) AS max_owners, coalesce(max_repos, 0) AS max_repos, coalesce(max_docs, 0) AS max_docs FROM d LEFT JOIN g USING (r)"""


def _js(p: str, q: str) -> str:
    """Jensen-Shannon distance of two lists of shares."""
    term = lambda a, b: f"CASE WHEN {a} > 0 THEN {a} * log2(2 * {a} / ({a} + {b})) ELSE 0.0 END"
    x, y = "z[1]", "z[2]"
    return f"sqrt(greatest(list_sum(list_transform(list_zip({p}, {q}), lambda z: {term(x, y)} + {term(y, x)})) / 2, 0.0))"


def _judged(name: str, refs: str) -> str:
    """CTEs: {name} is h with its distances to the references and ``passes``."""
    share = "(1 - rw[17])"
    few = f"list_transform(list_zip(rw, range(1, 18)), lambda z: CASE WHEN z[2] < 17 THEN z[1] * {COMMON_PART} ELSE 1 - {share} * {COMMON_PART} END)"
    listed = ", ".join(f"'{k}'" for k in COMMON)
    return f"""{name}_own AS (SELECT lang AS own_lang, rc, rw, {share} AS share, {_js(few, 'rw')} AS lim FROM {refs} WHERE NOT whole AND docs >= 30 AND lang IS NOT NULL),
{name}_at AS (SELECT h.*, o.share, o.lim, coalesce({_js('h.chars', 'coalesce(o.rc, a.rc)')}, 0.0) AS js_chars, coalesce({_js('h.common', 'coalesce(o.rw, a.rw)')}, 0.0) AS js_common
  FROM h LEFT JOIN {name}_own AS o ON h.lang = o.own_lang LEFT JOIN (SELECT * FROM {refs} WHERE whole AND docs > 0) AS a ON true),
{name} AS (SELECT *, n_words < 50 OR (js_chars <= 0.30 AND js_common <= least(0.60, CASE WHEN lang IN ({listed}) AND n_words * share >= {EXPECTED_COMMON} THEN lim END)) AS passes FROM {name}_at)"""


def quality_sql() -> str:
    """References are fitted twice: on all long documents, then on those that pass by the first."""
    lists = "CASE lang " + " ".join(f"WHEN '{k}' THEN {list(v)!r}" for k, v in COMMON.items()) + f" ELSE {list(COMMON['en'])!r} END"
    mean = lambda c, n: "[" + ", ".join(f"avg({c}[{i}])" for i in range(1, n + 1)) + "]"
    only = lambda c: f"length(regexp_replace(t, '[^{c}]+', '', 'g'))"
    fitted = lambda rows: f"(SELECT lang, grouping(lang) = 1 AS whole, count(*) AS docs, {mean('chars', 6)} AS rc, {mean('common', 17)} AS rw FROM {rows} GROUP BY GROUPING SETS ((lang), ()))"
    return rf"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t FROM documents),
w AS (SELECT *, regexp_extract_all(t, '{_WORD}') AS ws, {lists} AS common_list FROM d),
gram AS (SELECT r, i, ws[i] AS a, ws[i + 1] AS b, ws[i + 2] AS c FROM (SELECT r, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, a, b, c) AS n FROM gram) WHERE n > 1),
rep AS (SELECT r, count(DISTINCT i + k) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS k) GROUP BY r),
m AS (SELECT r, doc_id, lang, len(ws) AS n_words, length(array_to_string(ws, '')) AS word_chars, {only('#*$%&|<>')} AS n_symbols,
  list_filter({_LINES.format('t')}, lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines, coalesce(rep.n, 0) AS n_repeat_words, length(t) AS n,
  [length(t) - length(regexp_replace(t, '\p{{Ll}}+', '', 'g')), {only(r'\p{Lu}')}, {only('0-9')}, length(t) - length(array_to_string(ws, '')), {only(_MARKS)}] AS c,
  list_transform(common_list, lambda x: len(list_filter(ws, lambda y: y = x))) AS k FROM w LEFT JOIN rep USING (r)),
h AS (SELECT *, list_transform(list_append(c, (n - list_sum(c))::BIGINT), lambda x: x / greatest(n, 1)) AS chars, list_transform(list_append(k, (greatest(n_words, 1) - list_sum(k))::BIGINT), lambda x: x / greatest(n_words, 1)) AS common,
  n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m),
fit1 AS {fitted('(SELECT * FROM h WHERE n_words >= 50)')}, {_judged('early', 'fit1')},
fit2 AS {fitted('(SELECT * FROM early WHERE n_words >= 50 AND NOT base_failed AND passes)')}, {_judged('late', 'fit2')}
SELECT doc_id, n_words, word_chars, n_symbols, len(lines) - len(list_distinct(lines)) AS n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND passes AS kept, round(js_chars, 9) AS js_chars, round(js_common, 9) AS js_common FROM late"""


def mix_sql() -> str:
    pick = lambda values: f"{list(values)!r}[cls + 1]"
    taken = " + ".join(f"greatest(0, least(size, goal - {p} * source_size - start))" for p in range(3))
    return f"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{_WORD}')) AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % {len(WEIGHTS)} AS cls FROM d GROUP BY source),
c AS (SELECT *, {pick(WEIGHTS)} AS weight, 3 * source_size AS cap, 3 * source_size / {pick(WEIGHTS)} AS fill FROM s),
l AS (SELECT *, ((SELECT sum(size) FROM d) - coalesce(sum(cap) OVER (ORDER BY fill, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE / sum(weight) OVER (ORDER BY fill, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM c),
f AS (SELECT min(level) AS water, min(fill) AS from_fill FROM (SELECT level, fill FROM l WHERE level <= fill ORDER BY fill, level LIMIT 1)),
t AS (SELECT source, source_size, cls, CASE WHEN from_fill IS NULL OR fill < from_fill THEN cap::DOUBLE ELSE water * weight END AS target FROM l, f),
p AS (SELECT d.*, source_size, cls, target, round(target)::BIGINT AS goal, coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY md5('0|' || coalesce(doc_id::VARCHAR, '?')), doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
x AS (SELECT *, ({taken})::BIGINT AS taken, {pick(SLOPES)}::DOUBLE AS slope FROM p)
SELECT doc_id, size::BIGINT AS size, source_size, target, taken, CASE WHEN taken > 0 THEN (slope - 1 + sqrt((1 - slope) * (1 - slope) + 4 * slope * least(start / target, 1.0))) / (2 * slope) + 0.0 END AS first_position FROM x"""


def merkle_sql() -> str:
    cut = "chr(57345)"
    leaves_of = lambda s: f"list_transform({_LINES.format(s)}, lambda p: list_transform(string_split(regexp_replace(p, '([.!?])\\x20', '\\1' || {cut}, 'g'), {cut}), lambda q: substr(sha256(q), 1, 16)))"
    tree = lambda t: f"list_transform(string_split_regex({t}, '\\n[\\x20\\x09-\\x0D]*\\n'), lambda s: {leaves_of('s')})"
    sections = lambda n: f"list_transform({n}, lambda s: substr(sha256(array_to_string(list_transform(s, lambda p: sha256(array_to_string(p, ''))), '')), 1, 16))"
    mark = lambda n: f"sha256(array_to_string({n}_s, '')) || '/' || array_to_string({n}_s, ',') || '/' || array_to_string({n}_l, ',')"
    like = lambda a, b: f"(2 * len(list_intersect({a}_l, {b}_l)) / (len(list_distinct({a}_l)) + len(list_distinct({b}_l))))::DOUBLE"
    parts = ", ".join(f"{sections(f'{n}_t')} AS {n}_s, flatten(flatten({n}_t)) AS {n}_l" for n in "abc")
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t, coalesce(lead(coalesce(text, '')) OVER o, first(coalesce(text, '')) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) AS nxt FROM documents WINDOW o AS (ORDER BY doc_id DESC NULLS LAST)),
e AS (SELECT doc_id, t, nxt, length(t) AS n, substr(t, 1, (length(t) - length(t) // 2)::BIGINT) || substr(nxt, 1, (length(t) // 2)::BIGINT) AS edited FROM d),
x AS (SELECT doc_id, n, edited, {tree('t')} AS a_t, {tree('edited')} AS b_t, {tree('nxt')} AS c_t FROM e),
y AS (SELECT doc_id, n, edited, {parts} FROM x)
SELECT doc_id, n AS n_chars, sha256(edited) AS edited_sha256, {mark('a')} AS fingerprint, {mark('b')} AS edited_fingerprint, {like('a', 'b')} AS near_edited, {like('a', 'c')} AS near_next FROM y"""
