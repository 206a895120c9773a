"""What the first round's advice found missing: each test fails on the code before."""

import random

from bigtopics.llm import quality, secrets
from bigtopics.llm.line_dedup import line_report


def without_repeats(rows):
    """rows: [(id, text)] in order.  Every run of two or more lines that also starts at an earlier place goes; all places are compared line by line."""
    lines = [(d, k, x) for d, t in rows for k, x in enumerate(t.split("\n"))]
    gone = set()
    for i in range(len(lines)):
        for j in range(i):
            n = 0
            while i + n < len(lines) and lines[i + n][0] == lines[i][0] and lines[j + n][0] == lines[j][0] and lines[i + n][2] == lines[j + n][2]:
                n += 1
            if n >= 2:
                gone.update(range(i, i + n))
    return {d: "\n".join(x for i, (e, _, x) in enumerate(lines) if e == d and i not in gone) for d, _ in rows}


def test_every_repeated_run_of_lines_goes(spark):
    r = random.Random(4)
    fresh = lambda n: [f"line {r.randrange(10**12)}" for _ in range(n)]
    rows, planted = [], {}
    for size in range(2, 11):
        for _ in range(6):
            passage = fresh(size)
            for _ in range(3):
                rows.append((len(rows), "\n".join(fresh(r.randrange(1, 5)) + passage + fresh(r.randrange(1, 5)))))
            planted[len(rows) - 1] = planted[len(rows) - 2] = size
    a, b = rows[0][1].split("\n"), rows[5][1].split("\n")
    rows += [(len(rows), "\n".join([*a, *b])), (len(rows) + 1, "same\nsame\nsame\nsame"), (len(rows) + 2, "x\nsame\nsame\ny\n\n\n"), (len(rows) + 3, rows[9][1]), (len(rows) + 4, "\n".join(a[:2] + b[1:3] + a[1:3]))]
    df = spark.createDataFrame([*rows, rows[3], (None, rows[4][1])], "doc_id bigint, text string").repartition(4)
    got = {x.doc_id: x for x in line_report(df, runs=True).collect()}
    want = without_repeats(rows)
    assert all(got[d].text == want[d] and got[d].n_chars == len(want[d]) for d in want) and got[None].text == ""
    assert all(got[d].n_removed_lines == n for d, n in planted.items())
    assert {x for _, t in rows for x in t.split("\n")} == {x for t in want.values() for x in t.split("\n")}
    assert {x.doc_id: x.text for x in line_report(df, runs=True, bloom_bits=64).collect()} == {d: x.text for d, x in got.items()}


def test_long_text_without_common_words_goes_and_clean_text_stays(spark):
    r = random.Random(6)
    rare = lambda: "".join(r.choice("abcdeghilmnorstu") for _ in range(r.randrange(5, 9)))
    text = lambda lang, n: " ".join(r.choice(quality.COMMON[lang]) if lang and r.random() < 0.18 else rare() for _ in range(n))
    rows = [(lang, text(lang, r.randrange(70, 400)), True) for lang in ("en", "de", "fr") for _ in range(60)]
    rows += [(lang, text(None, n), False) for lang in ("en", "de", "fr") for n in (60, 300, 1500)]
    rows += [("en", text("de", 400), False), ("de", text("fr", 400), False)]  # a wrong label
    rows += [("xx", text(None, 300), True), (None, text("fr", 300), True)]  # no list of its own
    df = spark.createDataFrame([(i, t, lang) for i, (lang, t, _) in enumerate(rows)], "doc_id bigint, text string, lang string")
    got = {x.doc_id: x.kept for x in quality.quality_report(df).collect()}
    assert [i for i, (*_, kept) in enumerate(rows) if got[i] != kept] == []
    assert quality.keep_good(df).count() == sum(x[2] for x in rows)


def test_a_value_copied_inside_one_owner_is_shared(spark):
    key = lambda k: f"aB3dE5fG7hJ9kL1mN2p{k}"
    row = lambda k, source, lang: (f"secret={key(k)} and a run {key(k)}Zy8Xx", lang, source)
    rows = [row(1, "s0", lang) for lang in ("en", "fr", "de")]  # three repositories of one owner
    rows += [row(2, "s0", "en") for _ in range(10)]  # ten documents of one repository
    rows += [row(3, "s0", "en") for _ in range(9)] + [row(4, "s0", "en"), row(4, "s1", "en")]
    rows += [(f"token={key(5)} " * 12, "en", "s0")]  # often, but in one document
    df = spark.createDataFrame([(i, *x) for i, x in enumerate(rows)], "doc_id bigint, text string, lang string, source string")
    got = [x for x in sorted(secrets.scan_secrets(df).collect(), key=lambda x: x.doc_id)]
    counts = [(x.n_shared, x.n_live, x.spans.count("owned"), x.max_owners, x.max_repos, x.max_docs) for x in got]
    assert counts == [(1, 0, 0, 1, 3, 3)] * 3 + [(1, 0, 0, 1, 1, 10)] * 10 + [(0, 2, 1, 1, 1, 9)] * 9 + [(0, 0, 0, 2, 2, 2)] * 2 + [(0, 12, 0, 1, 1, 1)]
