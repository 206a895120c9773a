"""Queries against their SQL, packing's cuts, hard groups of the join, and the pipeline on odd tables."""

import random
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from bigtopics.llm import merkle, ngram_join, packing, queries

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
import brute as B  # noqa: E402
from oracle import database, differ  # noqa: E402

SF = "/root/testdata/sf0.001"
COLUMNS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_its_sql(spark, name):
    assert differ(queries.queries()[name](spark, SF), database(SF), queries.oracle_sql()[name]) is None


def test_few_documents_are_cut_and_sequences_are_full(spark):
    got = packing.pack(spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), queries.tokenizer_file()).collect()
    small = {}
    for r in got:
        if r.doc_tokens < 4096:
            small.setdefault(r.doc_id, []).append(r.length)
    used = {}
    for r in got:
        used[r.sequence_id] = used.get(r.sequence_id, 0) + r.length
    assert sum(len(v) > 1 for v in small.values()) < 0.1 * len(small)
    last = max(used)
    assert sum(4096 - n for s, n in used.items() if s != last) < 0.02 * sum(used.values())


def test_plan_sets_apart_no_more_than_the_gaps_need():
    counts = {(k, b): (50, 50 * (4096 // k - 7)) for k in (2, 5, 9) for b in range(64)}
    plan = packing.Plan.of(counts, 4096, 64)
    apart = sum(n for (k, b), (_, n) in counts.items() if b >= plan.apart_from[k > packing.LONG])
    kept = sum(n for _, n in counts.values()) - apart
    assert 0 < apart < 0.2 * kept and plan.sequences * 4096 - kept <= apart + 9 * 4096


def near_copies(n, words, changed, seed):
    """Texts that share most shingles with one another; with enough changed words no two of them link."""
    r = random.Random(seed)
    base = [f"w{r.randrange(10**6)}" for _ in range(words)]
    out = []
    for k in range(n):
        own = list(base)
        for i in r.sample(range(words), changed):
            own[i] = f"x{k}y{i}"
        out.append(" ".join(own))
    return out


@pytest.mark.parametrize("words,changed", [(150, 3), (150, 2), (400, 6)])
def test_groups_of_near_copies(spark, words, changed):
    texts = near_copies(90, words, changed, words + changed) + near_copies(40, words, 1, 5)
    want = B.components({k: B.shingles(t) for k, t in enumerate(texts)})
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    assert {r.doc_id: r.component_id for r in ngram_join.link_report(df).collect()} == want


def test_large_group_of_copies_that_do_not_link(spark):
    texts = near_copies(5000, 60, 6, 1)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(8)
    got = {r.doc_id: r.component_id for r in ngram_join.link_report(df).collect()}
    sets = {k: B.shingles(texts[k]) for k in range(300)}
    among = B.components(sets)
    assert all(got[a] == got[b] for a, b in among.items())
    assert len(set(got.values())) > 4000


def test_counts_of_shared_elements():
    import numpy as np

    r = np.random.default_rng(1)
    sets = [np.unique(r.integers(0, 60, n).astype(np.uint64)) for n in (1, 5, 30, 50, 0)]
    got = ngram_join.shared_counts(sets[:3], sets, columns=7)
    assert got.tolist() == [[len(np.intersect1d(a, b)) for b in sets] for a in sets[:3]]


def leaves(text):
    import hashlib
    import re

    cut = [[re.split(r"(?<=[.!?]) ", p) for p in s.split("\n")] for s in re.split(r"\n[ \t-\r]*\n", text)]
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    tree = [[[sha(x)[:16] for x in p] for p in s] for s in cut]
    sections = [sha("".join(sha("".join(p)) for p in s))[:16] for s in tree]
    return [x for s in tree for p in s for x in p], f"{sha(''.join(sections))}/{','.join(sections)}/{','.join(x for s in tree for p in s for x in p)}"


def test_fingerprints_against_plain_code(spark):
    texts = ["One. Two.\nThree! Four?\n\nFive.", "", "One. Two.\n \t\n Four", "a. . b\n\n\nc", "One. Two.\nThree! Four?\n\nSix."]
    df = spark.createDataFrame([(k, t, "x", "y") for k, t in enumerate(texts)], "doc_id bigint, text string, fingerprint string, n_chars string")
    assert [r.fingerprint for r in merkle.fingerprints(df).orderBy("doc_id").collect()] == [leaves(t)[1] for t in texts]
    for r in merkle.edited_report(df).collect():
        own, nxt = set(leaves(texts[r.doc_id])[0]), set(leaves(texts[(r.doc_id - 1) % len(texts)])[0])
        assert abs(r.near_next - 2 * len(own & nxt) / (len(own) + len(nxt))) < 1e-12


def table(spark, tmp_path, rows):
    spark.createDataFrame(rows, COLUMNS).repartition(2).write.parquet(f"file://{tmp_path}/documents.parquet")
    return f"file://{tmp_path}"


def test_pipeline_on_odd_rows(spark, tmp_path):
    r = random.Random(9)
    common = ("the", "of", "and", "to", "a", "in", "is", "that")
    text = lambda n: "\n".join(" ".join(r.choice(common) if r.random() < 0.3 else f"{r.choice('bcdfg')}{r.choice('aeiou')}n{r.choice('aeiou')}{r.randrange(10)}".rstrip("0123456789") + r.choice("lmnrst") for _ in range(12)) + "." for _ in range(n))
    good = [(k, text(r.randrange(6, 30)), "en", r.choice("ab")) for k in range(60)]
    rows = [*good, (100, good[0][1], "en", "a"), (101, good[1][1].replace(".", "!", 1), "en", "b"), (102, None, "en", "a"), (103, "", None, None), (None, text(9), None, None), (104, "#*$ " * 300, "en", "a"), good[5], good[5], (105, text(1500), "en", None)]
    d = table(spark, tmp_path, [(i, t, lang, s, None if t is None else len(t)) for i, t, lang, s in rows])
    docs = spark.read.parquet(f"{d}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, d)
        assert out.columns == docs.columns
        texts = {x.doc_id: x.text for x in out.collect()}
        ids = set(texts)
        if name == "quality rules":
            assert not ids & {102, 103, 104} and len(ids & set(range(60))) > 55
        if name == "line dedup":  # a copy loses all its lines, a near copy all but the changed one
            assert texts[100] == "" and texts[101].count("\n") == 0 and texts[0] == good[0][1]
        if name == "n-gram Jaccard join":
            assert {0, 1} <= ids and sum(x == good[5][1] for x in texts.values()) == 1
        if name == "source mix":
            assert 100 not in ids  # without words it is taken no time
        docs = out
    got = corpus_pipeline.run(spark, d).collect()
    assert got and {"doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"} <= set(got[0].asDict())


def test_pipeline_on_an_empty_table(spark, tmp_path):
    assert corpus_pipeline.run(spark, table(spark, tmp_path, [])).count() == 0


def test_join_equals_brute_force_on_given_texts(spark):
    rows = [(x.doc_id, x.text) for x in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    want = B.components({d: B.shingles(t) for d, t in rows})
    got = ngram_join.link_report(spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("lang", F.lit("x")))
    assert {r.doc_id: r.component_id for r in got.collect()} == want
