"""Every operator on a small table with nulls, empty and long texts, ties, repeated rows and clashing columns, against brute force."""

import hashlib
import random
import zlib

import brute as B
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from bigtopics.llm import html, merkle, mixing, ngram_join, packing, quality, secrets, tokens, urls
from bigtopics.llm.line_dedup import chunks_of, dedupe_lines, line_report
from bigtopics.llm.queries import tokenizer_file

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, words string, kept string, `row` string, size string"


def make_rows():
    r = random.Random(5)
    word = lambda: "".join(r.choice("abcdeghilmnorstu") for _ in range(r.randrange(1, 8)))
    text = lambda n: "\n".join(" ".join(word() for _ in range(9)) + "." for _ in range(n))
    base = [text(r.randrange(1, 12)) for _ in range(30)]
    near = []
    for t in base[:10]:
        w = t.split(" ")
        w[len(w) // 2] = "changed"
        near.append(" ".join(w))
    odd = [None, "", "   \n\t ", "one", "two words", "a b c d", "a b c d e", base[0], base[0], near[0], "x " * 3000, "Key: API_KEY = 'abcdefgh12345678' and AKIA" + "Z" * 16 + " " + "0a" * 20, "token=short secret: a:b PASSWORD:\"Sup3rLongValue99\"", "é" * 50 + " ünï\x0bcode 日本 😀 <|endoftext|>", base[1] + "\n" + base[2], base[2] + "\n" + base[1]]
    texts = base + near + odd
    rows = [(i if i != 33 else None, t, r.choice(["en", "fr", None, "xx"]), r.choice(["b", "a", "c", None, "a", "a"]), len(t or ""), "w", "k", "r", "s") for i, t in enumerate(texts)]
    return [*rows, rows[3], rows[3]]


ROWS = make_rows()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def pairs(out, col="doc_id"):
    return sorted(out, key=lambda r: (r[col] is None, r[col] or 0))


def test_secrets(docs, none):
    text = {r[0]: r[1] for r in ROWS}
    got = secrets.scan_secrets(docs).collect()
    assert len(got) == len(ROWS) and secrets.scan_secrets(none).count() == 0
    for r in got:
        base = B.base_spans(text[r.doc_id])
        assert r.base_sha256 == B.base_sha(text[r.doc_id])
        assert [r.n_assign, r.n_access, r.n_hex] == [sum(x[1] == k for x in base) for k in range(3)]
        assert set(B.spans_string(base).split(",")) <= set(r.spans.split(",")) | {""}


def test_secrets_ownership(spark):
    key = "aB3dE5fG7hJ9kL1mN2pQ4"
    rows = [(i, f"value {key} here", "en", f"s{i}") for i in range(4)] + [(9, "mine Zx8cV6bN4mQ2wE1rT3yU here", "en", "s0"), (10, "secret=Zz9Yy8Xx7Ww6Vv5", "en", "s1")]
    got = {r.doc_id: r for r in secrets.scan_secrets(spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string")).collect()}
    assert got[0].spans == "" and got[9].spans == "owned:5:25" and got[10].n_live == 1 and got[9].n_assign == 0


def test_quality(docs, none):
    text = {r[0]: r[1] for r in ROWS}
    for r in quality.quality_report(docs).collect():
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == B.quality(text[r.doc_id])
        assert not (r.base_failed and r.kept) and 0 <= r.js_chars <= 1 and 0 <= r.js_common <= 1
    assert quality.quality_report(none).count() == 0
    kept = quality.keep_good(docs)
    assert kept.columns == docs.columns and kept.count() == quality.quality_report(docs).filter("kept").count()
    assert quality.keep_good(none).count() == 0


def test_many_repeats_use_the_sorted_path(spark):
    r = random.Random(2)
    t = " ".join(r.choice("abcd") for _ in range(900))
    got = quality.quality_report(spark.createDataFrame([(1, t, "en")], "doc_id bigint, text string, lang string")).first()
    assert got.n_repeat_words == B.quality(t)[4]


def test_js_distance(spark):
    d = spark.range(1).select(quality.js_distance(F.array(F.lit(1.0), F.lit(0.0)), F.array(F.lit(0.0), F.lit(1.0))).alias("far"), quality.js_distance(F.array(F.lit(0.5), F.lit(0.5)), F.array(F.lit(0.5), F.lit(0.5))).alias("same")).first()
    assert d.far == 1 and d.same == 0


def test_urls(spark):
    cases = ["http://a.b.NET/x", "https://example.net/en/1", "http://x.example.net/de/1", "http://www.example.com/de/", "http://example.com/dex", "q://org/fr/", "http://my.org/fr/a?b#c", "http://x.net", "http://x.net?/", "nothing", None, "", "://", "http://HOST#f/x", "http://free-casino-pills.com/"]
    df = spark.createDataFrame([(i, u, "x") for i, u in enumerate(cases)], "page_id bigint, url string, host string")
    got = urls.judge_urls(df).orderBy("page_id").collect()
    for r, u in zip(got, cases, strict=True):
        assert (r.host, r.path) == urls.split_url(u)
        fits = [(len(t), t, v) for v, t in urls.RULES if (r.host == t.split("/")[0] or r.host.endswith("." + t.split("/")[0])) and r.path.startswith("/" + t.split("/", 1)[1])]
        assert r["rule"] == (max(fits)[1] if fits else None)
        assert r.verdict == (max(fits)[2] if fits else r.verdict)
    assert got[-1].verdict == "block" and got[10].verdict == "allow"
    assert urls.judge_urls(df.limit(0)).count() == 0


def test_url_model_on_held_out_rows():
    w, b = urls.fit(urls.labelled_urls())
    right = 0
    test = urls.labelled_urls(seed=99, rows=300)
    for u, y in test:
        k = urls.buckets_of(*urls.split_url(u), 15)
        right += (w[k].sum() / len(k) ** 0.5 + b >= 0) == bool(y)
    assert right / len(test) > 0.95


def test_html(spark):
    page = '<html><head><title>T</title><style>x</style><script>var a="</p>";</script></head><body><nav><ul><li><a href="/">Home</a></li><li><a>More</a></li></ul></nav><div class="ad">Buy now.</div><article><h1>Big &amp; small</h1><p>First <b>para</b>graph here,\n with  space and more words in it.<p>Second one, which is a good deal longer than that.</p><aside><ul><li><a>rel</a></li></ul></aside></article><section class="comments"><div class="comment"><p>Nice post!</p></div></section><footer>&copy; me</footer>'
    df = spark.createDataFrame([(1, "u", page), (2, None, None), (3, "v", ""), (None, "w", "<p>a<!-- b"), (5, "x", "<script>never closed"), (5, "x", "<script>never closed")], "page_id bigint, url string, html string")
    got = {(r.page_id, r.url): r for r in html.extract_main_text(df).collect()}
    assert got[1, "u"].text == "Big & small First paragraph here, with space and more words in it. Second one, which is a good deal longer than that."
    assert got[2, None].text == "" == got[5, "x"].text and got[1, "u"].n_chars == len(got[1, "u"].text)
    assert html.extract_main_text(df).count() == 6 and html.extract_main_text(df.limit(0)).count() == 0


def test_labeller_on_held_out_pages_and_its_gradient():
    test = html.training_set(60, 77)
    p = html.trained().label([x for x, _ in test])
    assert np.mean(np.concatenate([(a >= 0.5) == b for a, (_, b) in zip(p, test, strict=True)])) > 0.98
    net = html.BiLSTM(dims=5, hidden=3)
    r = np.random.default_rng(0)
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    x, mask, y = html.padded([(r.normal(size=(4, 5)), r.integers(0, 2, 4).astype(float)), (r.normal(size=(2, 5)), np.ones(2))])
    g, _ = net.gradients(x, mask, y)
    for name, at in (("xf", (1, 2)), ("hb", (0, 5)), ("out", (4,))):
        loss = []
        for e in (1e-3, -1e-3):
            net.w[name][at] += e
            loss.append(net.gradients(x, mask, y)[1])
            net.w[name][at] -= e
        assert abs((loss[0] - loss[1]) / 2e-3 - g[name][at]) < 2e-3


@pytest.fixture(scope="module")
def whole_ids():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_file())
    return {r[:2]: np.array([*t.encode(r[1] or "", add_special_tokens=False).ids, 2], "<u4") for r in ROWS}


def test_token_files(docs, none, whole_ids, tmp_path):
    files = tokens.write_tokens(docs, f"file://{tmp_path}/t", tokenizer_file())
    got = tokens.read_tokens(docs.sparkSession, files).orderBy("start").collect()
    assert len(got) == len(ROWS) and [r.doc_id for r in got] == [None, *sorted(r[0] for r in ROWS if r[0] is not None)]
    at = 0
    for r in got:
        options = [v for k, v in whole_ids.items() if k[0] == r.doc_id]
        assert r.start == at and (r.n_tokens, r.ids_crc32) in [(len(v), zlib.crc32(v.tobytes())) for v in options]
        at += r.n_tokens
    assert tokens.token_files(none, tokenizer_file()).count() == 0


def test_one_document_is_read_alone_and_damage_is_seen(tmp_path):
    path = tmp_path / "f.zst"
    with pa.OSFile(str(path), "wb") as sink:
        w = tokens.FrameWriter(sink, frame_ids=4)
        for k in range(5):
            w.add(k if k else None, np.arange(k * 3 + 1, dtype=np.uint32))
        w.close()
    raw = bytearray(path.read_bytes())
    got = tokens.FrameReader(pa.OSFile(str(path)))
    assert got.read(3).tolist() == list(range(10)) and got.find(None) == [0] and got.find(4) == [4]
    raw[int(got.at[got.first[2]]) + 12] ^= 0xFF
    path.write_bytes(raw)
    again = tokens.FrameReader(pa.OSFile(str(path)))
    assert again.read(4).tolist() == list(range(13))
    with pytest.raises(Exception):  # noqa: B017  (zstd or checksum)
        again.read(2)


def test_encoder_equals_the_tokenizer_with_any_cache():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_file())
    texts = ["", "Don't it's  THE", "naïve İstanbul ſtraße Σας", "é a\x1cd\x85e 日本", "½ ²³ 12,5%", "<|endoftext|>x", "wow!!! (yes)", "x\u00a0y"]
    for limit in (3, 10_000):
        e = tokens.Encoder(tokenizer_file(), limit)
        for _ in range(3):
            ids, n = e.encode(pa.array(texts))
            assert [x.tolist() for x in np.split(ids, np.cumsum(n)[:-1])] == [[*t.encode(x, add_special_tokens=False).ids, 2] for x in texts]


def test_mixing(docs, none):
    got = mixing.mix_report(docs).collect()
    source, text = {(r[0], r[1]): r[3] for r in ROWS}, {r[0]: r[1] for r in ROWS}
    own = {r[0]: r[3] for r in ROWS}
    sizes, taken, target = {}, {}, {}
    for r in got:
        s = own[r.doc_id]
        sizes[s] = sizes.get(s, 0) + r.size
        taken[s] = taken.get(s, 0) + r.taken
        target[s] = r.target
        assert r.size == len(B.WORD.findall(text[r.doc_id] or "")) and 0 <= r.taken <= 3 * r.size
    want = B.mix_targets(sizes)
    assert all(abs(want[s] - target[s]) < 1e-6 and abs(taken[s] - target[s]) <= 0.51 for s in sizes) and source
    again = mixing.mix_report(docs.repartition(5)).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))
    at = [r.first_position for r in got if r.first_position is not None]
    assert at == sorted(at) and mixing.mix_report(none).count() == 0
    mixed = mixing.mix_documents(docs)
    assert mixed.columns == docs.columns and mixing.mix_documents(none).count() == 0


def test_ngram_join(docs, none):
    want_sets = {i: B.shingles(r[1]) for i, r in enumerate(ROWS)}
    comp = B.components(want_sets)
    smallest = {}
    for i, c in comp.items():
        smallest.setdefault(c, []).append(ROWS[i][0])
    want = sorted(str((ROWS[i][0], len(want_sets[i]), min((d for d in smallest[c] if d is not None), default=None) if want_sets[i] else ROWS[i][0])) for i, c in comp.items())
    got = sorted(str(tuple(r)) for r in ngram_join.link_report(docs).select("doc_id", "n_shingles", "component_id").collect())
    assert got == want and ngram_join.link_report(none).count() == 0
    kept = ngram_join.keep_one(docs)
    assert kept.columns == docs.columns and kept.count() == sum(1 for i, c in comp.items() if not want_sets[i]) + len({c for i, c in comp.items() if want_sets[i]})


def test_ngram_join_on_chains_and_groups(spark):
    r = random.Random(8)
    rows, n = [], 0
    for size in (4, 6, 9, 14, 30, 60, 150):
        seed = [f"w{r.randrange(10**6)}" for _ in range(size)]
        for _ in range(14):
            rows.append((n, " ".join(seed)))
            n += 1
            for _ in range(r.randrange(1, 3)):
                k = r.randrange(len(seed) + 1)
                seed = [*seed[:k], f"w{r.randrange(10**6)}", *seed[k + (r.random() < 0.5) :]]
    want = B.components({d: B.shingles(t) for d, t in rows})
    got = {x.doc_id: x.component_id for x in ngram_join.link_report(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == want


def test_any_linked_pair_shares_a_signature():
    r = np.random.default_rng(3)
    for _ in range(1500):
        n = int(r.integers(1, 400))
        x = np.unique(r.integers(0, 2**63, n).astype(np.uint64))
        most = len(x) // 4
        y = np.unique(np.concatenate([x[r.permutation(len(x))[: len(x) - int(r.integers(0, most // 2 + 1))]], r.integers(0, 2**63, int(r.integers(0, most // 2 + 1))).astype(np.uint64)]))
        if len(y) and ngram_join.linked(*sorted((x, y), key=len)):
            a, b = sorted((x, y), key=len)
            sa, pa_, complete = ngram_join.signatures(a)
            sb, _, _ = ngram_join.signatures(b)
            assert not complete or np.intersect1d(sa[pa_], sb).size or (len(a) == len(b) and (a == b).all())


def test_line_dedup(docs, none):
    seen, want = {}, {}
    order = sorted({(r[0] is None, r[0] or 0, r[1]) for r in ROWS if r[1] is not None}, key=lambda x: x[:2])
    for none_, i, t in order:
        lines, cut = t.split("\n"), []
        for a, b, body in chunks_of(t):
            if body in seen:
                cut.append((a, b))
            seen.setdefault(body, i)
        for a, b in reversed(cut):
            del lines[a:b]
        want[None if none_ else i] = "\n".join(lines)
    got = line_report(docs).collect()
    assert len(got) == len(ROWS) and all(r.text == want.get(r.doc_id) for r in got if r.doc_id is not None)
    out = dedupe_lines(docs)
    assert out.columns == docs.columns and out.filter("n_chars <> length(text)").count() == 0 and dedupe_lines(none).count() == 0


def test_boundaries_resist_shifts():
    r = random.Random(1)
    lines = [f"line {r.randrange(10**9)}" for _ in range(200)]
    a = {b for _, _, b in chunks_of("\n".join(lines))}
    b = {b for _, _, b in chunks_of("\n".join(["inserted", *lines]))}
    assert len(a & b) >= len(a) - 2


def test_fingerprints(docs, none):
    order = sorted(((r[0] is None, -(r[0] or 0)), r) for r in ROWS)
    assert order
    unique = docs.dropDuplicates(["doc_id"])
    text = {r[0]: r[1] or "" for r in ROWS}
    ids = sorted(text, key=lambda d: (d is None, -(d or 0)))
    after = dict(zip(ids, ids[1:] + ids[:1], strict=True))
    got = merkle.edited_report(unique, ranges=7).collect()
    assert len(got) == len(text)
    for r in got:
        t = text[r.doc_id]
        h = len(t) // 2
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256((t[: len(t) - h] + text[after[r.doc_id]][:h]).encode()).hexdigest()
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    assert merkle.edited_report(docs).count() == len(ROWS) and merkle.edited_report(none).count() == 0
    prints = {r.doc_id: r.fingerprint for r in merkle.fingerprints(docs).collect()}
    assert prints[0] == prints[47] and len(set(prints.values())) == len({r[1] or "" for r in ROWS})


def test_differing_leaves_locate_an_edit(spark):
    a, b = "One. Two.\nThree. Four.\n\nFive.", "One. Two.\nThree. Changed.\n\nFive."
    d = merkle.fingerprints(spark.createDataFrame([(1, a), (2, b)], "doc_id bigint, text string")).orderBy("doc_id").collect()
    x = spark.createDataFrame([(d[0].fingerprint, d[1].fingerprint)], "a string, b string").select(merkle.differing_leaves(F.col("a"), F.col("b")).alias("at"), merkle.differing_leaves(F.col("a"), F.col("a")).alias("same")).first()
    assert x.at == [3] and x.same == []


@pytest.mark.parametrize("capacity,grain", [(4096, 64), (64, 8), (16, 16)])
def test_packing(docs, none, whole_ids, capacity, grain):
    got = packing.pack(docs, tokenizer_file(), capacity=capacity, grain=grain, buckets=4).collect()
    fill, seen = {}, 0
    for r in got:
        fill.setdefault(r.sequence_id, []).append((r.offset, r.length))
        seen += r.length
        assert any(zlib.crc32(v[r.start : r.start + r.length].tobytes()) == r.ids_crc32 and r.doc_tokens == len(v) for k, v in whole_ids.items() if k[0] == r.doc_id)
    assert seen == sum(len(whole_ids[r[:2]]) for r in ROWS)
    assert sorted(fill) == list(range(len(fill)))
    for v in fill.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= capacity
    assert len(fill) <= seen / max(capacity - grain, capacity / 2) + 2 and packing.pack(none, tokenizer_file()).count() == 0
