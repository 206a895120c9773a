"""The URL model on hosts that its word lists don't make, and the rules and n-grams against plain code."""

import re
import zlib

from bigtopics.llm import urls

GOOD = """https://www.sussex.gov.uk/council https://www.essex.ac.uk/courses https://www.betterhomes.com/ https://cashmere-shop.com/scarves
https://www.middlesbrough.gov.uk/ https://www.ox.ac.uk/research https://www.rspb.org.uk/birds https://www.nasa.gov/missions https://www.mit.edu/
https://www.lemonde.fr/politique https://www.spiegel.de/ https://www.elpais.com/ciencia https://en.wikipedia.org/wiki/Tibet https://docs.python.org/3/
https://www.dorset-walks.co.uk/ https://www.bbc.co.uk/weather https://stackoverflow.com/questions/11227809 https://www.nature.com/articles/
https://www.scunthorpe.police.uk/ https://www.winchester-cathedral.org.uk/ https://www.diabetes.org.uk/ https://www.elizabethgaskell.org/""".split()
BAD = """http://online-casino-roulette.net.co/ http://malware-download.com/setup http://bestpokercasino.info/ http://www.freeporn-xxx.com/ http://cheap-viagra-pills.org/
http://megajackpot-slots.com/win http://crackedkeygen-warez.net/ http://nude-camgirls.com/ http://paydayloans-cash.com/ http://sexyescorts-vip.com/""".split()


def score(url, model):
    w, b = model
    k = urls.buckets_of(*urls.split_url(url), 15)
    return w[k].sum() / len(k) ** 0.5 + b


def test_hosts_from_outside_the_table():
    model = urls._built_in()
    assert [u for u in GOOD if score(u, model) >= 0] == [] and [u for u in BAD if score(u, model) < 0] == []


def test_split_and_rules_against_regular_expressions(spark):
    cases = [*GOOD[:5], *BAD[:5], "http://A.b.EXAMPLE.net/en/x?y#z", "x://EXAMPLE.com/de/", "http://example.org/fr", "http://orgs/fr/", "http://example.net#/en/", "a" * 100_000 + "://" + "b" * 100_000 + "/" + "c" * 100_000, "http://x.net/" + "é" * 50_000, None, ""]
    got = urls.judge_urls(spark.createDataFrame([(i, u, "r", "v") for i, u in enumerate(cases)], "page_id bigint, url string, rule string, verdict string")).orderBy("page_id").collect()
    for r, u in zip(got, cases, strict=True):
        m = re.match(r"(?s).*?://([^/?#]*)([^?#]*)", u or "")
        assert r.host == re.sub("[A-Z]", lambda x: x[0].lower(), m[1] if m else "") and r.path == (m[2] if m else "")
        want = None
        for _, text in urls.RULES:
            host, path = text.split("/", 1)
            if re.search(rf"(^|\.){re.escape(host)}$", r.host) and r.path.startswith("/" + path) and len(text) > len(want or ""):
                want = text
        assert r["rule"] == want and r.verdict == (dict((t, v) for v, t in urls.RULES)[want] if want else "block" if r.score >= 0.5 else "allow")


def test_ngrams_against_plain_code():
    grams = {f"{m}{t[i : i + n]}" for m, t in (("h", "^a.example$"), ("p", "^/b$")) for n in (3, 4, 5, 6) for i in range(len(t) - n + 1)}
    assert urls.buckets_of("a.example", "/b", 15) == sorted({zlib.crc32(g.encode()) % (1 << 15) for g in grams})
