"""URL filter: rules on host and path first, then logistic regression on hashed character n-grams.

The model is trained on the driver from a small labelled URL table (given, or
the built-in one of 5,000 rows made from word lists, with
wanted words that hold an unwanted one by chance), and its
weights, 2**bits floats, go to the tasks; neither grows with the data.

Defined cases: a null url, or one without "://", has empty host and path, no
rule, and the model judges the empty string (allow); null ids are kept; repeated
rows each get their own result; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import random
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The rules of the query.
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
# Words of unwanted and of wanted hosts and paths.
UNWANTED = "casino casinos poker jackpot slots roulette blackjack betting gambling bookmaker wager bingo pills viagra cialis pharma steroids cheap replica counterfeit fakeid spam farm ads track banner popup clickbait adult porn porno sex sexy xxx nude naked erotic hentai camgirls milf escort escorts hookup dating loan loans payday crypto forex win winner prize lottery giveaway sweepstakes torrent warez crack cracked keygen serialkey malware phishing keylogger botnet ransom spy hack hacks bonus miracle weightloss bet bets free cash vip".split()
WANTED = "news library museum school university college science health garden travel music film sport weather history market city council gov parish forum recipes books garage bakery journal archive review studio research family photo design nature village kitchen hospital clinic therapist bank insurance energy water rail airport hotel restaurant cafe theatre cinema gallery orchestra choir football cricket rugby tennis golf cycling hiking blog wiki docs developer software hardware physics chemistry biology maths economics law justice police fire charity trust foundation union shop homes school maps jobs download help support learn".split()
# Wanted words that hold an unwanted one by chance.
INNOCENT = "sussex essex middlesex wessex sextant sexton unisex cashmere cashew cashier better alphabet bethany betony elizabeth diabetes tibet analysis therapist specialist socialist pharmacy pharmacology window winter winchester wine twins darwin freedom freezer freeway carefree update updating validating loaned farmers farmhouse adsorption uploads downloads roads heads spying spyglass hackney shack whack backpack jackdaw slackline packaging feedback blackbird racket scunthorpe cocktail classic assassin titanic bonusround alphabetical besets sherbet gibbet barbeque cryptography encrypt tracks soundtrack racetrack bannerman embankment banner".split()
# Endings of public bodies' hosts.
PUBLIC = "gov.uk ac.uk edu gov org.uk museum nhs.uk edu.au gouv.fr gob.es bund.de police.uk".split()
_ALPHABET = "etaoinshrdlucmfwypvbgk"


def labelled_urls(seed: int = 7, rows: int = 2500) -> list[tuple[str, int]]:
    """The built-in table, made from the word lists by a rule: (url, 1 if unwanted)."""
    r = random.Random(seed)
    tail = lambda: r.choice(("com", "net", "org", "info", "example.com", "example.org", "example.net", "co.uk", "de", "fr", "net.co"))
    front = lambda: r.choice(("", "", "www.", "blog.", "m."))
    path = lambda: r.choice(("", "/", f"/en/{r.randrange(999)}", f"/de/{r.randrange(999)}/", f"/fr/{r.randrange(999)}.html", f"/es/{r.randrange(999)}", f"/{r.choice(WANTED)}/{r.randrange(99)}", f"/{r.choice(INNOCENT)}"))
    made = lambda: "".join(r.choice(_ALPHABET) for _ in range(r.randrange(4, 10)))
    calm = lambda: r.choice((*WANTED, *INNOCENT))
    out = []
    for _ in range(rows):
        bad = r.choice(UNWANTED) + r.choice(("", "-", "")) + r.choice((r.choice(UNWANTED), r.choice(UNWANTED), calm(), made(), str(r.randrange(99)), ""))
        bad = r.choice((bad, bad, bad, f"{calm()}-{r.choice(UNWANTED)}"))
        out.append((f"http://{front()}{bad}.{tail()}{path()}", 1))
        good = r.choice((made(), made(), calm(), calm(), f"{calm()}-{made()}", f"{made()}{calm()}", f"{calm()}-{calm()}", f"{calm()}{calm()}"))
        end = r.choice((tail(), tail(), r.choice(PUBLIC)))
        out.append((f"https://{front()}{good}.{end}{path()}", 0))
    return out


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path; both empty without "://"."""
    if not url or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1].split("?", 1)[0].split("#", 1)[0]
    host, slash, path = rest.partition("/")
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host), slash + path


def buckets_of(host: str, path: str, bits: int) -> list[int]:
    """Hashed n-grams of 3 to 6 characters; host and path are told apart."""
    out = set()
    for mark, s in (("h", f"^{host}$"), ("p", f"^{path}$")):
        for n in (3, 4, 5, 6):
            for i in range(len(s) - n + 1):
                out.add(zlib.crc32(f"{mark}{s[i : i + n]}".encode("utf-8", "surrogatepass")) & ((1 << bits) - 1))
    return sorted(out)


def fit(rows: Iterable[tuple[str, int]], *, bits: int = 15, rounds: int = 1500, rate: float = 2.0, decay: float = 1e-5) -> tuple[np.ndarray, float]:
    """Weights and bias by full gradient steps; the table must be small: it is held on the driver."""
    at, owner, label = [], [], []
    for k, (url, y) in enumerate(rows):
        b = buckets_of(*split_url(url), bits)
        at += b
        owner += [k] * len(b)
        label.append(y)
    at, owner, y = np.array(at), np.array(owner), np.array(label, float)
    scale = 1 / np.sqrt(np.maximum(np.bincount(owner, minlength=len(y)), 1))
    w, bias = np.zeros(1 << bits), 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-(np.bincount(owner, w[at], len(y)) * scale + bias)))
        g = (p - y) * scale
        w -= rate * (np.bincount(at, g[owner], len(w)) / len(y) * 10 + decay * w)
        bias -= rate * float((p - y).mean())
    return w.astype(np.float32), bias


@functools.lru_cache(maxsize=1)
def _built_in() -> tuple[np.ndarray, float]:
    return fit(labelled_urls())


def judge_urls(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", rules: tuple[tuple[str, str], ...] = RULES, model: tuple[np.ndarray, float] | None = None, threshold: float = 0.5) -> DataFrame:
    """One row per input row: id, host, path, rule, verdict (allow or block), score (the model's probability of block)."""
    weights, bias = model or _built_in()
    bits = int(len(weights)).bit_length() - 1

    @F.pandas_udf("double")
    def score(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for hosts, paths in parts:
            out = []
            for h, p in zip(hosts, paths, strict=True):
                b = buckets_of(h, p, bits)
                out.append(1 / (1 + np.exp(-(float(weights[b].sum()) / max(1.0, len(b)) ** 0.5 + bias))) if h or p else 0.0)
            yield pd.Series(out, dtype="float64")

    at = F.instr(F.col("__bt_url"), "://")
    rest = F.regexp_extract(F.expr("substring(__bt_url, instr(__bt_url, '://') + 3)"), r"(?s)\A([^?#]*)", 1)
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    host = F.translate(F.regexp_extract("__bt_rest", r"(?s)\A([^/]*)", 1), upper, upper.lower())
    df = pages.select(F.col(id_col).alias("__bt_id"), F.col(url_col).alias("__bt_url")).withColumn("__bt_rest", F.when(at > 0, rest).otherwise(""))
    df = df.select("__bt_id", host.alias("__bt_host"), F.regexp_extract("__bt_rest", r"(?s)\A[^/]*(.*)", 1).alias("__bt_path"))
    rule: Column = F.lit(None).cast("string")
    what: Column = F.lit(None).cast("string")
    for verdict, text in sorted(rules, key=lambda x: len(x[1])):  # the longest is asked first
        h, slash, p = text.partition("/")
        fits = ((F.col("__bt_host") == h) | F.col("__bt_host").endswith(f".{h}")) & F.col("__bt_path").startswith(slash + p)
        rule, what = F.when(fits, text).otherwise(rule), F.when(fits, verdict).otherwise(what)
    df = df.select("*", rule.alias("__bt_rule"), what.alias("__bt_what"), score("__bt_host", "__bt_path").alias("__bt_score"))
    own = F.when(F.col("__bt_score") >= threshold, "block").otherwise("allow")
    return df.select(F.col("__bt_id").alias(id_col), F.col("__bt_host").alias("host"), F.col("__bt_path").alias("path"), F.col("__bt_rule").alias("rule"), F.coalesce("__bt_what", own).alias("verdict"), F.col("__bt_score").alias("score"))
