"""Main text of web pages by a recurrent block labeller.

A page is cut into leaf blocks: runs of text between block-level tags, each with
its tag path.  A bidirectional LSTM written in numpy reads the page's blocks in
order, each as a vector of hashed tag-path parts, hashed words and a few
scalars, and labels every block with the whole page as context.  It is trained
here, on the driver, from pages that a small generator makes with known labels;
their number is a parameter.  Scalars tell how much of the page's text and links
the elements around a block hold, so boxes without telling names are read too.
The weights (some 50 kB) go to the tasks.

Defined cases: null html is empty and gives an empty text; unclosed tags,
comments and scripts are closed as browsers do; null ids and urls are kept;
repeated rows each get their own result; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import html
import random
import re
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Tags.
_SILENT = "script|style|noscript|template|iframe|svg|math|object|canvas|audio|video|textarea|select"
_INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img br".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_SELF = frozenset("p li dt dd tr td th option".split())  # a new one ends an open one
# every quantifier is possessive, and a tag whose quotes don't close ends at its first ">", so no input makes it go back
_TAG = re.compile(rf"""<!--.*?(?:-->|\Z)|<({_SILENT})\b(?:[^>"']++|"[^"]{{0,16384}}+"|'[^']{{0,16384}}+')*+>.*?(?:</\1\s*+>|\Z)|<(/?)([a-zA-Z][\w:-]*+)((?:[^>"']++|"[^"]{{0,16384}}+"|'[^']{{0,16384}}+')*+(?:>|\Z)|[^>]*+(?:>|\Z))|<[!?/][^>]*+(?:>|\Z)""", re.S | re.I)
_NAMES = re.compile(r"""\b(?:class|id|role)\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s>]++))""", re.I)
# Words of text around the main text.
_CUES = re.compile(r"©|copyright|all rights reserved|cookie|privacy|subscribe|newsletter|advert|sponsor|related|share|comment|repl(?:y|ies)|log ?in|sign (?:in|up)|menu|search|home\b|contact|about us|read more|previous|next\b|follow us|terms", re.I)

PATH, WORDS, MORE = 64, 32, 12
DIMS = PATH + WORDS + MORE
DEEP = 24  # parts of a tag path that count, from the leaf up


class Block(NamedTuple):
    """A leaf block: its tag path, its text with single spaces, its characters inside links, and the numbers of the elements around it: parent and grandparent."""

    path: tuple[str, ...]
    text: str
    linked: int
    depth: int
    parent: int
    grand: int


def leaf_blocks(page: str) -> list[Block]:
    """The blocks that have text, in page order; time grows with the page, however deep its tags are nested."""
    out: list[Block] = []
    text: list[str] = []
    stack: list[tuple[str, tuple[str, ...], int]] = []  # tag, tag path to here, number
    solid: list[int] = []  # places in stack of the block-level elements
    many: dict[str, int] = {}  # open elements by tag
    linked, made, base = 0, 0, ((), 0, 0, 0)

    def flush() -> None:
        nonlocal linked
        if text:
            raw = "".join(text)
            joined = " ".join((html.unescape(raw) if "&" in raw else raw).split())
            if joined:
                out.append(Block(base[0], joined, min(linked, len(joined)), *base[1:]))
            text.clear()
        linked = 0

    def add(s: str) -> None:
        nonlocal linked
        if s:
            text.append(s)
            if many.get("a") and any(x[0] == "a" for x in stack[-3:]):
                linked += len(s)

    def close(k: int) -> None:
        for x in stack[k:]:
            many[x[0]] -= 1
        del stack[k:]
        while solid and solid[-1] >= k:
            solid.pop()

    at = 0
    for m in _TAG.finditer(page):
        add(page[at : m.start()])
        at = m.end()
        tag = (m[3] or "").lower()
        if not tag:
            continue
        inline = tag in _INLINE
        if not inline:
            flush()
        elif tag == "br":
            text.append(" ")
        top = solid[-1] if solid else -1
        if m[2]:
            if many.get(tag):
                # an inline end tag closes nothing outside its block
                least = max(top, len(stack) - 64 - 1) if inline else -1
                k = next((i for i in range(len(stack) - 1, least, -1) if stack[i][0] == tag), None)
                if k is not None:
                    close(k)
        elif tag not in _VOID:
            if top >= 0 and ((tag in _SELF and stack[top][0] in (tag, "p")) or (not inline and stack[-1][0] == "p")):
                close(top)
            names = [x.lower() for g in _NAMES.findall(m[4] or "") for y in g if y for x in re.split(r"[^A-Za-z]+", y) if x][:DEEP]
            above = stack[solid[-1]][1] if solid else ()
            made += 1
            many[tag] = many.get(tag, 0) + 1
            stack.append((tag, above if inline else (*above, tag, *(f".{x}" for x in names))[-DEEP:], made))
            if not inline:
                solid.append(len(stack) - 1)
        if not inline:
            ids = [stack[k][2] for k in solid[-3:]]
            base = (stack[solid[-1]][1] if solid else (), len(solid), *(ids[-2::-1] + [0, 0])[:2])
    add(page[at:])
    flush()
    return out


@functools.lru_cache(maxsize=20_000)
def _path_vector(path: tuple[str, ...]) -> np.ndarray:
    v = np.zeros(PATH, np.float32)
    for p in path:
        v[zlib.crc32(p.encode("utf-8", "surrogatepass")) % PATH] += 1
    if path:
        v[zlib.crc32(("leaf" + path[-1]).encode("utf-8", "surrogatepass")) % PATH] += 1
    return np.minimum(v, 2)


def _around(page: np.ndarray, box: np.ndarray, size: np.ndarray, linked: np.ndarray, whole: np.ndarray) -> tuple[np.ndarray, ...]:
    """Of the element each block is in: its part of the page's text, its part inside links, its blocks."""
    _, at = np.unique(page * (1 << 32) + box, return_inverse=True)
    total = np.bincount(at, size)
    return total[at] / whole, np.bincount(at, linked)[at] / total[at], np.bincount(at)[at]


def features(pages: list[list[Block]]) -> np.ndarray:
    """A row per block of all pages; words are hashed once per different word."""
    blocks = [x for own in pages for x in own]
    x = np.zeros((len(blocks), DIMS), np.float32)
    if not blocks:
        return x
    x[:, :PATH] = np.stack([_path_vector(b.path) for b in blocks])
    cut = pc.ascii_split_whitespace(pc.utf8_lower(pa.array([b.text for b in blocks], pa.large_string())))
    many = np.asarray(pc.list_value_length(cut)).astype(np.int64)
    coded = cut.flatten().dictionary_encode()
    slot = np.array([zlib.crc32(w.encode("utf-8", "surrogatepass")) % WORDS for w in coded.dictionary.to_pylist()], np.int64)[np.asarray(coded.indices)]
    owner = np.repeat(np.arange(len(blocks)), many)
    bag = np.bincount(owner * WORDS + slot, minlength=len(blocks) * WORDS).reshape(-1, WORDS)
    x[:, PATH : PATH + WORDS] = np.sqrt(bag / np.maximum(many, 1)[:, None])
    size, linked = np.array([len(b.text) for b in blocks], float), np.array([b.linked for b in blocks], float)
    lengths = np.array([len(own) for own in pages])
    page = np.repeat(np.arange(len(pages)), lengths)
    whole = np.bincount(page, size)[page]
    parent = _around(page, np.array([b.parent for b in blocks]), size, linked, whole)
    grand = _around(page, np.array([b.grand for b in blocks]), size, linked, whole)
    place = (np.arange(len(blocks)) - (np.cumsum(lengths) - lengths)[page]) / lengths[page]
    ends = [b.text[-1] in ".!?…。:;\"'" for b in blocks]
    stops = [sum(b.text.count(c) for c in ".,;!?") for b in blocks]
    cues = [len(b.text) < 300 and _CUES.search(b.text) is not None for b in blocks]
    deep = [min(b.depth, 12) / 12 for b in blocks]
    x[:, -MORE:] = np.stack([np.log1p(many) / 4, linked / size, ends, deep, parent[0], parent[1], np.log1p(parent[2]) / 3, grand[0], grand[1], place, np.log1p(stops) / 3, cues], 1)
    return x


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


class BiLSTM:
    """Two LSTMs over a sequence, one from each end, and a logistic unit on both states."""

    def __init__(self, dims: int = DIMS, hidden: int = 16, seed: int = 3):
        r, h = np.random.default_rng(seed), hidden
        make = lambda *s: r.normal(0, 1 / np.sqrt(s[0]), s).astype(np.float32)
        self.h = h
        self.w = {"out": make(2 * h, 1)[:, 0], "bias": np.zeros(1, np.float32)}
        for d in "fb":
            self.w |= {f"x{d}": make(dims, 4 * h), f"h{d}": make(h, 4 * h), f"c{d}": np.repeat(np.float32([0, 1, 0, 0]), h)}

    def run(self, x: np.ndarray, mask: np.ndarray, d: str) -> dict:
        """x: steps, pages, dims. All states, for learning."""
        steps, n, h = *x.shape[:2], self.h
        z = x @ self.w[f"x{d}"] + self.w[f"c{d}"]
        H, C, G = np.zeros((steps + 1, n, h), np.float32), np.zeros((steps + 1, n, h), np.float32), np.empty((steps, n, 4 * h), np.float32)
        order = range(steps) if d == "f" else range(steps - 1, -1, -1)
        last, first = (lambda t: t, lambda t: t + 1) if d == "f" else (lambda t: t + 1, lambda t: t)
        for t in order:
            a = z[t] + H[last(t)] @ self.w[f"h{d}"]
            G[t, :, : 3 * h], G[t, :, 3 * h :] = _sigmoid(a[:, : 3 * h]), np.tanh(a[:, 3 * h :])
            i, f, o, g = np.split(G[t], 4, axis=1)
            m = mask[t][:, None]
            c = f * C[last(t)] + i * g
            C[first(t)] = m * c + (1 - m) * C[last(t)]
            H[first(t)] = m * (o * np.tanh(c)) + (1 - m) * H[last(t)]
        return {"H": H, "C": C, "G": G, "order": order, "last": last, "first": first, "states": H[1:] if d == "f" else H[:-1]}

    def predict(self, x: np.ndarray, mask: np.ndarray) -> np.ndarray:
        f, b = self.run(x, mask, "f")["states"], self.run(x, mask, "b")["states"]
        return _sigmoid(np.concatenate([f, b], 2) @ self.w["out"] + self.w["bias"][0])

    def gradients(self, x: np.ndarray, mask: np.ndarray, y: np.ndarray) -> tuple[dict, float]:
        h, runs = self.h, {d: self.run(x, mask, d) for d in "fb"}
        both = np.concatenate([runs["f"]["states"], runs["b"]["states"]], 2)
        p = _sigmoid(both @ self.w["out"] + self.w["bias"][0])
        loss = float(-(mask * (y * np.log(p + 1e-7) + (1 - y) * np.log(1 - p + 1e-7))).sum() / mask.sum())
        e = mask * (p - y) / mask.sum()
        g = {"out": np.einsum("tn,tnk->k", e, both), "bias": e.sum(keepdims=True).ravel()}
        for k, d in enumerate("fb"):
            r, wh = runs[d], self.w[f"h{d}"]
            own = e[:, :, None] * self.w["out"][k * h : (k + 1) * h]
            dz, dh, dc = np.zeros_like(r["G"]), np.zeros(x.shape[1:2] + (h,), np.float32), np.zeros(x.shape[1:2] + (h,), np.float32)
            gh = np.zeros_like(wh)
            for t in reversed(r["order"]):
                m, before = mask[t][:, None], r["C"][r["last"](t)]
                i, f, o, c_in = np.split(r["G"][t], 4, axis=1)
                c = f * before + i * c_in
                tc = np.tanh(c)
                dh = dh + own[t]
                live = dh * m
                dcell = dc * m + live * o * (1 - tc * tc)
                dz[t] = np.concatenate([dcell * c_in * i * (1 - i), dcell * before * f * (1 - f), live * tc * o * (1 - o), dcell * i * (1 - c_in * c_in)], 1)
                gh += r["H"][r["last"](t)].T @ dz[t]
                dh = dz[t] @ wh.T + dh * (1 - m)
                dc = dcell * f + dc * (1 - m)
            g |= {f"h{d}": gh, f"c{d}": dz.sum((0, 1)), f"x{d}": np.einsum("tnk,tnz->kz", x, dz)}
        return g, loss

    def fit(self, pages: list[tuple[np.ndarray, np.ndarray]], *, rounds: int = 12, batch: int = 32, rate: float = 0.01, seed: int = 5) -> float:
        """Adam steps; returns the mean loss of the last round."""
        r, mean, var, step, loss = np.random.default_rng(seed), {}, {}, 0, 0.0
        for _ in range(rounds):
            order, losses = r.permutation(len(pages)), []
            # pages of similar length go together, in random company
            order = np.concatenate([sorted(order[a : a + 8 * batch], key=lambda k: len(pages[k])) for a in range(0, len(order), 8 * batch)])
            for a in (r.permutation(-(-len(order) // batch)) * batch).tolist():
                x, mask, y = padded([pages[k] for k in order[a : a + batch]])
                g, loss = self.gradients(x, mask, y)
                losses.append(loss)
                step += 1
                for k, v in g.items():
                    v = np.clip(v, -1, 1)
                    mean[k] = 0.9 * mean.get(k, 0) + 0.1 * v
                    var[k] = 0.999 * var.get(k, 0) + 0.001 * v * v
                    self.w[k] = (self.w[k] - rate * (mean[k] / (1 - 0.9**step)) / (np.sqrt(var[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
            loss = float(np.mean(losses))
        return loss

    def label(self, pages: list[np.ndarray], batch: int = 64) -> list[np.ndarray]:
        """Probability of main text for every block; pages of similar length go together."""
        out: list = [np.empty(0)] * len(pages)
        order = sorted(range(len(pages)), key=lambda k: len(pages[k]))
        for a in range(0, len(order), batch):
            own = [k for k in order[a : a + batch] if len(pages[k])]
            if own:
                x, mask, _ = padded([(pages[k], np.zeros(len(pages[k]))) for k in own])
                p = self.predict(x, mask)
                for j, k in enumerate(own):
                    out[k] = p[: len(pages[k]), j]
        return out


def padded(pages: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    steps, n = max(len(x) for x, _ in pages), len(pages)
    x, mask, y = np.zeros((steps, n, pages[0][0].shape[1]), np.float32), np.zeros((steps, n), np.float32), np.zeros((steps, n), np.float32)
    for j, (a, b) in enumerate(pages):
        x[: len(a), j], mask[: len(a), j], y[: len(a), j] = a, 1, b
    return x, mask, y


def training_page(r: random.Random) -> str:
    """A made page; its main text blocks hold the mark \x02.

    A third of the pages name their parts (article, nav, class="sidebar"), a third
    have boxes of names that say nothing, and a third boxes of random names, so
    that length, links, punctuation and neighbours must tell.
    """
    vowels, rest = "aeiouéäó", "bcdfghlmnprstvz"
    word = lambda: "".join(r.choice(rest) + r.choice(vowels) for _ in range(r.randrange(1, 5)))
    some = lambda a, b: " ".join(word() for _ in range(r.randrange(a, b)))
    comma = lambda s: s.replace(" ", ", ", 1) if r.random() < 0.3 else s
    sentence = lambda: comma(some(3, 18)).capitalize() + "."
    para = lambda: " ".join(sentence() for _ in range(r.randrange(1, 7)))
    link = lambda: f'<a href="/{word()}">{some(1, 4)}</a>'
    style = r.choice(("named", "plain", "random"))
    plain = "wrap wrapper col col1 col2 row inner box page site grid left right center cell block panel c1 x12 container layout holder outer area part"

    def menu() -> str:
        k = r.randrange(4)
        links = [link() for _ in range(r.randrange(2, 9))]
        if k < 2:
            return "<ul>" + "".join(f"<li>{x}</li>" for x in links) + "</ul>"
        return f"<div>{r.choice((' | ', ' ', ' &middot; ')).join(links)}</div>" if k == 2 else "".join(f"<div>{x}</div>" for x in links)

    def named(words: str, inner: str, tags: str = "div section aside") -> str:
        t = r.choice(tags.split()) if style == "named" else r.choice(("div", "div", "div", "section", "td"))
        name = r.choice(words.split()) if style == "named" or r.random() < 0.25 else (r.choice(plain.split()) if style == "plain" else word())
        mark = f' {r.choice(("class", "class", "id"))}="{name}"' if r.random() < 0.9 else ""
        return f"<table><tr><td{mark}>{inner}</td></tr></table>" if t == "td" else f"<{t}{mark}>{inner}</{t}>"

    def cue() -> str:
        return r.choice(("Subscribe to our newsletter", "Advertisement", "Sponsored", "We use cookies", "Share this", "Related", "Sign up", "Read more", "Follow us", "Search", "Log in"))

    def inset() -> str:
        return r.choice((
            lambda: named("ad ads advert advertisement sponsored promo banner", r.choice((some(2, 9), f"<p>{sentence()}</p>", link(), sentence(), cue()))) if style == "named" else named("ad ads advert", r.choice((link(), cue(), f"<p>{cue()}</p>{link()}"))),
            lambda: named("newsletter subscribe signup cookie notice alert consent gdpr", r.choice((sentence(), f"<p>{sentence()}</p><button>{word()}</button>"))) if style == "named" else named("newsletter cookie", f"<p>{cue()} {sentence()}</p><button>{word()}</button>"),
            lambda: f"<form action='/{word()}'><label>{some(1, 3)}</label><input name=q><button>{word()}</button><p>{sentence()}</p></form>",
            lambda: named("related share social sidebar widget tags breadcrumb", menu()),
            lambda: f"<aside><h3>{some(1, 4)}</h3><p>{sentence()}</p></aside>",
        ))()

    def block() -> str:
        k = r.randrange(12)
        body = para() if k < 9 else sentence()
        if k == 0:
            return f"<ul>{''.join(f'<li>\x02{some(2, 12)}</li>' for _ in range(r.randrange(2, 5)))}</ul>"
        if k == 1:
            return f"<blockquote><p>\x02{body}</p></blockquote>"
        if k == 2:
            return f"<h{r.randrange(2, 5)}>\x02{some(1, 7)}</h2>"
        if k == 3:
            return f"<table><tr><td>\x02{some(1, 4)}</td><td>\x02{some(1, 4)}</td></tr></table>"
        if k == 4:
            return f"<p><b>\x02{body}<br><p>\x02{para()}</p>"
        if k == 5:
            return f"<p>\x02{body} {link()} {some(1, 6)}.</p>"
        if k == 6:
            return f"<p>\x02{' '.join(w + r.choice(('%%%', '###', '***', '$$$', '|', '&amp;&amp;')) for w in para().split())}</p>"
        if k == 7:
            return f"<pre>\x02{some(2, 9)}</pre>"
        if k == 8 and style != "named":
            return f"<div>\x02{body}</div>"
        if k == 9 and style != "named":
            return f"\x02{body}<br><br>\x02{para()}" + r.choice(("", f"<br><br>\x02{para()}"))
        if k == 10 and r.random() < 0.3:  # what often stands around the text may stand in it
            return f"<p>\x02{r.choice(('All rights reserved.', 'Copyright ' + some(1, 3) + '.', cue() + '.', body))}</p>"
        return f"<p>\x02{body}</p>"

    def boxed() -> str:
        return named("block text", block()) if style != "named" and boxes else block()

    boxes = r.random() < 0.3
    blocks = [boxed() for _ in range(r.choice((1, 2, 3, 5, 8, 12, 20) if style == "named" else (2, 3, 5, 8, 12, 20)))]
    for _ in range(r.choice((0, 0, 1, 2))):
        blocks.insert(r.randrange(len(blocks) + 1), inset())
    title = some(2, 9)
    inside = f"<h1>\x02{title}</h1>" * (r.random() < 0.8) + "".join(blocks)
    remark = lambda: named("comment reply", r.choice((f"<p>{para()}</p>", f"<b>{word()}</b><p>{sentence()}</p>", para())), "div li article")
    said = r.choice((f"{r.randrange(2, 30)} comments", "Comments", "Replies", "Leave a reply"))
    head = some(1, 3) if style == "named" else said
    comments = named("comments responses discussion replies", f"<h3>{head}</h3>" + "".join(remark() for _ in range(r.randrange(1, 6))), "section div ol") if r.random() < 0.35 else ""
    late = comments if r.random() < 0.3 else ""
    if style == "named":
        main = r.choice((f"<article>{inside}{late}</article>", f"<main>{inside}{late}</main>", f"<main><article>{inside}{late}</article></main>", named("content post entry story article main body", inside + late, "div section"), f"<article>{inside}{late}</article>"))
    else:
        main = named("content post", inside + late)
        for _ in range(r.randrange(3)):
            main = named("main page", main)
    top = r.choice(("", f"<header><a href='/'>{some(1, 3)}</a><p>{some(2, 7)}</p></header>", f"<header>{menu()}</header>", named("header masthead", some(1, 5), "div")))
    nav = r.choice((f"<nav>{menu()}</nav>", f"<nav>{menu()}</nav>", named("nav menu navigation", menu(), "div"), "")) if style == "named" else r.choice((named("nav menu", menu()), menu(), ""))
    side = r.choice(("", "", f"<aside>{menu()}<p>{sentence()}</p></aside>", named("sidebar widget", f"<h3>{some(1, 3)}</h3>{menu()}<p>{sentence()}</p>", "div"))) if style == "named" else r.choice(("", named("sidebar", f"<h3>{some(1, 3)}</h3>{menu()}" + r.choice(("", f"<p>{cue()}</p>")))))
    mine = f"&copy; {r.choice((word() + '.example', '20' + str(r.randrange(10, 30)), some(1, 4)))}"
    foot = r.choice((f"<footer>&copy; {word()}.example &middot; {r.choice((sentence(), para(), some(2, 6)))}</footer>", f"<footer>{menu()}<p>{sentence()}</p></footer>", named("footer copyright", f"&copy; {some(2, 8)}", "div"), "")) if style == "named" else r.choice((named("footer", mine), named("footer", f"{menu()}<p>{mine} {r.choice(('', 'All rights reserved.', sentence()))}</p>"), ""))
    extra = [inset() if r.random() < 0.4 else "" for _ in range(3)]
    parts = [top, nav, extra[0], side, main, "" if late else comments, extra[1], extra[2], foot]
    if style != "named" and r.random() < 0.5:
        parts = [named("wrap", "".join(parts))]
    return f"<!DOCTYPE html><html><head><title>{title}</title><style>p{{}}</style></head><body>{''.join(parts)}" + r.choice(("</body></html>", ""))


def training_set(pages: int, seed: int) -> list[tuple[np.ndarray, np.ndarray]]:
    r = random.Random(seed)
    made = [leaf_blocks(training_page(r)) for _ in range(pages)]
    marked = [np.array(["\x02" in b.text for b in own], float) for own in made]
    x = features([[b._replace(text=b.text.replace("\x02", "").strip() or "-") for b in own] for own in made])
    return list(zip(np.split(x, np.cumsum([len(own) for own in made])[:-1]), marked, strict=True))


@functools.lru_cache(maxsize=1)
def trained(pages: int = 1200, seed: int = 11) -> BiLSTM:
    """The labeller, trained on so many made pages."""
    net = BiLSTM()
    net.fit(training_set(pages, seed))
    return net


_BYTES_AT_ONCE = 8 << 20


def extract_main_text(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", model: BiLSTM | None = None, threshold: float = 0.5) -> DataFrame:
    """One row per input row: id, url, text, n_chars (code points), n_blocks, n_kept."""
    net = model or trained()
    ids = pages.schema[id_col].dataType
    source = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            size = np.cumsum(np.asarray(pc.binary_length(batch.column("html"))).astype(np.int64)) // _BYTES_AT_ONCE
            edges = [0, *(np.flatnonzero(np.diff(size)) + 1).tolist(), len(size)]
            for a, b in zip(edges, edges[1:], strict=False):
                if b == a:
                    continue
                part = batch.slice(a, b - a)
                blocks = [leaf_blocks(x) for x in part.column("html").to_pylist()]
                x = features(blocks)
                ends = np.cumsum([len(own) for own in blocks])
                kept = net.label(np.split(x, ends[:-1]))
                texts = [" ".join(b.text for b, p in zip(own, q, strict=True) if p >= threshold) for own, q in zip(blocks, kept, strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), part.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64()), pa.array([len(own) for own in blocks], pa.int64()), pa.array([int((q >= threshold).sum()) for q in kept], pa.int64())],
                    names=["id", "url", "text", "n_chars", "n_blocks", "n_kept"],
                )

    out = source.mapInArrow(extract, f"id {ids.simpleString()}, url string, text string, n_chars long, n_blocks long, n_kept long")
    return out.withColumnRenamed("id", id_col)
