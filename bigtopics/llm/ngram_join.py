"""Exact Jaccard self-join of documents on their word shingles, by universe partition.

Two sets of sizes x <= y link when their Jaccard similarity is at least
``NUM / DEN``; then they differ in at most (x + y) (DEN - NUM) / (DEN + NUM)
elements.  Sizes fall into bands.  In the band of the smaller set the universe of
shingles is cut by a hash into m segments, m above that bound, so some segment
is equal in both sets, or differs in one element.

* Index side (a set in its own band and in the lower bands a smaller partner
  may have): the hash of each non-empty segment subset; in bands of small sets
  also the hash of each subset less one element.
* Probe side (a set in its own band): enough segments that any partner must
  agree on one.  They are chosen by cost: subsets of most elements first, which
  fewest sets share; where too few segments are non-empty, one-deletion
  neighbourhoods of the smallest subsets make up for it, each counting as two.
* A set that still lacks segments (none was seen) is probed again, against an
  index by another hash; so no case is lost.

Signatures travel as packed blocks, one for each bucket of the signature space.
Exact copies share a class (hash of the set) and are represented once.
Candidates sharing a signature form groups.  A first pass verifies each member
against one hub, mostly the same in groups that overlap, so rows grow with the
members; links join members into components.  Pairs of different components are
then looked at in tiles of bounded size, where a parity bitmap of each set bounds
the difference from below.  A second pass verifies a forest of the pairs that are
near enough by it.  The third verifies what is left: as rows where a member has
few possible partners, else in tiles of bounded bytes where whole sets meet, all
pairs are verified and only links that join components come out.  So no pass has
a row for each pair of a group.

Sets are compared by 64-bit hashes of shingles and classes by 64-bit hashes of
sets; for D different texts the chance of any false class is D^2 / 2^65.

Defined cases: a null or wordless text has an empty set and no links; fewer than
``k`` words make one shingle; null ids link like others and their component is
named by the smallest id in it (null if none has one); repeated rows are linked
as copies; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.graph import components
from .bloom import Bloom, build
from .common import give_back, key_of, settle, temporary

NUM, DEN = 4, 5
SMALL = 32  # bands up to this size also index one-deletion neighbourhoods
SKETCH = 16  # 64-bit words of the parity bitmap
ALL_PAIRS = 5  # up to so many members a group's pairs are all verified at once; a larger one has a hub first
PARTNERS = 16  # up to so many possible partners a member's pairs are rows; those of others are tested in tiles
TILE = 1024  # members of a tile whose bitmaps meet
TILE_ITEMS = 1 << 19  # elements of a tile whose sets meet
_M1, _M2, _M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_BYTES_AT_ONCE = 8 << 20


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _M2
    x = (x ^ (x >> np.uint64(27))) * _M3
    return x ^ (x >> np.uint64(31))


# --- sets -------------------------------------------------------------------------------------------


def shingle_sets(texts: pa.Array, k: int = 5) -> list[np.ndarray]:
    """Sorted different shingle hashes (uint64) of each text."""
    import xxhash

    cut = pc.ascii_split_whitespace(pc.ascii_trim_whitespace(pc.ascii_lower(texts)))
    many = np.asarray(pc.list_value_length(cut)).astype(np.int64)
    coded = cut.flatten().dictionary_encode()
    words = [xxhash.xxh64_intdigest(w.encode()) for w in coded.dictionary.to_pylist()]
    blank = next((i for i, w in enumerate(coded.dictionary.to_pylist()) if not w), -1)
    index = np.asarray(coded.indices)
    if blank >= 0:  # the one empty piece of a text without words
        owner = np.repeat(np.arange(len(many)), many)
        keep = index != blank
        index, many = index[keep], np.bincount(owner[keep], minlength=len(many)).astype(np.int64)
    h = np.array(words, np.uint64)[index] if len(index) else np.empty(0, np.uint64)
    with np.errstate(over="ignore"):
        g = h[: max(0, len(h) - k + 1)].copy()
        for j in range(1, k):
            g = g * _M1 + h[j : len(h) - k + 1 + j]
        g = mix(g)
        ends = np.cumsum(many)
        out = []
        for n, e in zip(many.tolist(), ends.tolist(), strict=True):
            if n >= k:
                out.append(np.unique(g[e - n : e - k + 1]))
            elif n:
                x = np.uint64(n)
                for w in h[e - n : e]:
                    x = x * _M1 + w
                out.append(mix(np.array([x], np.uint64)))
            else:
                out.append(np.empty(0, np.uint64))
    return out


def class_of(s: np.ndarray) -> int:
    import xxhash

    return int(np.uint64(xxhash.xxh64_intdigest(s.tobytes())).astype(np.int64))


def sketch_of(s: np.ndarray) -> bytes:
    """Parity bitmap: the number of differing bits of two is at most the number of differing elements."""
    counts = np.bincount((s >> np.uint64(40)).astype(np.int64) & (64 * SKETCH - 1), minlength=64 * SKETCH)
    return np.packbits((counts & 1).astype(np.uint8)).tobytes()


def _slices(batches: Iterator[pa.RecordBatch], text: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        size = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(batch.column(text)), 0)).astype(np.int64)) // _BYTES_AT_ONCE
        edges = [0, *(np.flatnonzero(np.diff(size)) + 1).tolist(), len(size)]
        for a, b in zip(edges, edges[1:], strict=False):
            if b > a:
                yield batch.slice(a, b - a)
    give_back()


# --- bands and signatures ---------------------------------------------------------------------------


class Bands:
    """Size bands and their segment counts."""

    def __init__(self, most: int = 1 << 31, growth: float = 1.2):
        edges = [1]
        while edges[-1] <= most:
            edges.append(max(edges[-1] + 1, int(edges[-1] * growth)))
        self.low = np.array(edges)

    def band(self, size: int) -> int:
        return int(np.searchsorted(self.low, size, "right")) - 1

    def top(self, band: int) -> int:
        return int(self.low[band + 1]) - 1

    @staticmethod
    def partner(size: int) -> int:
        """Largest partner of a smaller set."""
        return size * DEN // NUM

    @classmethod
    def differ(cls, size: int) -> int:
        """Most elements in which a set of this size and a partner as large or larger differ."""
        return (size + cls.partner(size)) * (DEN - NUM) // (DEN + NUM)

    def segments(self, band: int) -> int:
        need = self.differ(self.top(band)) + 1
        return 2 * need if self.top(band) <= 256 else -(-need * 7 // 5)

    def as_larger(self, size: int) -> list[int]:
        """Bands of smaller partners: its own and those below it."""
        out, b = [], self.band(size)
        while b >= 0 and self.partner(self.top(b)) >= size:
            out.append(b)
            b -= 1
        return out


BANDS = Bands()


def signatures(s: np.ndarray, bands: Bands = BANDS, seed: int = 0) -> tuple[np.ndarray, np.ndarray, bool]:
    """(signatures, True where it probes, whether probing is complete) of a sorted set; every one is in the index unless it is a probe alone."""
    n = len(s)
    sig, probe, complete = [], [], True
    own = bands.band(n)
    for b in bands.as_larger(n):
        m, differ = bands.segments(b), bands.differ(n)
        if not bands.differ(bands.top(b)):
            continue  # only equal sets link
        with np.errstate(over="ignore"):
            where = mix(s + np.uint64(0x51ED * (b + 1) + 0xABCD * seed)) % np.uint64(m)
            order = np.argsort(where, kind="stable")
            seg, each = where[order].astype(np.int64), mix(s[order] * _M1 + np.uint64(seed + 1))
            starts = np.flatnonzero(np.diff(seg, prepend=-1))
            sums, count = np.add.reduceat(each, starts), np.diff(starts, append=n)
            ids = seg[starts].astype(np.uint64) * _M2 + np.uint64(b + 1)
            whole = mix(sums + ids)
            chosen = np.zeros(len(starts), bool)
            small = bands.top(b) <= SMALL
            if b == own:
                chosen[np.argsort(-count, kind="stable")[: differ + 1]] = True
            sig.append(whole)
            probe.append(chosen)
            if small:
                less = mix(np.repeat(sums + ids, count) - each)
                lack = differ + 1 - len(starts) if b == own else 0
                by_cost = np.argsort(count, kind="stable")
                cheap = by_cost[count[by_cost] > 1][: max(0, lack)]
                sig.append(less)
                probe.append(np.isin(np.repeat(np.arange(len(starts)), count), cheap))
                complete &= lack <= len(cheap)
            elif b == own and len(starts) < differ + 1:
                complete = False
    if not sig:
        return np.empty(0, np.uint64), np.empty(0, bool), True
    return np.concatenate(sig), np.concatenate(probe), complete


# --- packed blocks ----------------------------------------------------------------------------------


def _pack(sig: np.ndarray, cls: np.ndarray, size: np.ndarray, probe: np.ndarray) -> bytes:
    """sig: the low 40 bits count; cls and size are written once per different class."""
    own, at = np.unique(cls, return_inverse=True)
    sizes = np.zeros(len(own), "<u4")
    sizes[at] = size
    wide = sig.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5]
    place = (at.astype("<u4") << 1) | probe
    return np.array([len(own), len(sig)], "<u4").tobytes() + own.astype("<i8").tobytes() + sizes.tobytes() + wide.tobytes() + (place.astype("<u2") if len(own) < 1 << 15 else place.astype("<u4")).tobytes()


def _unpack(raw: bytes) -> tuple[np.ndarray, ...]:
    n, m = np.frombuffer(raw, "<u4", 2)
    own = np.frombuffer(raw, "<i8", n, 8)
    sizes = np.frombuffer(raw, "<u4", n, 8 + 8 * n)
    wide = np.zeros((m, 8), np.uint8)
    wide[:, :5] = np.frombuffer(raw, np.uint8, 5 * m, 8 + 12 * n).reshape(-1, 5)
    place = np.frombuffer(raw, "<u2" if n < 1 << 15 else "<u4", m, 8 + 12 * int(n) + 5 * int(m)).astype(np.int64)
    return wide.view("<u8").ravel(), own[place >> 1], sizes[place >> 1].astype(np.int64), (place & 1) == 1


def signature_blocks(sets: DataFrame, buckets: int, seed: int, only: Bloom | None = None) -> DataFrame:
    """sets: cls, items.  bucket, block; in buckets below 0 the classes of sets whose probing is not complete."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for part in _slices(batches, "items"):
            sigs, owner, size, probes, short = [], [], [], [], []
            for c, raw in zip(part.column("cls").to_pylist(), part.column("items"), strict=True):
                if c in seen:
                    continue
                s = np.frombuffer(raw.as_buffer(), "<u8")
                if len(seen) > 500_000:
                    seen.clear()  # it only saves repeats
                seen.add(c)
                g, p, complete = signatures(s, seed=seed)
                if only is not None:
                    p &= bool(only.may_hold(np.array([c]))[0])
                if not complete and (only is None or only.may_hold(np.array([c]))[0]):
                    short.append(c)
                sigs.append(g)
                probes.append(p)
                owner.append(np.full(len(g), c, np.int64))
                size.append(np.full(len(g), len(s), np.int64))
            rows = [(-1 - c % buckets, np.array([c], "<i8").tobytes()) for c in short]
            if sigs:
                g, o, z, p = map(np.concatenate, (sigs, owner, size, probes))
                to = (g >> np.uint64(40)).astype(np.int64) % buckets
                order = np.argsort(to, kind="stable")
                edges = np.searchsorted(to[order], np.arange(buckets + 1))
                for b in range(buckets):
                    at = order[edges[b] : edges[b + 1]]
                    if len(at):
                        rows.append((b, _pack(g[at] & np.uint64((1 << 40) - 1), o[at], z[at], p[at])))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["bucket", "block"])

    return sets.mapInArrow(make, "bucket int, block binary")


_FOUND = pa.schema([("kind", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("size", pa.int64())])


def _runs(sig: np.ndarray, cls: np.ndarray, size: np.ndarray, probe: np.ndarray) -> tuple[list, list]:
    """Pairs of runs of two classes, and pairs with hubs and members of larger runs."""
    order = np.lexsort((cls, sig))
    sig, cls, size, probe = sig[order], cls[order], size[order], probe[order]
    first = np.ones(len(sig), bool)
    first[1:] = (sig[1:] != sig[:-1]) | (cls[1:] != cls[:-1])
    starts = np.flatnonzero(first)
    probe = np.logical_or.reduceat(probe, starts)
    sig, cls, size = sig[starts], cls[starts], size[starts]
    begin = np.flatnonzero(np.diff(sig, prepend=np.uint64(0)) != 0) if len(sig) else np.empty(0, np.int64)
    if len(sig) and (not len(begin) or begin[0] != 0):
        begin = np.concatenate([[0], begin])
    length = np.diff(begin, append=len(sig))

    def fits(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether the smaller may be the probe of the larger."""
        x, y = np.minimum(size[i], size[j]), np.maximum(size[i], size[j])
        return (y * NUM <= x * DEN) & (np.where(size[i] <= size[j], probe[i], probe[j]) | ((size[i] == size[j]) & (probe[i] | probe[j])))

    two = begin[length == 2]
    ok = fits(two, two + 1)
    pairs = [(cls[two[ok]], cls[two[ok] + 1])]
    members, known = [], set()
    for a, n in zip(begin[length > 2].tolist(), length[length > 2].tolist(), strict=True):
        own = np.arange(a, a + n)
        key = hash(cls[own].tobytes()) if n > ALL_PAIRS else None
        if key in known or not probe[own].any():
            continue
        if key is not None:
            known.add(key)
        if n <= ALL_PAIRS:
            i, j = np.triu_indices(n, 1)
            ok = fits(own[i], own[j])
            pairs.append((cls[own[i[ok]]], cls[own[j[ok]]]))
            continue
        # the smallest by a hash of the class: groups that overlap mostly have one hub and ask for the same pairs
        hub = a + int(np.argmin(mix(cls[own].view(np.uint64))))
        x, y = np.minimum(size[own], size[hub]), np.maximum(size[own], size[hub])
        near = (own != hub) & (y * NUM <= x * DEN)
        pairs.append((cls[own[near]], np.full(int(near.sum()), cls[hub])))
        members.append((class_of(cls[own].view(np.uint64)), cls[own], size[own]))
    return pairs, members


def candidates(blocks: DataFrame) -> DataFrame:
    """kind 0: pair a, b; kind 1: group a has member b of this size; kind 2: class a is to be probed again."""

    def find(table: pa.Table) -> pa.Table:
        if table.column("bucket")[0].as_py() < 0:
            again = np.unique(np.frombuffer(b"".join(table.column("block").to_pylist()), "<i8"))
            return pa.Table.from_arrays([pa.array(np.full(len(again), 2, np.int32)), pa.array(again), pa.array(again), pa.array(np.zeros(len(again), np.int64))], schema=_FOUND)
        parts = [_unpack(x) for x in table.column("block").to_pylist()]
        pairs, members = _runs(*(np.concatenate(x) for x in zip(*parts, strict=True)))
        a, b = (np.concatenate(x) for x in zip(*pairs, strict=True))
        both = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], 1), axis=0)
        g = np.concatenate([np.full(len(c), k, np.int64) for k, c, _ in members]) if members else np.empty(0, np.int64)
        c = np.concatenate([c for _, c, _ in members]) if members else np.empty(0, np.int64)
        z = np.concatenate([z for _, _, z in members]) if members else np.empty(0, np.int64)
        kind = np.repeat(np.array([0, 1], np.int32), [len(both), len(g)])
        del parts, pairs, members
        give_back()
        return pa.Table.from_arrays([pa.array(kind), pa.array(np.concatenate([both[:, 0], g])), pa.array(np.concatenate([both[:, 1], c])), pa.array(np.concatenate([np.zeros(len(both), np.int64), z]))], schema=_FOUND)

    return blocks.groupBy("bucket").applyInArrow(find, "kind int, a long, b long, size long")


# --- verification -----------------------------------------------------------------------------------


def class_sets(sets: DataFrame, wanted: Bloom) -> DataFrame:
    """cls, items (sorted hashes as bytes) of each class the filter lets through."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = wanted.may_hold(np.asarray(batch.column("cls")).astype(np.int64))
            if ok.any():
                yield batch.filter(pa.array(ok))

    return sets.mapInArrow(make, "cls long, items binary").groupBy("cls").agg(F.first("items").alias("items"))


def linked(x: np.ndarray, y: np.ndarray) -> bool:
    if min(len(x), len(y)) * DEN < max(len(x), len(y)) * NUM:
        return False
    at = np.searchsorted(y, x)
    at[at == len(y)] = 0
    both = int((y[at] == x).sum())
    return both * DEN >= (len(x) + len(y) - both) * NUM


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs a, b that link, by their whole sets."""

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = [linked(np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")) for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True)]
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    left, right = sets.toDF("a", "x"), sets.toDF("b", "y")
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(test, "a long, b long")


def tiles(members: DataFrame, limit: int) -> DataFrame:
    """grp, i, j, t and the other columns of members (grp, cls, label, weight, ...): a copy for each pair of tiles (i, j) to compare; t is the member's own.

    In a group, members of its largest component and the rest are dealt to tiles
    of about ``limit`` weight each.  Tiles below 0 are of the largest component; they
    meet those of the rest alone, so copies grow with the group times its rest.
    Groups of one component are left out.
    """
    per = members.groupBy("grp", "label").agg(F.sum("weight").alias("w"))
    groups = per.groupBy("grp").agg(F.max(F.struct("w", "label")).alias("most"), F.sum("w").alias("all"))
    many = lambda w: F.ceil(w / F.lit(float(limit))).cast("int")
    groups = groups.filter("all > most.w").select("grp", F.col("most.label").alias("main"), many(F.col("most.w")).alias("mains"), many(F.col("all") - F.col("most.w")).alias("rests"))
    # written, so that a large group is a hot join key whose side can be split
    own = members.join(settle(groups, "open"), "grp")
    deal = F.xxhash64("cls")
    own = own.withColumn("t", F.when(F.col("label") == F.col("main"), -1 - F.pmod(deal, F.col("mains"))).otherwise(F.pmod(deal, F.col("rests"))).cast("int"))
    others = F.sequence(F.when(F.col("t") < 0, 0).otherwise(-F.col("mains")), F.col("rests") - 1)
    rest = [c for c in members.columns if c not in ("grp", "weight")]
    return own.withColumn("u", F.explode(others)).select("grp", F.least("t", "u").alias("i"), F.greatest("t", "u").alias("j"), "t", *rest)


def sides(t: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the two tiles that meet; both are the same for a tile and itself."""
    return np.flatnonzero(t == i[0]), np.flatnonzero(t == j[0])


def _near_bits(table: pa.Table) -> Iterator[tuple[int, np.ndarray]]:
    """Of each row of the first tile, the rows of the second that are in another component and whose bitmap is near enough."""
    t, i, j, label, size = (np.asarray(table.column(c)) for c in ("t", "i", "j", "label", "size"))
    bits = np.frombuffer(b"".join(table.column("sketch").to_pylist()), np.uint64).reshape(len(t), -1)
    ours, theirs = sides(t, i, j)
    for x in ours.tolist():
        y = theirs[label[theirs] != label[x]]
        lo, hi = np.minimum(size[y], size[x]), np.maximum(size[y], size[x])
        y = y[hi * NUM <= lo * DEN]
        far = np.bitwise_count(bits[y] ^ bits[x]).sum(1)
        y = y[far * (DEN + NUM) <= (size[y] + size[x]) * (DEN - NUM)]
        if len(y):
            yield x, y


def likely_links(members: DataFrame) -> DataFrame:
    """a, b: in each pair of tiles, a forest of pairs whose bitmaps are near enough: at most one row less than members."""

    def compare(table: pa.Table) -> pa.Table:
        cls, root, out = np.asarray(table.column("cls")), np.asarray(table.column("label")).copy(), []
        for x, y in _near_bits(table):
            for k in y[np.argsort(cls[y], kind="stable")].tolist():
                if root[k] != root[x]:
                    out.append((min(cls[x], cls[k]), max(cls[x], cls[k])))
                    root[root == root[k]] = root[x]
        return pa.table({"a": pa.array([int(p) for p, _ in out], pa.int64()), "b": pa.array([int(q) for _, q in out], pa.int64())})

    return tiles(members, TILE).groupBy("grp", "i", "j").applyInArrow(compare, "a long, b long").distinct()


def open_pairs(members: DataFrame, most: int = PARTNERS) -> tuple[DataFrame, DataFrame]:
    """(a, b) and (grp, cls, label, size) of what may still link: each pair of which one side has at most ``most`` partners by its bitmap, and the members with more.

    Of groups with the same such members one stays.
    """
    schema = pa.schema([("pair", pa.bool_()), ("grp", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("size", pa.int64())])

    def compare(table: pa.Table) -> pa.Table:
        cls, label, size, grp = (np.asarray(table.column(c)) for c in ("cls", "label", "size", "grp"))
        many, few, found = np.zeros(len(cls), np.int64), [], []
        for x, y in _near_bits(table):
            many[x] += len(y)
            many[y] += 1
            found.append((x, y))
        for x, y in found:
            y = y if many[x] <= most else y[many[y] <= most]
            few += [(min(cls[x], cls[k]), max(cls[x], cls[k])) for k in y.tolist()]
        two = np.unique(np.array(few, np.int64).reshape(-1, 2), axis=0)
        rest = np.flatnonzero(many > most)
        kind = np.repeat([True, False], [len(two), len(rest)])
        columns = (kind, np.full(len(kind), grp[0]), np.concatenate([two[:, 0], cls[rest]]), np.concatenate([two[:, 1], label[rest]]), np.concatenate([np.zeros(len(two), np.int64), size[rest]]))
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    found = settle(tiles(members, TILE).groupBy("grp", "i", "j").applyInArrow(compare, "pair boolean, grp long, a long, b long, size long"), "open")
    rest = found.filter("not pair").select("grp", F.col("a").alias("cls"), F.col("b").alias("label"), "size").distinct()
    mark = F.xxhash64("cls")
    same = rest.groupBy("grp").agg(F.count(F.lit(1)).alias("n"), F.bit_xor(mark).alias("x"), F.sum(mark.cast("decimal(20,0)")).alias("s"))
    one = same.groupBy("n", "x", "s").agg(F.min("grp").alias("grp")).select("grp")
    return found.filter("pair").select("a", "b").distinct(), rest.join(one, "grp")


def shared_counts(x: list[np.ndarray], y: list[np.ndarray], columns: int = 4096) -> np.ndarray:
    """How many elements each set of x has in common with each of y: products of 0/1 matrices over the elements that both sides have."""
    ends = [np.repeat(np.arange(len(z)), [len(s) for s in z]) for z in (x, y)]
    values = [np.concatenate(z) if z else np.empty(0, np.uint64) for z in (x, y)]
    both = np.intersect1d(*values)
    out = np.zeros((len(x), len(y)), np.float32)
    at = [np.searchsorted(both, v) for v in values]
    kept = [(p < len(both)) & (both[np.minimum(p, len(both) - 1)] == v) if len(both) else np.zeros(len(v), bool) for p, v in zip(at, values, strict=True)]
    for a in range(0, len(both), columns):
        m = []
        for side, n in ((0, len(x)), (1, len(y))):
            here = kept[side] & (at[side] >= a) & (at[side] < a + columns)
            m.append(np.zeros((n, min(columns, len(both) - a)), np.float32))
            m[side][ends[side][here], at[side][here] - a] = 1
        out += m[0] @ m[1].T
    return out.astype(np.int64)


def joining_links(members: DataFrame, sets: DataFrame, limit: int = TILE_ITEMS) -> DataFrame:
    """a, b: labels of components that a link joins, at most one row less than a tile has members; every pair of members in different components is verified on whole sets."""

    def verify_all(table: pa.Table) -> pa.Table:
        t, i, j, label = (np.asarray(table.column(c)) for c in ("t", "i", "j", "label"))
        items = [np.frombuffer(x, "<u8") for x in table.column("items").to_pylist()]
        size = np.array([len(x) for x in items])
        ours, theirs = sides(t, i, j)
        both = shared_counts([items[k] for k in ours], [items[k] for k in theirs])
        links = both * DEN >= (size[ours][:, None] + size[theirs][None, :] - both) * NUM
        root, out = label.copy(), []
        for r, x in enumerate(ours.tolist()):
            for y in theirs[links[r]].tolist():
                if root[y] != root[x]:
                    out.append((int(label[x]), int(label[y])))
                    root[root == root[y]] = root[x]
        return pa.table({"a": pa.array([p for p, _ in out], pa.int64()), "b": pa.array([q for _, q in out], pa.int64())})

    spread = tiles(members.withColumn("weight", F.col("size") + 512), limit)
    return spread.join(sets, "cls").groupBy("grp", "i", "j").applyInArrow(verify_all, "a long, b long")


def _labelled(members: DataFrame, labels: DataFrame) -> DataFrame:
    """members with the label of their component (a class without a link is its own) and weight 1."""
    return members.join(labels.toDF("cls", "label"), "cls", "left").withColumn("label", F.coalesce("label", "cls")).withColumn("weight", F.lit(1))


def _by_label(links: DataFrame, members: DataFrame) -> DataFrame:
    """links between classes as links between the labels of their components."""
    of = members.select("cls", "label").distinct()
    return links.join(of.toDF("a", "p"), "a").join(of.toDF("b", "q"), "b").select(F.col("p").alias("a"), F.col("q").alias("b"))


def _merged(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (node, label) after their components are joined by links between labels."""
    links = settle(links, "links")
    if links.isEmpty():
        return labels
    joined = components(links).toDF("label", "to")
    # labels of classes without a link are the classes themselves
    alone = joined.select(F.col("label").alias("node"), "label").join(labels.select("node"), "node", "left_anti")
    return settle(labels.unionByName(alone).join(joined, "label", "left").select("node", F.coalesce("to", "label").alias("label")), "labels")


# --- the operator -----------------------------------------------------------------------------------


def document_classes(docs: DataFrame, id_col: str, text_col: str, k: int) -> DataFrame:
    """A row per document: key columns, id, n_shingles, cls (null: empty set), sketch, items (the sorted set as bytes)."""
    schema = pa.schema([("__bt_k1", pa.int64()), ("__bt_k2", pa.int64()), ("id", pa.int64()), ("n_shingles", pa.int64()), ("cls", pa.int64()), ("sketch", pa.binary()), ("items", pa.binary())])

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _slices(batches, "text"):
            sets = shingle_sets(part.column("text"), k)
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in ("__bt_k1", "__bt_k2", "id")), pa.array([len(s) for s in sets], pa.int64()), pa.array([class_of(s) if len(s) else None for s in sets], pa.int64()), pa.array([sketch_of(s) if len(s) else None for s in sets], pa.binary()), pa.array([s.astype("<u8").tobytes() if len(s) else None for s in sets], pa.binary())], schema=schema)

    rows = docs.select(*key_of(id_col, text_col), F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return rows.mapInArrow(make, "__bt_k1 long, __bt_k2 long, id long, n_shingles long, cls long, sketch binary, items binary")


def join_components(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", k: int = 5, buckets: int | None = None, bloom_bits: int | None = None) -> DataFrame:
    """A row per document: key columns, id, n_shingles, cls, component (class label), component_id (smallest id of the component; its own for an empty set).

    The tables written on the way are deleted at its end.
    """
    with temporary(docs.sparkSession) as keep:
        return keep(_components_of(docs, id_col, text_col, k, buckets, bloom_bits), "joined")


def _components_of(docs: DataFrame, id_col: str, text_col: str, k: int, buckets: int | None, bloom_bits: int | None) -> DataFrame:
    spark = docs.sparkSession
    buckets = buckets or max(8, int(spark.conf.get("spark.sql.shuffle.partitions")))
    known = settle(document_classes(docs, id_col, text_col, k), "classes")
    sketches = settle(known.filter("cls is not null").groupBy("cls").agg(F.first("sketch").alias("sketch")), "sketches")
    # texts are read once: what follows needs the written sets alone
    stored = known.filter("cls is not null").select("cls", "items")

    found, only, seed = None, None, 0
    while True:  # again only for sets whose probing was not complete
        new = settle(candidates(signature_blocks(stored, buckets, seed, only)), "candidates")
        found = new if found is None else found.union(new)
        again = new.filter("kind = 2").select(F.col("a").alias("cls"))
        if again.isEmpty():
            break
        only, seed = build(again, "cls", bloom_bits), seed + 1

    pairs = settle(found.filter("kind = 0").select("a", "b").distinct(), "pairs")
    groups = settle(found.filter("kind = 1").select(F.col("a").alias("grp"), F.col("b").alias("cls"), "size").distinct(), "groups")
    wanted = pairs.select(F.col("a").alias("cls")).union(pairs.select("b")).union(groups.select("cls"))
    sets = settle(class_sets(stored, build(wanted, "cls", bloom_bits)), "sets")
    links = settle(verify(pairs, sets), "links")
    labels = components(links)
    members = settle(_labelled(groups, labels).join(sketches, "cls"), "members")
    likely = settle(likely_links(members).join(pairs, ["a", "b"], "left_anti"), "likely")
    links = settle(verify(likely, sets), "links")
    labels = _merged(labels, _by_label(links, members))
    members = settle(_labelled(members.drop("label", "weight"), labels), "members")
    two, rest = open_pairs(members)
    links = settle(verify(two.join(pairs, ["a", "b"], "left_anti").join(likely, ["a", "b"], "left_anti"), sets), "links")
    labels = _merged(labels, _by_label(links, members))
    rest = settle(_labelled(rest.drop("label"), labels), "rest")
    if not rest.isEmpty():
        labels = _merged(labels, joining_links(rest, sets))
    named = known.join(labels.toDF("cls", "label"), "cls", "left").withColumn("label", F.coalesce("label", "cls"))
    least = settle(named.filter("label is not null").groupBy("label").agg(F.min("id").alias("least")), "least")
    return named.join(least, "label", "left").select("__bt_k1", "__bt_k2", "id", "n_shingles", "cls", F.col("label").alias("component"), F.when(F.col("cls").isNull(), F.col("id")).otherwise(F.col("least")).alias("component_id"))


def link_report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row per input row: id, n_shingles, component_id."""
    return join_components(docs, id_col=id_col, text_col=text_col, **options).select(F.col("id").alias(id_col), "n_shingles", "component_id")


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs without all but one document (the one of smallest id) of each linked group; documents with empty sets all stay."""
    rows = join_components(docs, id_col=id_col, text_col=text_col, **options)
    best = rows.filter("cls is not null").groupBy("component").agg(F.min(F.struct(F.col("id").isNull().alias("none"), F.col("id").alias("i"), F.col("__bt_k1").alias("k1"), F.col("__bt_k2").alias("k2"))).alias("best"))
    keep = best.select(F.col("best.k1").alias("__bt_k1"), F.col("best.k2").alias("__bt_k2"), F.lit(True).alias("__bt_one")).union(rows.filter("cls is null").select("__bt_k1", "__bt_k2", F.lit(False)).distinct())
    joined = docs.select("*", *key_of(id_col, text_col)).join(settle(keep, "keep").hint("merge"), ["__bt_k1", "__bt_k2"])
    # rows equal in id and text have one key: one of them stays
    turn = F.row_number().over(Window.partitionBy("__bt_k1", "__bt_k2").orderBy(F.lit(0)))
    return joined.withColumn("__bt_turn", turn).filter("not __bt_one or __bt_turn = 1").select(*docs.columns)
