"""Benchmark decontamination: fingerprints of item-sized windows, Hamming blocks, exact similarity.

Texts and items are lower-cased words of letters and digits; their elements are runs of five words, weighted by
count (an item or text under five words is one element).  A window has as many words as the item it is compared
with (or is the whole text, where that is shorter).  Its SimHash is 64 bits over its elements.  Fingerprints are cut
into ``BLOCKS`` blocks; two that differ in ``RADIUS`` bits at most differ in RADIUS // BLOCKS bits at most in one
block at least, so a table that lists, for every value of a block, the items within that many bits of it misses none
of the radius.  The tables choose the items that a window is compared with; those within the radius are verified by
the weighted Jaccard similarity of the elements, and the best window of each (document, item) at ``SIMILAR`` or more
is returned.  At a similarity of 0.8 fingerprints differ in 9.7 bits on average with a deviation of 2.9, so about one
such window in 2,000 lies outside the radius; neighbouring windows are further chances.

Every window of an item's size that shares any element with any item is fingerprinted; others have similarity 0.

Items go to every task, ``ITEMS_AT_ONCE`` at a time; a longer list makes several passes.  Defined results: null
and empty texts and items match nothing; repeated items are reported each; repeated documents are rows of
their own; ties between windows go to the first.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import small_batches, text_key
from conflate.llm.textkit import ALNUM, Words, mix, pieces
from conflate.plans.tables import broadcast_if_small, materialise

WORDS = 5
SIMILAR = 0.8
RADIUS = 19
BLOCKS = 5
ITEMS_AT_ONCE = 4_000
_U = np.uint64
_BITS = np.arange(64, dtype=_U)


def fingerprint(h: np.ndarray) -> np.uint64:
    """SimHash of a bag of element hashes."""
    votes = ((mix(h)[:, None] >> _BITS) & _U(1)).astype(np.int64).sum(0) * 2 - len(h)
    return np.bitwise_or.reduce(np.where(votes > 0, _U(1) << _BITS, _U(0)))


def blocks() -> list[tuple[int, int]]:
    """(first bit, bits) of the blocks of 64 bits."""
    cuts = [64 * i // BLOCKS for i in range(BLOCKS + 1)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:])]


class Lanes:
    """Bit counts of any windows of a row of elements: several bits' running sums share one long."""

    def __init__(self, h: np.ndarray, most: int):
        self.width = 8 if most < 128 else 16 if most < 1 << 15 else 32
        self.ones = _U(sum(1 << i for i in range(0, 64, self.width)))
        mixed = mix(h)
        self.sums = np.zeros((self.width, len(h) + 1), _U)
        for j in range(self.width):
            np.cumsum(mixed >> _U(j) & self.ones, out=self.sums[j, 1:])

    def prints(self, start: np.ndarray, span: int) -> np.ndarray:
        """Fingerprints of the windows of ``span`` elements: the bits that more than half of them have."""
        room, top, out = _U((1 << self.width - 1) - 1 - span // 2) * self.ones, _U(self.width - 1), np.zeros(len(start), _U)
        for j in range(self.width):
            out |= (self.sums[j, start + span] - self.sums[j, start] + room >> top & self.ones) << _U(j)
        return out


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Weighted Jaccard of two bags."""
    ua, ca = np.unique(a, return_counts=True)
    ub, cb = np.unique(b, return_counts=True)
    _, ia, ib = np.intersect1d(ua, ub, assume_unique=True, return_indices=True)
    shared = np.minimum(ca[ia], cb[ib]).sum()
    total = len(a) + len(b) - shared
    return float(shared / total) if total else 0.0


class Near:
    """Block tables over some items: a bit for each item within the block's share of the radius of a value."""

    def __init__(self, prints: np.ndarray, radius: int):
        self.prints, self.radius = prints, radius
        self.tables = []
        for first, bits in blocks():
            value = np.arange(1 << bits, dtype=_U)
            table = np.zeros((-(-len(prints) // 64), 1 << bits), _U)
            for i, f in enumerate(prints):
                near = np.bitwise_count(value ^ (f >> _U(first) & _U((1 << bits) - 1))) <= radius // BLOCKS
                table[i // 64] |= near.astype(_U) << _U(i % 64)
            self.tables.append((_U(first), _U((1 << bits) - 1), table))

    def search(self, f: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """(item, places of the fingerprints within the radius of it) of the items that the tables name."""
        for word in range(len(self.tables[0][2])):
            found = np.zeros(len(f), _U)
            for first, mask, table in self.tables:
                found |= table[word][(f >> first & mask).astype(np.int64)]
            some = int(np.bitwise_or.reduce(found)) if len(found) else 0
            for i in range(64):
                if some >> i & 1:
                    at = np.flatnonzero(found >> _U(i) & _U(1))
                    at = at[np.bitwise_count(f[at] ^ self.prints[word * 64 + i]) <= self.radius]
                    if len(at):
                        yield word * 64 + i, at


@dataclass
class Items:
    """ids, words and elements of the items, their distinct elements and fingerprints."""

    ids: list
    size: np.ndarray
    bags: list[np.ndarray]
    prints: np.ndarray
    keys: np.ndarray

    @classmethod
    def build(cls, ids: list, texts: pa.Array, words: int) -> "Items":
        w = Words(texts, ALNUM, fold=True)
        d, h = w.shingles(words)
        keep = np.flatnonzero(w.counts() > 0)
        first = np.searchsorted(d, np.arange(w.n_docs + 1))
        bags = [h[first[i] : first[i + 1]] for i in keep]
        prints = np.array([fingerprint(b) for b in bags], _U) if bags else np.zeros(0, _U)
        keys = np.unique(np.concatenate(bags)) if bags else np.zeros(0, _U)
        return cls([ids[i] for i in keep], w.counts()[keep], bags, prints, keys)

    def by_span(self, words: int) -> list[tuple[int, np.ndarray]]:
        """(elements of a window, items of that size) for items of ``words`` words or more."""
        return [(int(n) - words + 1, np.flatnonzero(self.size == n)) for n in np.unique(self.size[self.size >= words])]


def _search(sent, words: int, least: float, radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items: Items = sent.value
        sieve = np.zeros(1 << 22, bool)
        sieve[(items.keys & _U((1 << 22) - 1)).astype(np.int64)] = True
        shorter = sorted({int(s) for s in items.size if s < words})
        spans = [(span, mine, Near(items.prints[mine], radius)) for span, mine in items.by_span(words)]
        for b in batches:
            for lo, hi in pieces(b.column(1)):
                w = Words(b.column(1).slice(lo, hi - lo), ALNUM, fold=True)
                found = []
                at, h = w.windows(words)
                hit = np.flatnonzero(sieve[(h & _U((1 << 22) - 1)).astype(np.int64)])
                if len(hit) and len(items.keys):
                    k = np.minimum(np.searchsorted(items.keys, h[hit]), len(items.keys) - 1)
                    found += _windows(items, w, at, h, hit[items.keys[k] == h[hit]], spans, least)
                if shorter or (w.counts() < words).any():
                    found += _short(items, w, words, shorter)
                if found:
                    found.sort()
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array([lo + f[0] for f in found])), pa.array([f[1] for f in found], pa.int32()), pa.array([f[2] for f in found], pa.int32()), pa.array([f[3] for f in found], pa.float64())], ["doc_id", "item", "first_word", "similarity"])

    return run


def _windows(items: Items, w: Words, at: np.ndarray, h: np.ndarray, hit: np.ndarray, spans: list, least: float) -> list:
    """The best window of each document for each item, among the windows that hold an element of any item."""
    if not len(hit) or not spans:
        return []
    doc = w.doc[at]
    rows = np.unique(doc[hit])
    # only the documents with such an element, one after the other
    edge = np.searchsorted(doc, np.stack([rows, rows + 1]))
    pick = np.concatenate([np.arange(a, z) for a, z in edge.T])
    h, at, doc = h[pick], at[pick], doc[pick]
    shared = np.zeros(len(h) + 1, np.int64)
    shared[np.searchsorted(pick, hit) + 1] = 1
    shared = np.cumsum(shared)
    lanes = Lanes(h, max(s for s, _, _ in spans))
    ends = np.searchsorted(doc, rows, "right")
    starts = np.searchsorted(doc, rows)
    best: dict[tuple[int, int], tuple[float, int]] = {}

    def verify(mine: np.ndarray, near: Near, start: np.ndarray, span: int) -> None:
        for i, places in near.search(lanes.prints(start, span)):
            for s in start[places].tolist():
                key = (int(doc[s]), int(mine[i]))
                j = jaccard(h[s : s + span], items.bags[key[1]])
                if j >= least and j > best.get(key, (0.0, 0))[0]:
                    best[key] = (j, int(at[s]) - int(w.first[key[0]]))

    for span, mine, near in spans:
        n = len(h) - span + 1
        if n > 0:
            start = np.flatnonzero((doc[:n] == doc[span - 1 :]) & (shared[span:] > shared[:n]))
            verify(mine, near, start, span)
        # a shorter text is one window, if it can reach the similarity at all
        length = ends - starts
        for m in np.unique(length[(length < span) & (length >= least * span - 1e-9)]).tolist():
            verify(mine, near, starts[length == m], m)
    return [(d, i, p, j) for (d, i), (j, p) in best.items()]


def _short(items, w, words, shorter) -> list:
    """Items under ``words`` words: one element, equal or not."""
    out = []
    short_items: dict[int, dict[int, list[int]]] = {}
    for i, s in enumerate(items.size):
        if s < words:
            short_items.setdefault(int(s), {}).setdefault(int(items.bags[i][0]), []).append(i)
    for n in shorter:
        at, _ = w.windows(n)
        for s in at.tolist():
            whole = int(mix(np.bitwise_xor.reduce(mix(w.hash[s : s + n] + np.arange(n, dtype=_U)), keepdims=True))[0])
            for i in short_items[n].get(whole, ()):
                d = int(w.doc[s])
                out.append((d, i, s - int(w.first[d]), 1.0))
    firsts: dict = {}
    for d, i, p, j in sorted(out):
        firsts.setdefault((d, i), (d, i, p, j))
    return list(firsts.values())


def matches(docs: DataFrame, benchmark: DataFrame, words: int = WORDS, least: float = SIMILAR, radius: int = RADIUS) -> DataFrame:
    """(doc_id, item_id, first_word, similarity): the best window of each document for each item found in it."""
    spark = docs.sparkSession
    small_batches(spark)
    rows = benchmark.select("item_id", "text").where("text is not null")
    n = rows.count()
    chunks = max(1, -(-n // ITEMS_AT_ONCE))
    kind, item_kind = docs.schema["doc_id"].dataType.simpleString(), benchmark.schema["item_id"].dataType
    parts = []
    for c in range(chunks):
        here = rows if chunks == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(chunks)) == c)
        got = here.toArrow()
        ids = got.column("item_id").to_pylist()
        texts = pa.concat_arrays(got.column("text").chunks) if got.num_rows else pa.array([], pa.string())
        sent = spark.sparkContext.broadcast(Items.build(ids, texts, words))
        found = docs.select("doc_id", "text").mapInArrow(_search(sent, words, least, radius), f"doc_id {kind}, item int, first_word int, similarity double")
        names = spark.createDataFrame([(i, x) for i, x in enumerate(sent.value.ids)], f"item int, item_id {item_kind.simpleString()}")
        parts.append(found.join(F.broadcast(names), "item").select("doc_id", "item_id", "first_word", "similarity"))
    return reduce(DataFrame.unionByName, parts)


def decontaminate(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """``docs`` without the rows that hold a benchmark item; all columns kept.  Rows are judged by their text, so a
    null or shared doc_id takes no other row with it."""
    hashed = docs.select(text_key(F.col("text")).alias("doc_id"), "text")
    bad = materialise(matches(hashed, benchmark, **options).select(F.col("doc_id").alias("__th")).distinct(), "leaks")
    keyed = docs.withColumn("__th", text_key(F.col("text")))
    return keyed.join(broadcast_if_small(bad), "__th", "left_anti").select(*docs.columns)
