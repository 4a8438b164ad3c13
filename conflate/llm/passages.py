"""Substring dedup: words covered by a passage of ``size`` words that starts anywhere else are removed.

Words are runs of characters other than the ASCII blanks, unchanged.  Every window of ``size`` consecutive
words has one anchor, its phrase of ``GRAM`` words with the least hash (the first such phrase); equal windows
have equal anchors, so only windows under a recurring anchor can recur.  Windows in a row under one anchor
form a run of at most size - GRAM + 1 windows.

1. Anchors are counted over all documents; those that occur once are done.
2. Under the others, equal runs confirm all their windows at once.  Where an anchor also has runs that differ,
   as at the ends of a shared passage, the windows of one copy of each such run are counted one by one.
3. Each stretch of confirmed windows of a run is a passage, read as a word sequence from one document.
4. A document's least confirmed anchor names its shard, so that copies meet in one shard; a shard's dictionary is
   every passage that one of its documents may hold.  Shards have about ``PASSAGES`` passages, and a shard of many
   documents is dealt to several tasks with the dictionary in each.
5. Every task reads its shards one after the other: it compiles the dictionary into an Aho-Corasick automaton whose
   letters are words, streams the shard's documents through it, and removes the words of every occurrence found.
   Nothing else tells it where a passage stands; a 64-bit hash of the words confirms each occurrence.  Documents
   without a confirmed anchor can't hold a passage and only have their words counted.

No step gathers a group of equal passages in one place: counts combine on the map side, and what is carried
back is one small row per run of a document.  Defined results: null and empty texts have no words; texts under
``size`` words lose nothing; repeated rows (and repeated or null doc_ids) are separate occurrences; overlapping
windows of one document count as different starts, so long repetitions within one text are removed too; an empty
table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import small_batches, text_key
from conflate.llm.textkit import _STEP, _STEP_INV, BLANK_SPLIT, Words, _power, mix, pieces, ranges, signed
from conflate.plans.tables import broadcast_if_small, discard, materialise

SIZE = 35
GRAM = 12
#: Rows of one or two longs up to which a side is broadcast.
NARROW_ROWS = 1_000_000
#: Passages of one automaton, about, and documents of one task of a shard at most.
PASSAGES = 10_000
DOCUMENTS = 2_000
_U = np.uint64


class Runs:
    """Windows, anchors and runs of one piece."""

    def __init__(self, w: Words, size: int, gram: int):
        self.at, self.hash = w.windows(size)
        g_at, g = w.windows(gram)
        n, width = len(w.hash), size - gram + 1
        self.gram = np.full(n, np.iinfo(_U).max, _U)
        self.gram[g_at] = g
        least, where, have = self.gram, np.arange(n), 1
        while have < width:
            k = min(have, width - have)
            if len(least) <= k:  # fewer words than a window: there is none
                break
            later = least[k:] < least[: len(least) - k]
            least, where, have = np.where(later, least[k:], least[: len(least) - k]), np.where(later, where[k:], where[: len(where) - k]), have + k
        self.anchor_at = where[self.at] if len(self.at) else np.zeros(0, np.int64)
        first = np.ones(len(self.at), bool)
        first[1:] = (self.anchor_at[1:] != self.anchor_at[:-1]) | (self.at[1:] != self.at[:-1] + 1)
        self.first = np.flatnonzero(first)
        self.count = np.diff(np.append(self.first, len(self.at)))
        self.anchor = self.gram[self.anchor_at[self.first]] if len(self.first) else np.zeros(0, _U)
        last = self.first + self.count - 1
        self.id = mix(self.hash[self.first] * _U(3) ^ mix(self.hash[last] + _U(1)) ^ self.count.astype(_U)) if len(self.first) else np.zeros(0, _U)
        self.doc = w.doc[self.at[self.first]] if len(self.first) else np.zeros(0, np.int64)


def _anchors(size: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in pieces(b.column(0)):
                values, n = np.unique(Runs(Words(b.column(0).slice(lo, hi - lo)), size, gram).anchor, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(signed(values)), pa.array(n)], ["anchor", "n"])

    return run


def _runs(size: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            key = b.column(0).to_numpy()
            for lo, hi in pieces(b.column(1)):
                r = Runs(Words(b.column(1).slice(lo, hi - lo)), size, gram)
                yield pa.RecordBatch.from_arrays([pa.array(key[lo + r.doc]), pa.array(signed(r.anchor)), pa.array(signed(r.id))], ["key", "anchor", "run"])

    return run


def _windows(size: int, gram: int):
    """Windows of the runs asked for: (run, place in the run, window hash)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in pieces(b.column(0)):
                asked = b.column(1).slice(lo, hi - lo)
                r = Runs(Words(b.column(0).slice(lo, hi - lo)), size, gram)
                pairs_doc = np.repeat(np.arange(hi - lo), np.asarray(asked.value_lengths()))
                want = np.unique(mix(asked.flatten().to_numpy().view(_U)) ^ pairs_doc.astype(_U))
                mine, once = np.unique(mix(r.id) ^ r.doc.astype(_U), return_index=True)
                at = once[np.isin(mine, want)]
                place = ranges(r.count[at])
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(signed(r.id)[at], r.count[at])), pa.array(place.astype(np.int32)), pa.array(signed(r.hash)[np.repeat(r.first[at], r.count[at]) + place])], ["run", "place", "window"])

    return run


def letters(w: Words) -> np.ndarray:
    """A 16-bit character for each word, by hash: below the surrogates, above the controls."""
    return ((w.hash >> _U(40)) % _U(0xD7E0) + _U(0x20)).astype(np.uint16)


class Sequences:
    """64-bit hashes of any word sequences of one piece."""

    def __init__(self, w: Words):
        n = len(w.hash)
        self.total = np.zeros(n + 1, _U)
        np.cumsum(w.hash * _power("word", _STEP, n), out=self.total[1:])
        self.inv = _power("word_inv", _STEP_INV, n + 1)

    def hash(self, at: np.ndarray, size: np.ndarray) -> np.ndarray:
        return mix((self.total[at + size] - self.total[at]) * self.inv[at] + size.astype(_U))


def stretches(mask: int, n: int) -> list[tuple[int, int]]:
    """(first, windows) of the runs of set bits among n; -1 stands for all."""
    if mask == -1:
        return [(0, n)]
    out, k = [], 0
    while k < n:
        if mask >> k & 1:
            first = k
            while k < n and mask >> k & 1:
                k += 1
            out.append((first, k - first))
        k += 1
    return out


def _passages(size: int, gram: int):
    """(run, phrase, check) of the confirmed stretches of the runs asked for: two bytes a word, and the words' hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in pieces(b.column(0)):
                w = Words(b.column(0).slice(lo, hi - lo))
                r, code, sequences = Runs(w, size, gram), letters(w), Sequences(w)
                ids = signed(r.id)
                first_of = {(d, i): k for k, (d, i) in reversed(list(enumerate(zip(r.doc.tolist(), ids.tolist()))))}
                names, at, length = [], [], []
                for d, asked in enumerate(b.column(1).slice(lo, hi - lo).to_pylist()):
                    for a in asked:
                        k = first_of.get((d, a["run"]))
                        if k is None:
                            continue
                        for first, n in stretches(a["mask"], int(r.count[k])):
                            names.append(a["run"])
                            at.append(int(r.at[r.first[k] + first]))
                            length.append(n + size - 1)
                at, length = np.array(at, np.int64), np.array(length, np.int64)
                phrases = [code[i : i + n].tobytes() for i, n in zip(at.tolist(), length.tolist())]
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(phrases, pa.binary()), pa.array(signed(sequences.hash(at, length)))], ["run", "phrase", "check"])

    return run


def automaton_of(phrases: list[bytes]) -> ahocorasick.Automaton | None:
    """The automaton that finds the phrases' ends; an occurrence carries the phrase's place in the list."""
    if not phrases:
        return None
    made = ahocorasick.Automaton()
    for i, p in enumerate(phrases):
        made.add_word(p.decode("utf-16-le"), i)
    made.make_automaton()
    return made


def covered(w: Words, automaton: ahocorasick.Automaton | None, sizes: np.ndarray, checks: np.ndarray) -> np.ndarray:
    """Which words lie in a passage that the automaton finds."""
    hit = np.zeros(len(w.hash) + 1, np.int64)
    if automaton is not None and len(w.hash):
        code, ends, which = letters(w), [], []
        for d in range(w.n_docs):
            a, z = int(w.first[d]), int(w.first[d + 1])
            for end, i in automaton.iter(code[a:z].tobytes().decode("utf-16-le")):
                ends.append(a + end + 1)
                which.append(i)
        which = np.array(which, np.int64)
        at = np.array(ends, np.int64) - sizes[which]
        true = Sequences(w).hash(at, sizes[which]) == checks[which]
        np.add.at(hit, at[true], 1)
        np.subtract.at(hit, (at + sizes[which])[true], 1)
    return np.cumsum(hit[:-1]) > 0


def _kept(ids: pa.Array, col: pa.Array, automaton, sizes: np.ndarray, checks: np.ndarray, texts: bool) -> Iterator[pa.RecordBatch]:
    for lo, hi in pieces(col):
        w = Words(col.slice(lo, hi - lo), BLANK_SPLIT)
        gone = covered(w, automaton, sizes, checks)
        lost = np.add.reduceat(np.append(gone, 0).astype(np.int64), w.first[:-1]) if len(w.first) > 1 else np.zeros(0, np.int64)
        lost[w.counts() == 0] = 0
        buf, kept = w.data.tobytes(), []
        for d in range(hi - lo):
            i, j = w.first[d], w.first[d + 1]
            keep = np.flatnonzero(~gone[i:j]) + i
            kept.append(b" ".join([buf[s:e] for s, e in zip(w.start[keep].tolist(), w.end[keep].tolist())]))
        result = pa.array([k.decode() for k in kept], pa.string()) if texts else pa.array([hashlib.sha256(k).hexdigest() for k in kept], pa.string())
        yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo), pa.array(w.counts()), pa.array(lost), result], ["doc_id", "n_words", "n_removed", "kept"])


_NONE = np.zeros(0, np.int64), np.zeros(0, _U)


def _count(texts: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield from _kept(b.column(0), b.column(1), None, *_NONE, texts)

    return run


def _stream(texts: bool):
    """Rows (shard, part, phrase, check, doc_id, text), a shard's phrases before its documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, phrases, checks, automaton, sizes = None, [], [], None, None
        for b in batches:
            shard, part, document = b.column(0).to_numpy(), b.column(1).to_numpy(), np.asarray(b.column(2).is_null())
            change = np.flatnonzero((shard[1:] != shard[:-1]) | (part[1:] != part[:-1]) | (document[1:] != document[:-1])) + 1
            for lo, hi in zip([0, *change.tolist()], [*change.tolist(), b.num_rows]):
                if lo == hi:
                    continue
                if now != (shard[lo], part[lo]):
                    now, phrases, checks, automaton, sizes = (shard[lo], part[lo]), [], [], None, None
                rows = b.slice(lo, hi - lo)
                if not document[lo]:
                    phrases += rows.column(2).to_pylist()
                    checks += rows.column(3).to_pylist()
                    continue
                if sizes is None:
                    automaton, sizes = automaton_of(phrases), np.array([len(p) // 2 for p in phrases], np.int64)
                    known = np.array(checks, np.int64).view(_U)
                yield from _kept(rows.column(4), rows.column(5), automaton, sizes, known, texts)

    return run


def confirmed(docs: DataFrame, size: int = SIZE, gram: int = GRAM) -> tuple[DataFrame, DataFrame]:
    """(key, anchor, run) of the runs with a confirmed window, by the text's hash; (run, mask, key of one text)."""
    rows = docs.select(text_key(F.col("text")).alias("key"), "text")
    often = rows.select("text").mapInArrow(_anchors(size, gram), "anchor long, n long").groupBy("anchor").agg(F.sum("n").alias("n")).where("n > 1").select("anchor")
    often = materialise(often, "anchors")
    held = rows.mapInArrow(_runs(size, gram), "key long, anchor long, run long")
    held = materialise(held.join(broadcast_if_small(often, limit=NARROW_ROWS), "anchor").select("key", "anchor", "run"), "runs")
    discard(often)
    distinct = materialise(held.groupBy("anchor", "run").agg(F.count("*").alias("n"), F.min("key").alias("key")), "distinct")
    # anchors with a run of one occurrence: there single windows count, else whole runs decide
    split = distinct.groupBy("anchor").agg(F.min("n").alias("least"), F.count("*").alias("kinds")).where("least = 1 and kinds > 1").select("anchor")
    # two starts under one anchor in one document may be equal windows too: such anchors are in `split` or equal runs
    single = materialise(distinct.join(split, "anchor", "left_semi"), "single")
    asked = single.groupBy("key").agg(F.collect_list("run").alias("asked"))
    text_once = rows.join(asked, "key").select("text", "asked")
    seen = text_once.mapInArrow(_windows(size, gram), "run long, place int, window long").join(single.select("run", "n"), "run")
    # a text that stands in several rows gives its windows as often: count each (run, place) once
    seen = materialise(seen.distinct(), "windows")
    many = seen.groupBy("window").agg(F.sum("n").alias("all")).where("all > 1").select("window")
    partial = seen.join(many, "window", "left_semi").groupBy("run").agg(F.bit_or(F.expr("shiftleft(1L, place)")).alias("mask"))
    whole = distinct.where("n > 1").select("run", F.lit(-1).cast("long").alias("mask"))
    masks = whole.unionByName(partial).groupBy("run").agg(F.min("mask").alias("mask"))
    masks = materialise(masks.join(distinct.groupBy("run").agg(F.min("key").alias("key")), "run"), "masks")
    out = materialise(held.distinct().join(masks.select("run"), "run").select("key", "anchor", "run"), "held")
    for done in (held, distinct, single, seen):
        discard(done)
    return out, masks


def remove(docs: DataFrame, size: int = SIZE, gram: int = GRAM, texts: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed and the kept words joined by blanks (``kept``), or their sha256 without ``texts``."""
    small_batches(docs.sparkSession)
    held, masks = confirmed(docs, size, gram)
    asked = masks.groupBy("key").agg(F.collect_list(F.struct("run", "mask")).alias("asked"))
    rows = docs.select("doc_id", "text", text_key(F.col("text")).alias("key"))
    once = rows.select("key", "text").join(asked, "key").dropDuplicates(["key"]).select("text", "asked")
    phrases = materialise(once.mapInArrow(_passages(size, gram), "run long, phrase binary, check long"), "passages")
    home = materialise(held.groupBy("key").agg(F.min("anchor").alias("home")), "homes")
    needs = materialise(held.join(home, "key").select("home", "run").distinct(), "needs")
    discard(held)
    shards = max(1, needs.count() // PASSAGES)
    shard = F.pmod(F.xxhash64("home"), F.lit(shards)).alias("shard")
    sizes = rows.select("key").join(home, "key").select(shard).groupBy("shard").agg(F.count("*").alias("documents"))
    parts = materialise(sizes.select("shard", F.ceil(F.col("documents") / F.lit(DOCUMENTS)).cast("int").alias("parts")), "parts")
    dictionary = needs.select(shard, "run").distinct().join(phrases, "run").select("shard", "phrase", "check").distinct().join(parts, "shard")
    kind = docs.schema["doc_id"].dataType.simpleString()
    dictionary = dictionary.select("shard", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), "phrase", "check", F.lit(None).cast(kind).alias("doc_id"), F.lit(None).cast("string").alias("text"))
    homed = rows.join(home, "key").select(shard, "doc_id", "text").join(broadcast_if_small(parts), "shard")
    homed = homed.select("shard", F.pmod(F.monotonically_increasing_id(), F.col("parts")).cast("int").alias("part"), F.lit(None).cast("binary").alias("phrase"), F.lit(None).cast("long").alias("check"), "doc_id", "text")
    # a null phrase is a document, and comes after the phrases
    dealt = dictionary.unionByName(homed).repartition("shard", "part").sortWithinPartitions("shard", "part", F.col("phrase").isNull())
    out = f"doc_id {kind}, n_words long, n_removed long, kept string"
    found = dealt.mapInArrow(_stream(texts), out)
    others = rows.join(broadcast_if_small(home.select("key"), limit=NARROW_ROWS), "key", "left_anti").select("doc_id", "text")
    return found.unionByName(others.mapInArrow(_count(texts), out))
