"""Sampled subword segmentations without replacement, and their decoding.

A text's lattice has every way to write it in pieces of a public vocabulary (a character outside it is written
in byte pieces).  A piece's weight falls with its rank, p ~ 1 / (rank + ``SHIFT``), and a segmentation's probability is
the product of its pieces' weights over the sum for all segmentations.  Every segmentation has a perturbed score, its
log-probability plus Gumbel noise; the ``k`` best perturbed scores are a sample of k distinct segmentations.

They are found by a best-first search whose bound is exact: the best perturbed score below a partial
segmentation is Gumbel noise around its total log-probability, and once that maximum is drawn, the branch that
attains it keeps the value while the others together draw theirs below it.  A finished search path leaves, at each of
its steps, the set of the other branches with one bound; the next sample continues from the set with the best bound.
Its inclusion score is 1 - exp(-exp(log p - t)), t being the (k + 1)-th perturbed score: the chance to have been
among the k given that threshold (1 where fewer than k + 1 segmentations exist).

No piece holds a space after another character, so the lattice falls apart at spaces; the distinct units of
192 KB of text share one lattice.  Randomness is a hash of the row key: a row gives the same samples in
any partition, and repeated keys give repeated samples.  Defined results: a null or empty text has one segmentation
without pieces; texts are never cut; decoding gives back the very text, literal block marks and all.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import small_batches
from conflate.llm.textkit import mix, pieces

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SHIFT = 10.0
SAMPLES = 2
#: Bytes of text whose distinct units share one lattice.
CHUNK = 3 << 16
_U = np.uint64
_UNIT = re.compile(" +[^ ]*|[^ ]+")


@dataclass
class Vocabulary:
    """Pieces with plain spaces as a trie in arrays, and what decoding needs.

    The trie's steps stand in an open-addressing table (``keys`` -> ``child``); ``piece`` and ``logp`` say what ends
    at a node.
    """

    pieces: dict[str, tuple[int, float]]
    byte_ids: np.ndarray
    byte_logp: float
    content: list[bytes]
    longest: int
    letter: np.ndarray
    keys: np.ndarray
    child: np.ndarray
    piece: np.ndarray
    logp: np.ndarray

    @classmethod
    def load(cls, path: str = MODEL, shift: float = SHIFT, power: float = 1.0) -> "Vocabulary":
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        names = sp.id_to_piece(list(range(n)))
        normal = [i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        normal.sort(key=lambda i: -sp.get_score(i))
        total = float(np.log((1 / (np.arange(len(normal)) + shift)).sum()))
        table = {names[i].replace("▁", " "): (i, power * (-float(np.log(r + shift)) - total)) for r, i in enumerate(normal)}
        bytes_ = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        content = [names[i].replace("▁", " ").encode() for i in range(n)]
        for b, i in enumerate(bytes_):
            content[i] = bytes([b])
        if any(" " in p.lstrip(" ") for p in table):
            raise ValueError("a piece holds a space after another character: texts can't be cut at spaces")
        return cls(table, np.array(bytes_), power * (-float(np.log(len(normal) + shift)) - total), content, max(map(len, table)), *_trie(table))


def _trie(table: dict[str, tuple[int, float]]) -> tuple[np.ndarray, ...]:
    letters = sorted({c for p in table for c in p})
    letter = np.zeros(0x110000, np.int32)
    letter[[ord(c) for c in letters]] = np.arange(1, len(letters) + 1)
    node: dict[str, int] = {"": 0}
    steps = []
    for p in sorted(table, key=len):
        for k in range(1, len(p) + 1):
            if p[:k] not in node:
                node[p[:k]] = len(node)
                steps.append((node[p[: k - 1]], int(letter[ord(p[k - 1])]), node[p[:k]]))
    size = 1 << max(12, (len(steps) * 6).bit_length())
    keys, child = np.full(size, -1, np.int64), np.zeros(size, np.int64)
    for a, c, z in steps:
        at = int(_slot(np.array([a << 21 | c]), size)[0])
        while keys[at] >= 0:
            at = (at + 1) % size
        keys[at], child[at] = a << 21 | c, z
    piece, logp = np.full(len(node), -1, np.int64), np.zeros(len(node))
    for p, (i, x) in table.items():
        piece[node[p]], logp[node[p]] = i, x
    return letter, keys, child, piece, logp


def _slot(key: np.ndarray, size: int) -> np.ndarray:
    return ((key.astype(_U) * _U(0x9E3779B97F4A7C15)) >> _U(65 - size.bit_length())).astype(np.int64)


def _step(v: Vocabulary, node: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The node one letter on; 0 where there is none."""
    key = node << 21 | c
    at = _slot(key, len(v.keys))
    held = v.keys[at]
    out = np.where(held == key, v.child[at], 0)
    open_ = np.flatnonzero((held != key) & (held >= 0))
    while len(open_):
        at[open_] = (at[open_] + 1) % len(v.keys)
        held = v.keys[at[open_]]
        same = held == key[open_]
        out[open_[same]] = v.child[at[open_[same]]]
        open_ = open_[~same & (held >= 0)]
    return out


class Lattice:
    """All ways to write the given distinct units in pieces.

    A state is a place in the units' joined characters.  Branches stand by state; ``upper`` is the state's number
    plus the cumulated probability, so that one binary search over all states draws a branch.  ``next`` is the
    state behind a branch, -1 at a unit's end; ``piece`` is a piece, or minus a code point to write in bytes.
    """

    def __init__(self, v: Vocabulary, units: list[str]):
        self.v = v
        sizes = np.fromiter(map(len, units), np.int64, len(units))
        stop = np.cumsum(sizes)
        self.root = stop - sizes
        codes = np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), np.uint32)
        n = len(codes)
        end = np.repeat(stop, sizes)
        letter = v.letter[codes].astype(np.int64)
        live, node, count, found = np.arange(n), np.zeros(n, np.int64), np.zeros(n, np.int64), []
        for k in range(v.longest):
            on = live + k < end[live]
            live, node = live[on], node[on]
            node = _step(v, node, letter[live + k])
            on = node > 0
            live, node = live[on], node[on]
            if not len(live):
                break
            hit = v.piece[node] >= 0
            src = live[hit]
            found.append((src, count[src], src + k + 1, v.piece[node[hit]], v.logp[node[hit]]))
            count[src] += 1
            if k == 0:
                lacks = np.ones(n, bool)
                lacks[src] = False
        if not found:
            lacks = np.ones(n, bool)
        raw = np.flatnonzero(lacks)
        width = 1 + (codes[raw] >= 0x80).astype(np.int64) + (codes[raw] >= 0x800) + (codes[raw] >= 0x10000)
        found.append((raw, count[raw], raw + 1, -codes[raw].astype(np.int64) - 1, v.byte_logp * width))
        count[raw] += 1
        self.begin = np.concatenate([[0], np.cumsum(count)])
        m = int(self.begin[-1])
        self.src, self.next, self.piece, score = np.zeros(m, np.int64), np.zeros(m, np.int64), np.zeros(m, np.int64), np.zeros(m)
        for src, rank, dst, piece, logp in found:
            at = self.begin[src] + count[src] - 1 - rank  # longest piece first: the likeliest, found at once
            self.src[at], self.next[at], self.piece[at], score[at] = src, dst, piece, logp
        del found, live, node, letter
        self.next[self.next == end[self.src]] = -1
        # from the units' ends backwards: what is left at each state sums to exp(below)
        below = np.zeros(n + 1)
        by_size = np.argsort(-sizes, kind="stable")
        tails, lengths = stop[by_size], sizes[by_size]
        for r in range(1, int(lengths[0]) + 1 if len(lengths) else 0):
            p = tails[: int(np.searchsorted(-lengths, -r, "right"))] - r
            c = count[p]
            first = np.cumsum(c) - c
            e = np.repeat(self.begin[p] - first, c) + np.arange(int(c.sum()))
            x = score[e] + below[self.next[e]]  # next is -1 at an end, and below[-1] is 0
            most = np.maximum.reduceat(x, first)
            below[p] = most + np.log(np.add.reduceat(np.exp(x - np.repeat(most, c)), first))
            score[e] = x
        q = score - below[self.src]
        q[np.repeat(count == 1, count)] = 0.0
        self.logq = q
        del score, below
        total = np.concatenate([[0.0], np.cumsum(np.exp(q))])
        self.upper = self.src + np.minimum(total[1:] - total[self.begin[self.src]], 1.0 - 1e-9)
        self.upper[self.begin[1:] - 1] = np.arange(n) + 1.0

    def branches(self, state: int) -> np.ndarray:
        return np.arange(self.begin[state], self.begin[state + 1])

    def ids(self, path: np.ndarray) -> np.ndarray:
        """Piece numbers of a path; characters outside the vocabulary in byte pieces."""
        out = self.piece[path]
        raw = out < 0
        if raw.any():
            code = -out - 1
            out = np.where(raw & (code < 0x80), self.v.byte_ids[np.where(raw & (code < 0x80), code, 0)], out)
            wide = np.flatnonzero(raw & (code >= 0x80))
            if len(wide):
                written = [self.v.byte_ids[list(chr(c).encode("utf-8", "surrogatepass"))] for c in code[wide].tolist()]
                parts, at = [], 0
                for i, w in zip(wide.tolist(), written):
                    parts += [out[at:i], w]
                    at = i + 1
                out = np.concatenate([*parts, out[at:]])
        return out.astype(np.int32)


def _uniform(x: np.ndarray) -> np.ndarray:
    return ((x >> _U(11)).astype(np.float64) + 0.5) * 2.0**-53


def _hash(key: int, *parts: int) -> float:
    h = hashlib.blake2b(np.array([key, *parts], np.int64).tobytes(), digest_size=8).digest()
    return ((int.from_bytes(h, "little") >> 11) + 0.5) * 2.0**-53


def draw(lattice: Lattice, start: np.ndarray, seed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One segmentation of every unit: branches in order, and where each unit's begin (n + 1 numbers)."""
    upper = lattice.upper
    live, state, steps, edges = np.arange(len(start)), start, [], []
    counts = np.zeros(len(start), np.int64)
    step = 0
    while len(live):
        u = _uniform(mix(seed[live] + _U(step * 0x9E3779B97F4A7C15 & (1 << 64) - 1)))
        e = lattice.begin[state]
        x = state + u
        far = np.flatnonzero(upper[e] <= x)
        while len(far):
            e[far] += 1
            far = far[upper[e[far]] <= x[far]]
        steps.append(live)
        edges.append(e)
        counts[live] += 1
        state = lattice.next[e]
        go = state >= 0
        live, state, step = live[go], state[go], step + 1
    first = np.concatenate([[0], np.cumsum(counts)])
    out = np.zeros(first[-1], np.int64)
    for i, (units, e) in enumerate(zip(steps, edges)):
        out[first[units] + i] = e
    return out, first


def _below(mu: np.ndarray, bound: float, u: np.ndarray) -> np.ndarray:
    """The largest of a set's perturbed scores, given that it is below ``bound``: Gumbel around mu, cut off."""
    return mu - np.log(np.exp(np.minimum(mu - bound, 700)) - np.log(u))


class Search:
    """Best-first search of one text; draws are whole-text segmentations made beforehand, one a sample."""

    #: Noise around a set's log-mass can't exceed this with 53-bit uniforms.
    REACH = 37.5

    def __init__(self, lattice: Lattice, key: int, starts: np.ndarray, draws: list[tuple[np.ndarray, np.ndarray]]):
        self.lat, self.key, self.starts, self.draws = lattice, key, starts, draws
        self.open: list = []  # (bound, path, step, excluded branches)
        self.turn = 0

    def _noise(self) -> float:
        self.turn += 1
        return _hash(self.key, 2, self.turn)

    def _siblings(self, path: np.ndarray, begin: int, bound: float) -> None:
        """Adds the sets left beside ``path`` from step ``begin`` on."""
        size = min(len(path), begin + 256)
        while True:
            q = self.lat.logq[path[:size]]
            before = np.concatenate([[0.0], np.cumsum(q)])
            at = np.arange(begin, size)
            at = at[q[begin:] < 0]
            mu = before[at] + np.log1p(-np.exp(np.minimum(q[at], -1e-16)))
            # noise lies within -4 and REACH but for a chance of exp(-exp(4)) a draw: what can't reach the best is left out
            if size == len(path) or (len(at) and before[-1] + self.REACH <= mu.max() - 12.0):
                break
            size = min(len(path), 4 * size)
        if not len(at):
            return
        reach = mu + self.REACH > mu.max() - 12.0
        near, mu = at[reach], mu[reach]
        self.turn += 1
        u = _uniform(mix(np.arange(len(near), dtype=_U) + _U(int(_hash(self.key, 3, self.turn) * 2**63))))
        g = _below(mu, bound, u)
        for i in np.argsort(-g, kind="stable")[: len(self.draws) + 1]:  # no more can be taken or be the threshold
            self.open.append((float(g[i]), path, int(near[i]), [int(path[near[i]])]))

    def run(self) -> list[tuple[np.ndarray, float, float]]:
        """(path, log-probability, perturbed score) of each sample, then the threshold as a last bound."""
        lat, k = self.lat, len(self.draws)
        g = -np.log(-np.log(_hash(self.key, 1)))
        path = self.draws[0][0]
        out = [(path, float(lat.logq[path].sum()), g)]
        self._siblings(path, 0, g)
        while len(out) < k and self.open:
            self.open.sort(key=lambda x: -x[0])
            g, parent, step, out_of = self.open.pop(0)
            state = int(lat.src[parent[step]])
            options = lat.branches(state)
            options = options[~np.isin(options, out_of)] if len(out_of) > 1 else options[options != out_of[0]]
            p = np.exp(lat.logq[options])
            e = int(options[min(len(options) - 1, int(np.searchsorted(np.cumsum(p), self._noise() * p.sum(), "right")))])
            rest = options[options != e]
            if len(rest):
                mu = float(lat.logq[parent[:step]].sum() + np.log(np.exp(lat.logq[rest]).sum()))
                self.open.append((float(_below(np.array([mu]), g, np.array([self._noise()]))[0]), parent, step, [*out_of, e]))
            path = self._complete(parent, step, e, self.draws[len(out)])
            out.append((path, float(lat.logq[path].sum()), g))
            self._siblings(path, step + 1, g)
        self.threshold = max((o[0] for o in self.open), default=-np.inf)
        return out

    def _complete(self, parent: np.ndarray, step: int, branch: int, fresh: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        done = [branch]
        state = int(self.lat.next[branch])
        while state >= 0:
            options = self.lat.branches(state)
            p = np.cumsum(np.exp(self.lat.logq[options]))
            b = int(options[min(len(options) - 1, int(np.searchsorted(p, self._noise() * p[-1], "right")))])
            done.append(b)
            state = int(self.lat.next[b])
        # units completed so far: a unit ends where the next state is -1
        units = int((self.lat.next[parent[:step]] == -1).sum()) + 1
        edges, first = fresh
        return np.concatenate([parent[:step], np.array(done, np.int64), edges[first[units] :]])


def _sample(sent, k: int, ids_out: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = sent.value
        content = vocabulary.content
        for b in batches:
            for lo, hi in pieces(b.column(2), CHUNK):
                texts = b.column(2).slice(lo, hi - lo).to_pylist()
                keys = b.column(1).slice(lo, hi - lo).to_pylist()
                units = [_UNIT.findall(" " + t) if t else [] for t in texts]
                sizes = np.array([len(x) for x in units], np.int64)
                flat = [x for us in units for x in us]
                number = {x: i for i, x in enumerate(dict.fromkeys(flat))}
                which = np.fromiter(map(number.__getitem__, flat), np.int64, len(flat))
                lattice = Lattice(vocabulary, list(number))
                start = lattice.root[which]
                place = np.concatenate([[0], np.cumsum(sizes)])
                within = np.arange(place[-1]) - np.repeat(place[:-1], sizes)
                seeds = mix(np.repeat(np.array(keys, np.int64).view(_U), sizes)) + within.astype(_U)
                drawn = [draw(lattice, start, mix(seeds ^ mix(np.array([i + 1], _U)))) for i in range(k)]
                rows: list[list] = [[] for _ in range(7)]
                for d, text in enumerate(texts):
                    u0, u1 = int(place[d]), int(place[d + 1])
                    if u0 == u1:
                        found, threshold = [(np.zeros(0, np.int64), 0.0, 0.0)], -np.inf
                    else:
                        own = [(e[f[u0] : f[u1]], f[u0 : u1 + 1] - f[u0]) for e, f in drawn]
                        search = Search(lattice, keys[d], start[u0:u1], own)
                        found = search.run()
                        threshold = search.threshold
                    for i, (path, logp, g) in enumerate(found):
                        ids = lattice.ids(path)
                        plain = b"".join([content[x] for x in ids.tolist()])
                        whole = plain[1:] == (text or "").encode("utf-8", "surrogatepass")
                        inclusion = 1.0 if threshold == -np.inf else float(-np.expm1(-np.exp(min(logp - threshold, 700.0))))
                        for c, x in zip(rows, (lo + d, i, len(ids), logp, inclusion, whole, ids if ids_out else hashlib.sha256(ids.astype("<i4").tobytes()).hexdigest())):
                            c.append(x)
                last = pa.array(rows[6], pa.list_(pa.int32())) if ids_out else pa.array(rows[6], pa.string())
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(rows[0], pa.int64())), pa.array(rows[1], pa.int32()), pa.array(rows[2], pa.int32()), pa.array(rows[3], pa.float64()), pa.array(rows[4], pa.float64()), pa.array(rows[5], pa.bool_()), last], ["doc_id", "sample", "n_pieces", "log_prob", "inclusion", "decodes", "ids"])

    return run


def encode(docs: DataFrame, model: str = MODEL, k: int = SAMPLES, power: float = 1.0, ids: bool = True, seed: int = 0) -> DataFrame:
    """Up to k sampled segmentations of each document.

    doc_id, sample, n_pieces, log_prob, inclusion, decodes (whether the pieces give the text back) and ``ids``
    (piece numbers; their sha256 as little-endian 32-bit numbers with ``ids=False``).  The vocabulary file is
    read on the driver only.
    """
    small_batches(docs.sparkSession)
    vocabulary = Vocabulary.load(model, power=power)
    vocabulary.pieces = {}  # the tasks need the trie only
    sent = docs.sparkSession.sparkContext.broadcast(vocabulary)
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", F.xxhash64(F.lit(seed), F.col("doc_id")).alias("key"), "text")
    return rows.mapInArrow(_sample(sent, k, ids), f"doc_id {kind}, sample int, n_pieces int, log_prob double, inclusion double, decodes boolean, ids {'array<int>' if ids else 'string'}")


def decode(encoded: DataFrame, model: str = MODEL) -> DataFrame:
    """``encoded`` with the text of its ids as ``text``."""
    sent = encoded.sparkSession.sparkContext.broadcast(Vocabulary.load(model).content)

    @F.pandas_udf("string")
    def text(ids):  # noqa: ANN001, ANN202
        content = sent.value
        return ids.map(lambda x: b"".join([content[i] for i in x])[1:].decode("utf-8", "surrogatepass"))

    return encoded.withColumn("text", text("ids"))
