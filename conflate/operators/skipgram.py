"""Skip-gram vectors with negative sampling: a count of the tokens and a pass of training, in one scan each.

Every task trains on its documents from the same start; a term's vector is the mean of the tasks', weighted by its
occurrences there.  The vocabulary goes to every task, as it must: the model has two vectors of each term.  In a batch
of tokens the gradients of a term are added up and stepped by AdaGrad.  A context at distance d counts with the share
of windows, drawn evenly from 1 to ``WINDOW``, that reach it.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from conflate.plans.tables import discard, materialise

WINDOW, NEGATIVES, SHARED = 5, 5, 32
#: Tokens of a sentence, and of a batch at least.
SENTENCE, BATCH = 1_000, 2_000
STEP = 0.1
#: Terms that a task counts before it hands them on.
HELD = 300_000
#: Tasks at least, and tokens of a task beyond.
TASKS, PER_TASK = 12, 32_000_000


def letters(spark: SparkSession) -> str:
    """A class of regular expressions of all lower-cased letters, as Spark's own expressions see them."""
    code = spark.range(0x80, 0x110000, 1, 8).where("id < 55296 or id > 57343").withColumn("c", F.expr("decode(unhex(lpad(hex(id), 8, '0')), 'UTF-32')"))
    other = sorted(r.id for r in code.where(F.col("c").rlike(r"^\p{L}$")).select("id").collect())
    ends = [[0x61, 0x7A]]
    for x in other:
        if ends[-1][1] == x - 1:
            ends[-1][1] = x
        else:
            ends.append([x, x])
    return "[" + "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in ends) + "]+"


def _words(pattern: str) -> Callable[[str], list[str]]:
    plain, every, far = re.compile("[a-z]+").findall, re.compile(pattern).findall, re.compile("[\U00010000-\U0010ffff]").search
    # letters beyond 16 bits are tried range by range, at every blank too; few texts have any
    near = re.compile(re.sub(r"\\U000[1-9a-f][0-9a-f]{4}-\\U000[1-9a-f][0-9a-f]{4}", "", pattern)).findall
    return lambda text: plain(text) if text.isascii() else every(text) if far(text) else near(text)


def opening(word: str) -> str:
    """The extra token of a word of more than four letters."""
    return word[:4] + "*"


def counts(lowered: DataFrame, pattern: str) -> DataFrame:
    """(term, n) of the words and their openings."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, seen = _words(pattern), Counter()

        def flush() -> pa.RecordBatch:
            short = Counter()
            for w, n in seen.items():
                if len(w) > 4:
                    short[opening(w)] += n
            out = pa.RecordBatch.from_pydict({"term": [*seen, *short], "n": pa.array([*seen.values(), *short.values()], pa.int64())})
            seen.clear()
            return out

        for batch in batches:
            for text in batch.column(0):
                if text.is_valid:
                    seen.update(words(text.as_py()))
                if len(seen) > HELD:
                    yield flush()
        yield flush()

    return lowered.mapInArrow(count, "term string, n long").groupBy("term").agg(F.sum("n").alias("n"))


def _summed(ids: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct ids and the sums of their rows."""
    order = np.argsort(ids, kind="stable")
    sorted_ids = ids[order]
    starts = np.flatnonzero(np.r_[True, sorted_ids[1:] != sorted_ids[:-1]])
    return sorted_ids[starts], np.add.reduceat(g[order], starts, axis=0)


class Trainer:
    """Both vectors of every term, and the sums of squares that AdaGrad divides by."""

    def __init__(self, n: np.ndarray, dim: int, seed: int) -> None:
        rng = np.random.default_rng(seed)
        self.rng = rng
        self.near = ((rng.random((len(n), dim), dtype=np.float32) - 0.5) / dim).astype(np.float32)
        self.far = np.zeros((len(n), dim), np.float32)
        self.sums = np.full((2, len(n)), 1e-6, np.float32)
        self.seen = np.zeros(len(n), np.int64)
        self.drawn = np.cumsum(n**0.75)

    def _step(self, which: int, ids: np.ndarray, g: np.ndarray) -> None:
        at, g = _summed(ids, g)
        self.sums[which, at] += np.einsum("ij,ij->i", g, g) / g.shape[1]
        (self.near, self.far)[which][at] += STEP * g / np.sqrt(self.sums[which, at])[:, None]

    def learn(self, ids: np.ndarray, sentence: np.ndarray) -> None:
        """One step on a batch: terms in order and the sentence of each."""
        np.add.at(self.seen, ids, 1)
        w, c = self.near[ids], self.far[ids]
        gw, gc, pairs = np.zeros_like(w), np.zeros_like(c), np.zeros(len(ids), np.float32)
        for d in range(1, min(WINDOW, len(ids) - 1) + 1):
            share = (sentence[d:] == sentence[:-d]) * np.float32((WINDOW + 1 - d) / WINDOW)
            one, other = slice(None, -d), slice(d, None)
            held = np.empty_like(w[d:])
            for a, b in ((one, other), (other, one)):
                g = np.einsum("ij,ij->i", w[a], c[b])
                np.exp(g, out=g)
                g += 1
                np.divide(share, g, out=g)
                gw[a] += np.multiply(g[:, None], c[b], out=held)
                gc[b] += np.multiply(g[:, None], w[a], out=held)
                pairs[a] += share
        drawn = np.searchsorted(self.drawn, self.rng.random(SHARED) * self.drawn[-1])
        against = self.far[drawn]
        g = -(pairs * np.float32(NEGATIVES / SHARED))[:, None] / (1 + np.exp(-(w @ against.T)))
        gw += g @ against
        self._step(0, ids, gw)
        self._step(1, np.r_[ids, drawn], np.r_[gc, g.T @ w])


def _trained(pattern: str, held: object, dim: int, seed: int) -> Callable:
    def train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, (joined, n) = _words(pattern), held.value
        terms = joined.split("\n")
        number = {t: i for i, t in enumerate(terms)}
        of, model = number.get, Trainer(n, dim, seed)
        short = np.array([of(opening(t), -1) if len(t) > 4 and t[-1] != "*" else -1 for t in terms], np.int64)
        ids, sentence, size, k = [], [], 0, 0

        def learn() -> None:
            model.learn(np.concatenate(ids), np.concatenate(sentence))
            ids.clear()
            sentence.clear()

        for batch in batches:
            for text in batch.column(0):
                if not text.is_valid or not (found := words(text.as_py())):
                    continue
                # a word and its opening, and of those the ones of the vocabulary
                both = np.empty((len(found), 2), np.int64)
                both[:, 0] = [of(w, -1) for w in found]
                both[:, 1] = short[both[:, 0]]
                for i in np.flatnonzero(both[:, 0] < 0):
                    both[i, 1] = of(opening(found[i]), -1) if len(found[i]) > 4 else -1
                known = both.ravel()
                known = known[known >= 0]
                # a very long document is several batches
                for at in range(0, len(known), BATCH):
                    part = known[at : at + BATCH]
                    ids.append(part)
                    sentence.append(k + np.arange(len(part)) // SENTENCE)
                    size, k = size + len(part), k + len(part) // SENTENCE + 1
                    if size >= BATCH:
                        learn()
                        size = 0
        if ids:
            learn()
        met = np.flatnonzero(model.seen)
        for at in range(0, len(met), 50_000):
            part = met[at : at + 50_000]
            columns = {"term": [terms[i] for i in part], "seen": model.seen[part].astype(np.float64)}
            yield pa.RecordBatch.from_pydict(columns | {f"v{j}": np.ascontiguousarray(model.near[part, j]) for j in range(dim)})

    return train


def vectors(docs: DataFrame, text: str, dim: int, min_count: int, seed: int) -> DataFrame:
    """(term, vec) of every term of ``min_count`` occurrences or more."""
    spark = docs.sparkSession
    lowered, pattern = docs.select(F.lower(text).alias("text")), letters(spark)
    vocabulary = materialise(counts(lowered, pattern).where(F.col("n") >= min_count), "vocabulary")
    rows = vocabulary.orderBy(F.desc("n"), "term").toArrow()
    discard(vocabulary)
    n = rows["n"].to_numpy().astype(np.float64)
    if not len(n):
        return spark.createDataFrame([], "term string, vec array<double>")
    held = spark.sparkContext.broadcast(("\n".join(rows["term"].to_pylist()), n))
    kind = "term string, seen double, " + ", ".join(f"v{j} float" for j in range(dim))
    models = lowered.coalesce(max(TASKS, int(n.sum()) // PER_TASK)).mapInArrow(_trained(pattern, held, dim, seed), kind)
    mean = models.groupBy("term").agg(*[(F.sum(F.col(f"v{j}") * F.col("seen")) / F.sum("seen")).alias(f"v{j}") for j in range(dim)])
    return mean.select("term", F.array(*[f"v{j}" for j in range(dim)]).alias("vec"))
