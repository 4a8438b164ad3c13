"""Toxicity scores by weak supervision.

1. Voters.  Terms (lower-cased words, and openings of ``STEMS`` letters, once or repeated, as patterns) that stand in labelled toxic
   texts far more than in others become lexicon and pattern voters: each votes "toxic" where it occurs and
   abstains elsewhere.  Further voters look at the shape of a text (shouting, exclamation marks, repeated letters,
   no voter at all) and vote either way.
2. Label model.  A generative model of the votes, with one accuracy per voter and class, is fitted by expectation
   maximisation from the labelled counts; rows without label join in.  Voters whose votes stay correlated beyond
   what the classes explain form groups, and a group's vote is shared among its members, so that near-copies of
   one cue (a word and its opening) count once.
3. Classifier.  A logistic regression over the voters and the commonest other terms is trained on the posterior
   labels; a score is its probability.

Everything learned comes from rows for learning, at most about ``MAX_LABELLED`` labelled and ``MAX_UNLABELLED``
other ones, chosen by a hash of doc_id; every document is scored whole.  Labels, lang, source and doc_id are never
inputs of a score.  Defined results: null and empty texts get the score of a text without any term; a repeated
row is scored alike; without any labelled toxic row every score is the share of toxic labels (0).
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import small_batches
from conflate.plans.tables import materialise

MAX_LABELLED = 16_000
MAX_UNLABELLED = 6_000
STEMS = (4, 5)
TIMES = (2, 3)
#: Repeated openings count where one stands in so many words at least.
WORDS_EACH = 300
VOTERS = 400
TERMS = 300
MIN_DOCS = 4
#: Pull of the weights to 0, of voters and of the other terms.
VOTER_L2, OTHER_L2 = 0.5, 20.0
#: Log-odds that a label adds to what the votes say.
HINT = 8.0
CUT = 0.3
_WORD = re.compile(r"[^\W\d_]+")
_DRAWN = re.compile(r"(.)\1\1")


def terms(text: str | None) -> set[str]:
    """Words; openings ("abcd*"); openings of two or three words and more, where they stand thick enough ("abcd*2")."""
    words = Counter(_WORD.findall((text or "").lower()))
    total, out = sum(words.values()), set(words)
    for size in STEMS:
        stems: Counter = Counter()
        for w, c in words.items():
            if len(w) > size:
                stems[w[:size]] += c
        for stem, c in stems.items():
            out.add(stem + "*")
            out.update(f"{stem}*{n}" for n in TIMES if c >= n and c * WORDS_EACH >= total)
    return out


def shapes(text: str | None, voted: bool) -> list[int]:
    """Votes of the shape voters: 1 toxic, 0 not toxic, -1 abstains."""
    t = text or ""
    low = t.lower()
    shouted = sum(map(str.isupper, t)) if t != low else 0
    loud = shouted > 20 and 2 * shouted > sum(map(str.isalpha, t))
    return [1 if loud else -1, 1 if t.count("!") > 2 + len(t) // 400 else -1, 1 if _DRAWN.search(t) else -1, -1 if voted else 0]


N_SHAPES = 4


@dataclass
class Scorer:
    weights: dict[str, float] = field(default_factory=dict)
    shape_weights: list[float] = field(default_factory=lambda: [0.0] * (2 * N_SHAPES))
    voters: frozenset = frozenset()
    bias: float = -20.0

    def score(self, text: str | None) -> float:
        z, voted = self.bias, False
        for t in terms(text):
            w = self.weights.get(t)
            if w is not None:
                z += w
                voted = voted or t in self.voters
        for i, v in enumerate(shapes(text, voted)):
            if v >= 0:
                z += self.shape_weights[2 * i + v]
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def _chosen(rows: DataFrame, bound: int, seed: int) -> DataFrame:
    n = rows.count()
    if n <= bound:
        return rows
    return rows.where(F.pmod(F.xxhash64(F.lit(seed), F.col("doc_id")), F.lit(1_000_003)) < int(1_000_003 * bound / n))


def _tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(term, documents with label 1, documents with label 0) of each batch."""
    for b in batches:
        by = {1: Counter(), 0: Counter()}
        for y, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            by[y].update(terms(text))
        names = list(by[1] | by[0])
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), *(pa.array([by[y][t] for t in names], pa.int64()) for y in (1, 0))], ["term", "n1", "n0"])


def _features(sent):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = sent.value
        for b in batches:
            texts = b.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([sorted(index[t] for t in terms(x) if t in index) for x in texts], pa.list_(pa.int32())), pa.array([shapes(x, False)[:3] for x in texts], pa.list_(pa.int32()))], ["toxic", "terms", "shapes"])

    return run


def label_model(votes: np.ndarray, known: np.ndarray, rounds: int = 40) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """votes: rows x voters of 1, 0 and -1 (abstains); known: 1, 0 or -1 for rows without label.

    Returns the posterior of class 1, P(vote = 1 | class), P(vote = 0 | class) and the voters' shares.
    Rows with a label start as it says and may move, as labels are only strong hints here.
    """
    n, m = votes.shape
    one, zero = votes == 1, votes == 0
    hint = np.where(known == 1, HINT, np.where(known == 0, -HINT, 0.0))
    labelled = known >= 0
    prior = max(1e-4, float((known == 1).sum() / max(1, labelled.sum())))
    post = np.where(known == 1, 0.99, np.where(known == 0, 0.01, prior))
    share = np.ones(m)
    for turn in range(rounds):
        weight = np.stack([1 - post, post], 1)
        mass = weight.sum(0) + 2.0
        p1, p0 = (one.T.astype(float) @ weight + 0.05) / mass, (zero.T.astype(float) @ weight + 0.05) / mass
        if turn == 2:
            share = 1 / _dependence(one, zero, p1, post)
        rest = np.maximum(1 - p1 - p0, 1e-6)
        odds = [np.log(np.maximum(p[:, 1], 1e-9)) - np.log(np.maximum(p[:, 0], 1e-9)) for p in (p1, p0, rest)]
        z = one @ (share * (odds[0] - odds[2])) + zero @ (share * (odds[1] - odds[2])) + (share * odds[2]).sum() + np.log(prior / (1 - prior)) + hint
        new = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        moved = float(np.abs(new - post).max())
        post = new
        if turn > 3 and moved < 1e-4:
            break
    return post, p1, p0, share


def _dependence(one: np.ndarray, zero: np.ndarray, p1: np.ndarray, post: np.ndarray) -> np.ndarray:
    """How many voters each voter stands for: 1 + the residual slopes of the others on it, where they are strong."""
    r = one - (p1[:, 0][None, :] * (1 - post)[:, None] + p1[:, 1][None, :] * post[:, None])
    c = r.T @ r
    slope = c / np.maximum(np.diag(c), 1e-9)[:, None]
    np.fill_diagonal(slope, 0)
    return 1 + np.minimum(np.where(slope > 0.3, slope, 0), 1).sum(1)


def logistic(rows: np.ndarray, cols: np.ndarray, n: int, m: int, target: np.ndarray, l2: np.ndarray, steps: int = 300) -> np.ndarray:
    """Weights (m, then the bias) of a logistic regression on 0/1 features given as (row, column) entries."""
    def value(x: np.ndarray) -> tuple[float, np.ndarray]:
        z = x[m] + np.bincount(rows, x[cols], minlength=n)
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        loss = float((np.logaddexp(0, z) - target * z).sum() + 0.5 * (l2 * x[:m] ** 2).sum())
        d = p - target
        return loss, np.append(np.bincount(cols, d[rows], minlength=m) + l2 * x[:m], d.sum())

    x = np.append(np.zeros(m), float(np.log((target.mean() + 1e-6) / (1 - target.mean() + 1e-6))))
    f, g = value(x)
    past: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(steps):  # limited-memory quasi-Newton steps with backtracking
        d, saved = g.copy(), []
        for s, y in reversed(past):
            a = s @ d / (s @ y)
            saved.append(a)
            d -= a * y
        d *= (past[-1][0] @ past[-1][1]) / (past[-1][1] @ past[-1][1]) if past else 1 / max(1.0, float(np.abs(g).sum()))
        for (s, y), a in zip(past, reversed(saved)):
            d += (a - y @ d / (s @ y)) * s
        step = 1.0
        while True:
            f2, g2 = value(x - step * d)
            if f2 <= f - 1e-4 * step * float(g @ d) or step < 1e-8:
                break
            step /= 2
        s, y = -step * d, g2 - g
        if s @ y > 1e-12:
            past = [*past[-9:], (s, y)]
        done = f - f2 < 1e-7 * max(1.0, abs(f))
        x, f, g = x + s, f2, g2
        if done:
            break
    return x


def learn(docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED, max_unlabelled: int = MAX_UNLABELLED) -> Scorer:
    """A scorer from the rows of ``docs`` (doc_id, text), all of them for learning, and their labels."""
    small_batches(docs.sparkSession)
    marked = labels.where("toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    with_label = _chosen(docs.select("doc_id").join(marked, "doc_id"), max_labelled, 11).select("doc_id", "toxic")
    without = _chosen(docs.select("doc_id").join(marked, "doc_id", "left_anti"), max_unlabelled, 12).select("doc_id", F.lit(-1).alias("toxic"))
    picked = with_label.unionByName(without)
    sample = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select(F.col("toxic").cast("int").alias("toxic"), "text")
    sizes = {r[0]: r[1] for r in picked.groupBy("toxic").count().collect()}
    n1, n0 = sizes.get(1, 0), sizes.get(0, 0)
    if not n1:
        return Scorer()
    tally = sample.where("toxic >= 0").mapInArrow(_tally, "term string, n1 long, n0 long").groupBy("term").agg(F.sum("n1").alias("n1"), F.sum("n0").alias("n0")).where(F.col("n1") + F.col("n0") >= MIN_DOCS)
    tally = materialise(tally, "tally")
    # likelihood ratio of "occurs more in toxic texts" for each term, held against the number of terms tried
    bar = 2 * np.log(max(2, tally.count())) + 4
    c, d, expected = F.col("n1"), F.col("n0"), (F.col("n1") + F.col("n0")) * (n1 / (n1 + n0))
    other = F.when(d > 0, d * F.log(d / (c + d - expected))).otherwise(0.0)
    lean = F.when(c > expected, 2 * (c * F.log(c / expected) + other)).otherwise(0.0)
    cast = [r[0] for r in tally.select("term", lean.alias("g")).where(F.col("g") > float(bar)).orderBy(F.desc("g"), "term").limit(VOTERS).collect()]
    others = [r[0] for r in tally.where(~F.col("term").isin(cast)).orderBy(F.desc(c + d), "term").limit(TERMS).select("term").collect()]
    index = {t: i for i, t in enumerate([*cast, *others])}
    sent = docs.sparkSession.sparkContext.broadcast(index)
    got = sample.mapInArrow(_features(sent), "toxic int, terms array<int>, shapes array<int>").toArrow()
    known = got.column("toxic").to_numpy()
    bags, shaped = got.column("terms").to_pylist(), got.column("shapes").to_pylist()
    # rows arrive in any order; a fixed one makes sums, and so scores, the same in every run
    order = sorted(range(len(bags)), key=lambda i: (int(known[i]), bags[i], shaped[i]))
    known, bags, shaped = known[order], [bags[i] for i in order], [shaped[i] for i in order]
    n, v = len(bags), len(cast)
    rows = np.repeat(np.arange(n), [len(x) for x in bags])
    cols = [i for bag in bags for i in bag]
    rows, cols = np.array(rows, np.int64), np.array(cols, np.int64)
    votes = np.full((n, v + N_SHAPES), -1, np.int8)
    votes[rows[cols < v], cols[cols < v]] = 1
    votes[:, v : v + 3] = np.array(shaped, np.int8).reshape(n, 3)
    votes[:, v + 3] = np.where((votes[:, :v] == 1).any(1), -1, 0)
    post, *_ = label_model(votes, known)
    base = len(index)
    r2, c2 = np.nonzero(votes[:, v:] >= 0)
    shape_cols = base + 2 * c2 + votes[:, v:][r2, c2]
    w = logistic(np.concatenate([rows, r2]), np.concatenate([cols, shape_cols]), n, base + 2 * N_SHAPES, post, np.where((np.arange(base + 2 * N_SHAPES) >= v) & (np.arange(base + 2 * N_SHAPES) < base), OTHER_L2, VOTER_L2))
    return Scorer({t: float(w[i]) for t, i in index.items() if abs(w[i]) > 1e-3 or i < v}, [float(x) for x in w[base : base + 2 * N_SHAPES]], frozenset(cast), float(w[-1]))


def score(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """doc_id and score of every row."""
    small_batches(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(scorer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = sent.value
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([s.score(t) for t in b.column(1).to_pylist()], pa.float64())], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, score double")
