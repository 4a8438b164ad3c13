"""Language identification by rank-order profiles.

A profile lists a language's most frequent character n-grams (1 to 4 letters, word edges included) in order
of frequency.  A text is compared with each profile by the out-of-place distance: how far each of the text's
most frequent n-grams stands from its place in the profile, at most the profile's length when it is absent.

Defined results: a null text, an empty one and one without a letter get ``und`` with score 0; ties go to the
language that comes first in alphabetic order; without any learnable row every text is ``und``.  Repeated rows
are judged alike and one by one.  Text is read whole, whatever its length.

Learning is the one bounded step: about ``MAX_ROWS_PER_LANGUAGE`` rows of each language (all, where there are
fewer), chosen by a hash of doc_id.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from conflate.llm.common import bounded_sample, small_batches
from conflate.llm.textkit import pieces

MAX_ROWS_PER_LANGUAGE = 4_000
PROFILE = 1_200
TOP = 400
LONGEST = 4
UND = "und"
#: Most languages a profile table may hold; it is sent to every task.
MAX_LANGUAGES = 2_000

_fold: np.ndarray | None = None


def _letters() -> np.ndarray:
    """Code point of the Basic Multilingual Plane -> its lower-case letter, or 0 for what is no letter."""
    global _fold
    if _fold is None:
        _fold = np.array([ord(chr(i).lower()[0]) if chr(i).isalpha() else 0 for i in range(0x10000)], np.uint64)
    return _fold


def ngrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-grams of a text as 64-bit keys (16 bits a letter, 1 for a word edge) and their counts."""
    cp = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    low = _letters()[np.minimum(cp, 0xFFFF)]
    if cp.size and cp.max() > 0xFFFF:
        high = np.flatnonzero(cp > 0xFFFF)
        low[high] = [(ord(text[i].lower()[0]) & 0xFFFF) | 2 if text[i].isalpha() else 0 for i in high]
    s = np.ones(len(low) + 2, np.uint64)
    s[1:-1] = np.where(low == 0, 1, low)
    keep = np.ones(len(s), bool)
    keep[1:] = (s[1:] != 1) | (s[:-1] != 1)
    s = s[keep]
    edge = s == 1
    parts, key, inner = [s[~edge]], s, None
    for n in range(2, LONGEST + 1):
        if len(s) < n:
            break
        key = key[:-1] | (s[n - 1 :] << np.uint64(16 * (n - 1)))
        inner = np.zeros(len(s) - 1, bool) if n == 2 else inner[:-1] | edge[n - 2 : -1]
        parts.append(key[~inner])
    k = np.concatenate(parts)
    k.sort()
    if not len(k):
        return k, np.zeros(0, np.int64)
    at = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    return k[at], np.diff(np.append(at, len(k)))


@dataclass
class Profiles:
    """keys: sorted n-grams of any profile; places[i, j]: place of n-gram i in language j (PROFILE if absent)."""

    languages: list[str]
    keys: np.ndarray
    places: np.ndarray

    def judge(self, text: str | None) -> tuple[str, float]:
        k, c = ngrams(text or "")
        if not len(k) or not self.languages:
            return UND, 0.0
        top = np.argsort(-c, kind="stable")[:TOP]
        k = k[top]
        at = np.minimum(np.searchsorted(self.keys, k), len(self.keys) - 1)
        known = self.keys[at] == k
        place = np.where(known[:, None], self.places[at], PROFILE)
        # places of a short list are spread over the profile's scale only as far as the list goes
        away = np.where(place < PROFILE, np.abs(place - np.arange(len(k))[:, None]), PROFILE).sum(0)
        best = int(away.argmin())
        return self.languages[best], float(1 - away[best] / (PROFILE * len(k)))


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        by: dict[str, list] = {}
        for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            by.setdefault(lang, []).append(ngrams(text or ""))
        for lang, got in by.items():
            k, inverse = np.unique(np.concatenate([g[0] for g in got]), return_inverse=True)
            n = np.bincount(inverse, np.concatenate([g[1] for g in got]), minlength=len(k)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(k), pa.string()), pa.array(k.view(np.int64)), pa.array(n)], ["lang", "gram", "n"])


def learn(rows: DataFrame, per_language: int = MAX_ROWS_PER_LANGUAGE) -> Profiles:
    """Profiles from (doc_id, text, lang) rows with a language."""
    small_batches(rows.sparkSession)
    known = rows.where("lang is not null and text is not null").select("doc_id", "lang", "text")
    sample = bounded_sample(known, "doc_id", "lang", per_language)
    counts = sample.select("lang", "text").mapInArrow(_count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    w = Window.partitionBy("lang").orderBy(F.desc("n"), "gram")
    top = counts.withColumn("place", F.row_number().over(w) - 1).where(F.col("place") < PROFILE).select("lang", "gram", "place")
    got = top.toArrow()
    langs = sorted(set(got.column("lang").to_pylist()))
    if len(langs) > MAX_LANGUAGES:
        raise ValueError(f"{len(langs)} languages: the profiles are too large to send to every task")
    g = got.column("gram").to_numpy().view(np.uint64)
    keys = np.unique(g)
    places = np.full((len(keys), len(langs)), PROFILE, np.int64)
    index = {x: i for i, x in enumerate(langs)}
    places[np.searchsorted(keys, g), [index[x] for x in got.column("lang").to_pylist()]] = got.column("place").to_numpy()
    return Profiles(langs, keys, places)


def predict(docs: DataFrame, profiles: Profiles, keep: list[str] | None = None) -> DataFrame:
    """The ``keep`` columns (default: doc_id) with lang_pred and score; only ``text`` is looked at."""
    small_batches(docs.sparkSession)
    keep = keep or ["doc_id"]
    sent = docs.sparkSession.sparkContext.broadcast(profiles)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = sent.value
        for b in batches:
            texts = b.column(b.num_columns - 1)
            got = [p.judge(t) for lo, hi in pieces(texts) for t in texts.slice(lo, hi - lo).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([x[0] for x in got], pa.string()), pa.array([x[1] for x in got], pa.float64())], [*b.schema.names[:-1], "lang_pred", "score"])

    kept = [F.col(c) for c in keep]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*kept).schema)
    return docs.select(*kept, F.col("text").alias("__text")).mapInArrow(run, f"{schema}, lang_pred string, score double")


def accepted(lang_pred: Column) -> Column:
    """What the filter keeps: texts with a language."""
    return lang_pred != UND
