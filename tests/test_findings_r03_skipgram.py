"""skipgram_terms: the vocabulary is Spark's own, training is one scan, and words of like contexts come out alike."""

import random

import numpy as np
from pyspark.sql import functions as F

from conflate.operators import skipgram, taxonomy


def test_terms_are_those_of_spark_expressions(spark):
    odd = [None, "", "Über ÉCOLE naïve ² Ⅷ x_y 漢字漢字漢 𐐀𐐁𐐂𐐃𐐄𐐅 İstanbul ΟΔΟΣ école", "plain words, plain wordy words 12 a1b"]
    docs = spark.createDataFrame([(t,) for t in odd * 5], "text string")
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: w != "")
    tokens = docs.select(F.explode(F.flatten(F.transform(words, lambda w: F.when(F.char_length(w) > 4, F.array(w, F.concat(F.substring(w, 1, 4), F.lit("*")))).otherwise(F.array(w))))).alias("t"))
    want = {r.t for r in tokens.groupBy("t").count().where("count >= 5").collect()}
    assert {r.term for r in taxonomy.skipgram_vectors(docs).collect()} == want and "word*" in want
    assert taxonomy.skipgram_vectors(docs.where("text = ''")).count() == 0


def test_like_contexts_give_like_vectors_in_one_scan_of_training(spark):
    rng = random.Random(5)
    group = [[f"{g}{x}" for x in "abcdefgh"] for g in ("k", "m")]
    rows = [(" ".join(rng.choices(group[i % 2], k=40)),) for i in range(3000)]
    docs = spark.createDataFrame(rows, "text string").coalesce(2)
    made = taxonomy.skipgram_vectors(docs, dim=8)
    # before, the fit dealt all tokens anew by a shuffle and walked a tree for every pair
    assert "MapInArrow" in made._jdf.queryExecution().toString()
    v = {r.term: np.array(r.vec) / np.linalg.norm(r.vec) for r in made.collect()}
    near = np.mean([v[a] @ v[b] for g in group for a in g for b in g if a != b])
    apart = np.mean([v[a] @ v[b] for a in group[0] for b in group[1]])
    assert len(v) == 16 and near > apart + 0.5


def test_sums_of_repeated_ids():
    at, g = skipgram._summed(np.array([3, 1, 3]), np.array([[1.0], [2.0], [5.0]]))
    assert at.tolist() == [1, 3] and g.ravel().tolist() == [2.0, 6.0]
