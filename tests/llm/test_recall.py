"""Recall of the fuzzy lines and the benchmark windows against brute force."""

import random

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from conflate.llm import decontam, fuzzylines
from conflate.plans.graph import components


def similar_lines(lines, least):
    """All pairs of lines of that edit similarity; letter counts rule out most before the distance is worked out."""
    lines = sorted(lines, key=len)
    size = np.array([len(x) for x in lines])
    counts = np.zeros((len(lines), 64), np.int32)
    for i, x in enumerate(lines):
        np.add.at(counts[i], np.frombuffer(x.encode("utf-32-le"), np.uint32) % 64, 1)
    pairs = []
    for a in range(len(lines)):
        hi = np.searchsorted(size, size[a] / least + 1e-9, "right")
        d = counts[a + 1 : hi] - counts[a]
        bound = np.maximum(np.maximum(d, 0).sum(1), np.maximum(-d, 0).sum(1))
        pairs += [(a, a + 1 + int(k)) for k in np.flatnonzero(bound <= (1 - least) * size[a + 1 : hi] + 1e-9)]
    pair, line = pd.DataFrame(pairs, columns=["a", "b"]), pd.DataFrame({"i": range(len(lines)), "t": lines})
    db = duckdb.connect()
    db.register("pair", pair)
    db.register("line", line)
    return db.execute(f"SELECT x.t, y.t FROM pair JOIN line x ON x.i = a JOIN line y ON y.i = b WHERE 1 - levenshtein(x.t, y.t) / greatest(length(x.t), length(y.t)) >= {least}").fetchall()


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_fuzzy_lines_recall(spark, sf):
    docs = spark.read.parquet(f"/root/testdata/{sf}/documents.parquet")
    lines = fuzzylines.raw_lines(docs).select(fuzzylines.normalised(F.col("line")).alias("t")).where("t <> '' and length(t) <= 3000").distinct()
    true = similar_lines([r.t for r in lines.collect()], fuzzylines.SIMILAR)
    ids = {r.t: r.id for r in lines.select("t", F.xxhash64("t").alias("id")).collect()}
    root = {r.v: r.root for r in components(fuzzylines.links(docs)[1]).collect()}
    found = sum(root.get(ids[a], ids[a]) == root.get(ids[b], ids[b]) for a, b in true)
    assert len(true) >= 40 and found >= 0.9 * len(true), (found, len(true))


def test_windows_within_reach_are_found(spark):
    """Items edited down to 0.8 of their shingles are found wherever they stand."""
    r = random.Random(5)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(6))
    items, docs, due = [], [], 0
    for i in range(60):
        w = [word() for _ in range(r.randint(15, 60))]
        items.append((i, " ".join(w)))
        cut = w[: max(5, round((len(w) - 4) * 0.92) + 4)]
        docs.append((i, " ".join([word() for _ in range(40)] + cut + [word() for _ in range(40)])))
        n, m = len(w) - 4, len(cut) - 4
        due += m / (2 * n - m) >= 0.8
    got = decontam.matches(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    hit = {(x.doc_id, x.item_id) for x in got.collect()}
    assert all(a == b for a, b in hit) and len(hit) >= 0.97 * due and due >= 40
