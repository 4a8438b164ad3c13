"""Accuracy, coverage, overlap and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ATTRIBUTES = ("coordinates", "address", "name", "place_type", "tags")


def confusion(df: DataFrame) -> DataFrame:
    """One row: tp, tn, fp, fn from label and prediction."""
    c = lambda y, p: F.count_if((F.col("label") == y) & (F.col("prediction") == p))
    return df.agg(c(1, 1).alias("tp"), c(0, 0).alias("tn"), c(0, 1).alias("fp"), c(1, 0).alias("fn"))


def accuracy(df: DataFrame) -> DataFrame:
    """Confusion counts with overall accuracy, balanced accuracy (mean share decided right over the true classes),
    its literal one-vs-rest reading (equal to overall for two classes), precision, recall and f1 (null where
    undefined), and the gap between overall and balanced."""
    tp, tn, fp, fn = (F.col(x) for x in ("tp", "tn", "fp", "fn"))
    n = tp + tn + fp + fn
    recall, precision, specificity = F.try_divide(tp, tp + fn), F.try_divide(tp, tp + fp), F.try_divide(tn, tn + fp)
    r = lambda c, name: F.round(c, 6).alias(name)
    return confusion(df).select("tp", "tn", "fp", "fn", r(F.try_divide(tp + tn, n), "overall"), r((recall + specificity) / 2, "balanced"), r((F.try_divide(tp + tn, n) + F.try_divide(tn + tp, n)) / 2, "balanced_literal"), r(precision, "prec"), r(recall, "recall"), r(F.try_divide(2 * precision * recall, precision + recall), "f1"), r(F.try_divide(tp + tn, n) - (recall + specificity) / 2, "gap"))


def class_balance(df: DataFrame, label: str = "label") -> DataFrame:
    """(label, n, share) of each class."""
    total = df.agg(F.count("*").alias("total"))
    return df.groupBy(F.col(label).alias("label")).agg(F.count("*").alias("n")).crossJoin(F.broadcast(total)).select("label", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def coverage(raw: DataFrame, unified: DataFrame) -> DataFrame:
    """Counts and percentages of rows that have each attribute, by source and for the unified set."""
    has = [F.col("lat").isNotNull() & F.col("lon").isNotNull(), F.col("address").isNotNull(), F.col("name").isNotNull(), F.size("place_type") > 0, F.size("tags") > 0]
    flat = raw.select(F.col("src").alias("source"), *[h.alias(a) for a, h in zip(ATTRIBUTES, has)]).unionByName(unified.select(F.lit("unified").alias("source"), *[h.alias(a) for a, h in zip(ATTRIBUTES, has)]))
    counts = flat.groupBy("source").agg(F.count("*").alias("n"), *[F.count_if(F.col(a)).alias(f"n_{a}") for a in ATTRIBUTES])
    return counts.select("source", "n", *[F.col(f"n_{a}") for a in ATTRIBUTES], *[F.round(100.0 * F.col(f"n_{a}") / F.col("n"), 1).alias(f"pct_{a}") for a in ATTRIBUTES])


def overlap(raw: DataFrame, unified: DataFrame) -> DataFrame:
    """Places procured, absorbed by a match, their share, and unified places."""
    a, b = raw.agg(F.count("*").alias("procured")), unified.agg(F.count("*").alias("unified"))
    return a.crossJoin(b).select("procured", "unified", (F.col("procured") - F.col("unified")).alias("absorbed"), F.round((F.col("procured") - F.col("unified")) / F.col("procured"), 6).alias("share"))


def cluster_pairs(clusters: DataFrame, truth: DataFrame) -> DataFrame:
    """Pairwise precision and recall of clusters, from group sizes rather than pairs."""
    both = clusters.join(truth, "uid")
    pairs = lambda *k: both.groupBy(*k).agg((F.count("*") * (F.count("*") - 1) / 2).alias("p")).agg(F.sum("p").cast("long").alias("n"))
    tp, said, true = (pairs(*k).withColumnRenamed("n", n) for k, n in ((("poi_id", "e"), "tp"), (("poi_id",), "said"), (("e",), "true_pairs")))
    return tp.crossJoin(said).crossJoin(true).select("tp", (F.col("said") - F.col("tp")).alias("fp"), (F.col("true_pairs") - F.col("tp")).alias("fn"), F.round(F.try_divide(F.col("tp"), F.col("said")), 6).alias("prec"), F.round(F.try_divide(F.col("tp"), F.col("true_pairs")), 6).alias("recall"))


def blocking_quality(pairs: DataFrame, truth: DataFrame, n_true: DataFrame, radii: tuple[float, ...] = (25.0, 50.0, 100.0, 150.0)) -> DataFrame:
    """(r, pairs, true_pairs, recall): one pass over unordered pairs at the largest radius."""
    t = pairs.join(truth.select(F.col("uid").alias("c"), F.col("e").alias("ec")), "c").join(truth.select(F.col("uid").alias("m"), F.col("e").alias("em")), "m")
    r = F.explode(F.array(*[F.lit(x) for x in radii])).alias("r")
    rows = t.select("dist_m", (F.col("ec") == F.col("em")).alias("same"), r).where("dist_m <= r")
    return rows.groupBy("r").agg(F.count("*").alias("pairs"), F.count_if(F.col("same")).alias("true_pairs")).crossJoin(n_true).select("r", "pairs", "true_pairs", F.round(F.col("true_pairs") / F.col("n_true"), 6).alias("recall"))
