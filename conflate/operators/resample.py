"""Stratified splits and balanced resampling, all by hashes of the pair: the same under any partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Labelled pairs at most; a person's or a fixture's labels of one region.
LABELLED = 20_000_000


def hash32(c: Column) -> Column:
    """First 8 hex digits of the md5, as a number; the same in any engine."""
    return F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long")


def pair_hash(tag: str) -> Column:
    return hash32(F.concat(F.lit(tag), F.col("a"), F.lit("|"), F.col("b")))


def split(df: DataFrame, share: float = 0.75, seed: str = "s") -> DataFrame:
    """Adds ``train``: the first floor(share * n) rows of each class in hash order."""
    by_class = Window.partitionBy("label")
    k = F.row_number().over(by_class.orderBy(pair_hash(seed), "a", "b"))
    return df.withColumn("train", k <= F.floor(F.lit(share) * F.count("*").over(by_class)))


def folds(df: DataFrame, n: int = 5, seed: str = "f") -> DataFrame:
    """Adds ``fold``: dealt in hash order within each class, by the original pair, so that copies made by
    oversampling share a fold."""
    pairs = df.select("a", "b", "label").distinct()
    w = Window.partitionBy("label").orderBy(pair_hash(seed), "a", "b")
    dealt = pairs.withColumn("fold", (F.row_number().over(w) - 1) % n).select("a", "b", "fold")
    return df.join(dealt, ["a", "b"])


def over(minority: DataFrame, size: int, seed: str = "o") -> DataFrame:
    """``size`` draws with replacement: draw i takes the row of number h(seed, i) mod n."""
    numbered = minority.withColumn("k", F.row_number().over(Window.orderBy("a", "b")) - 1)
    n = minority.agg(F.count("*").alias("n"))
    draws = minority.sparkSession.range(size).select(F.col("id").alias("draw")).crossJoin(n).where("n > 0")
    draws = draws.select("draw", (hash32(F.concat(F.lit(seed), F.col("draw").cast("string"))) % F.col("n")).cast("int").alias("k"))
    return draws.join(numbered, "k").drop("k")


def under(majority: DataFrame, size: int, seed: str = "u") -> DataFrame:
    """``size`` rows without replacement: the first in hash order (a top-k, no global sort)."""
    return majority.orderBy(pair_hash(seed), "a", "b").limit(size)


def balanced_sets(train: DataFrame, n_bags: int = 5, size: int | str = "sqrt") -> DataFrame:
    """(bag_id, train columns): in each bag ``size`` drawn rows of the minority and ``size`` of the majority.

    ``size``: a number, ``minority``, ``majority``, or ``sqrt`` for the geometric mean of the class sizes.
    Training sets of labelled pairs are small: beyond ``LABELLED`` rows, where windows of one class would no longer
    fit a task, this raises.  Only the two class counts come to the driver.
    """
    counts = {r["label"]: r["count"] for r in train.groupBy("label").count().collect()}
    if sum(counts.values()) > LABELLED:
        raise ValueError(f"{sum(counts.values())} labelled pairs; at most {LABELLED} are resampled")
    if len(counts) < 2:
        raise ValueError("one class is absent from the training part")
    small, big = sorted(counts, key=lambda k: (counts[k], -k))
    m = size if isinstance(size, int) else {"minority": counts[small], "majority": counts[big], "sqrt": int((counts[small] * counts[big]) ** 0.5)}[size]
    bags = []
    for i in range(n_bags):
        a = over(train.where(F.col("label") == small), m, f"o{i}|").drop("draw")
        b = under(train.where(F.col("label") == big), m, f"u{i}|")
        if m > counts[big]:
            b = over(train.where(F.col("label") == big), m, f"u{i}|").drop("draw")
        bags.append(a.unionByName(b).withColumn("bag_id", F.lit(i)))
    out = bags[0]
    for b in bags[1:]:
        out = out.unionByName(b)
    return out


def class_weights(df: DataFrame) -> DataFrame:
    """(label, n, weight): weight = rows / (classes * rows of the class)."""
    g = df.groupBy("label").agg(F.count("*").alias("n"))
    totals = g.agg(F.sum("n").alias("total"), F.count("*").alias("classes"))
    return g.crossJoin(F.broadcast(totals)).select("label", "n", F.round(F.col("total") / (F.col("classes") * F.col("n")), 6).alias("weight"))
