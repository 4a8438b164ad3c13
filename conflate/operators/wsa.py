"""Weighted-sum deciders: S = alpha * name score + beta * address score, match when S > V."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Published optima (V, alpha, beta) by method.
PUBLISHED = {"string": (0.85, 0.80, 0.20), "tfidf": (0.45, 0.90, 0.10), "hybrid": (0.85, 0.95, 0.05)}


def decide(features: DataFrame, v: float, alpha: float, beta: float) -> DataFrame:
    s = F.round(F.lit(alpha) * F.col("s_name") + F.lit(beta) * F.col("s_addr"), 9)
    return features.withColumn("score", s).withColumn("prediction", (s > F.lit(v)).cast("int"))


def grid(labelled: DataFrame, steps: int = 20, simplex: bool = True) -> DataFrame:
    """(alpha, beta, v, tp, tn, fp, fn) of every grid point, in one pass over the pairs.

    ``simplex=False`` scans alpha and beta freely up to a sum of 1.
    """
    points = labelled.sparkSession.range(steps + 1).select(F.col("id").cast("int").alias("i"))
    spread = points.crossJoin(points.select(F.col("i").alias("k"))).where(F.col("i") + F.col("k") == steps if simplex else F.col("i") + F.col("k") <= steps)
    spread = spread.crossJoin(points.select(F.col("i").alias("j")))
    g = spread.select((F.col("i") / float(steps)).alias("alpha"), (F.col("k") / float(steps)).alias("beta"), (F.col("j") / float(steps)).alias("v"))
    # distinct scores first: pairs fall together and the grid meets each value once
    counted = labelled.groupBy("s_name", "s_addr", "label").agg(F.count("*").alias("n"))
    hit = F.round(F.col("alpha") * F.col("s_name") + F.col("beta") * F.col("s_addr"), 9) > F.col("v")
    one = lambda cond: F.sum(F.when(cond, F.col("n")).otherwise(0)).alias
    return counted.crossJoin(F.broadcast(g)).groupBy("alpha", "beta", "v").agg(one(hit & (F.col("label") == 1))("tp"), one(~hit & (F.col("label") == 0))("tn"), one(hit & (F.col("label") == 0))("fp"), one(~hit & (F.col("label") == 1))("fn"))


def best(scored_grid: DataFrame, select_by: str = "balanced") -> DataFrame:
    """The grid point of the best measure; ties go to the smaller v, then the larger alpha."""
    overall = (F.col("tp") + F.col("tn")) / (F.col("tp") + F.col("tn") + F.col("fp") + F.col("fn"))
    balanced = (F.coalesce(F.try_divide(F.col("tp"), F.col("tp") + F.col("fn")), F.lit(0.0)) + F.coalesce(F.try_divide(F.col("tn"), F.col("tn") + F.col("fp")), F.lit(0.0))) / 2
    m = scored_grid.withColumn("overall", F.round(overall, 9)).withColumn("balanced", F.round(balanced, 9))
    return m.orderBy(F.desc(select_by), "v", F.desc("alpha"), F.desc("beta")).limit(1)
