"""From ordered decisions to groups: undirect, connected components, star, mutual best."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from conflate.plans import graph


def undirect(decided: DataFrame, how: str = "any") -> DataFrame:
    """(a, b, prob) of the matched pairs: by either direction, by both, or by the mean score above one half."""
    g = decided.groupBy(F.least("c", "m").alias("a"), F.greatest("c", "m").alias("b")).agg(F.max("prediction").alias("hi"), F.min("prediction").alias("lo"), F.avg("prediction").alias("share"), F.max("score").alias("prob"))
    return g.where({"any": "hi = 1", "both": "lo = 1", "mean": "share > 0.5"}[how]).select("a", "b", "prob")


def components(vertices: DataFrame, links: DataFrame) -> DataFrame:
    """(uid, poi_id): poi_id is the least uid of the component; places without a link stand alone."""
    roots = graph.components(links).select(F.col("v").alias("uid"), "root")
    return vertices.select("uid").join(roots, "uid", "left").select("uid", F.coalesce("root", "uid").alias("poi_id"))


def star(places: DataFrame, links: DataFrame) -> DataFrame:
    """Each place joins its best-ranked matched neighbour of a better rank; no chains longer than one step count."""
    both = links.select(F.col("a").alias("uid"), F.col("b").alias("other"), "prob").union(links.select("b", "a", "prob"))
    ranks = places.select("uid", "rank")
    led = both.join(ranks, "uid").join(ranks.select(F.col("uid").alias("other"), F.col("rank").alias("orank")), "other").where("orank < rank")
    w = Window.partitionBy("uid").orderBy("orank", F.desc("prob"), "other")
    first = led.withColumn("k", F.row_number().over(w)).where("k = 1").select("uid", F.col("other").alias("head"))
    # a head that itself follows another is not a hub: its followers follow that one
    second = first.select(F.col("uid").alias("head"), F.col("head").alias("head2"))
    return places.select("uid").join(first, "uid", "left").join(second, "head", "left").select("uid", F.coalesce("head2", "head", "uid").alias("poi_id"))


def mutual_best(vertices: DataFrame, links: DataFrame) -> DataFrame:
    """Pairs that are each other's best match; everything else stands alone."""
    both = links.select(F.col("a").alias("uid"), F.col("b").alias("other"), "prob").union(links.select("b", "a", "prob"))
    w = Window.partitionBy("uid").orderBy(F.desc("prob"), "other")
    top = both.withColumn("k", F.row_number().over(w)).where("k = 1").select("uid", "other")
    back = top.select(F.col("other").alias("uid"), F.col("uid").alias("other"))
    pairs = top.join(back, ["uid", "other"]).select("uid", F.least("uid", "other").alias("poi_id"))
    return vertices.select("uid").join(pairs, "uid", "left").select("uid", F.coalesce("poi_id", "uid").alias("poi_id"))


def oversized(clusters: DataFrame, max_members: int = 25) -> DataFrame:
    """(poi_id, n) of clusters with more members than a real place can have: chains to be looked at."""
    return clusters.groupBy("poi_id").agg(F.count("*").alias("n")).where(F.col("n") > max_members)
