"""Merging a cluster's attributes by source reliability, in one aggregation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from conflate.schema import BOUNDS

#: Reliability rank of each source role, 1 the most trusted.
RANKS = {"authority_map": 1, "authority_registry": 2, "social_places": 3, "commercial_map": 4, "open_map": 5}


def source_rank(df: DataFrame, ranks: dict[str, int] | None = None) -> DataFrame:
    """Adds ``rank`` from the source; ties between sources are allowed, unknown sources come last."""
    table = df.sparkSession.createDataFrame(list((ranks or RANKS).items()), "src string, rank int")
    return df.drop("rank").join(F.broadcast(table), "src", "left").withColumn("rank", F.coalesce("rank", F.lit(1_000_000)))


def _longest(value: str, fallback: bool) -> Column:
    """Longest string of the best rank that has one (or of the best rank only); ties to the least string."""
    key = F.struct(F.col("rank").alias("r"), (-F.char_length(value)).alias("l"), F.col(value).alias("v"))
    usable = F.col(value).isNotNull() if fallback else F.col(value).isNotNull() & F.col("top")
    return F.min(F.when(usable, key))["v"]


def _union(column: str) -> Column:
    return F.array_sort(F.array_distinct(F.flatten(F.collect_list(column))))


def merge(places: DataFrame, clusters: DataFrame, fallback: bool = True, bounds: str = "largest") -> DataFrame:
    """One row a cluster.

    places: uid, src, rank, lat, lon, bounds, name, address, place_type, tags, extraction_date,
    requires_verification.  Location: mean of the best-ranked members.  Name, address: longest string of the
    best rank; with ``fallback`` the next rank that has one.  Bounds: the largest member's (``envelope``: that
    of all).  Sets: unions.  Date: latest.  Flag: any member's, or no place type.
    """
    w = Window.partitionBy("poi_id")
    rows = places.join(clusters, "uid").withColumn("top", F.col("rank") == F.min("rank").over(w))
    area = (F.col("bounds.north") - F.col("bounds.south")) * (F.col("bounds.east") - F.col("bounds.west"))
    if bounds == "largest":
        box = F.max(F.when(F.col("bounds").isNotNull(), F.struct(F.round(area, 15).alias("area"), F.col("uid"), F.col("bounds"))))["bounds"]
    else:
        box = F.when(F.count("bounds") > 0, F.struct(F.min("bounds.south").alias("south"), F.min("bounds.west").alias("west"), F.max("bounds.north").alias("north"), F.max("bounds.east").alias("east")))
    out = rows.groupBy("poi_id").agg(
        F.avg(F.when(F.col("top"), F.col("lat"))).alias("lat"), F.avg(F.when(F.col("top"), F.col("lon"))).alias("lon"), box.alias("bounds"),
        _longest("name", fallback).alias("name"), _longest("address", fallback).alias("address"), _union("place_type").alias("place_type"), _union("tags").alias("tags"),
        F.array_sort(F.collect_set("src")).alias("sources"), F.array_sort(F.collect_list("uid")).alias("members"), F.count("*").alias("n_members"),
        F.max("extraction_date").alias("extraction_date"), F.bool_or("requires_verification").alias("flag"),
    )
    return out.withColumn("requires_verification", F.col("flag") | (F.size("place_type") == 0)).drop("flag")


@F.pandas_udf(BOUNDS)
def most_conservative_bounds(south, west, north, east):  # noqa: ANN001, ANN201
    """Demonstration as a vectorised function of arrays: the largest of a cluster's boxes."""
    import pandas as pd

    rows = []
    for s, w, n, e in zip(south, west, north, east):
        k = max(range(len(s)), key=lambda i: (n[i] - s[i]) * (e[i] - w[i]), default=None)
        rows.append((None,) * 4 if k is None else (s[k], w[k], n[k], e[k]))
    return pd.DataFrame(rows, columns=["south", "west", "north", "east"])
