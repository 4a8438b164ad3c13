"""Verification: reasons, the queue, manual overrides, programmatic checks, the map view."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.plans.tables import broadcast_if_small

UNMAPPED, UNTYPED = "place type not mapped", "no place type"


def reasons(df: DataFrame, mapped: str = "mapped") -> DataFrame:
    """Adds verify_reasons and requires_verification from ``mapped`` and ``place_type``."""
    why = F.array_compact(F.array(F.when((F.size("place_type") > 0) & ~F.col(mapped), F.lit(UNMAPPED)), F.when(F.size("place_type") == 0, F.lit(UNTYPED))))
    return df.withColumn("verify_reasons", why).withColumn("requires_verification", F.size(why) > 0)


def queue(df: DataFrame) -> DataFrame:
    return df.where("requires_verification")


def apply_overrides(df: DataFrame, overrides: DataFrame) -> DataFrame:
    """overrides (label, types): a person's decision for a label; rows whose labels are all resolved lose the flag."""
    table = broadcast_if_small(overrides.select(F.col("label"), F.col("types")))
    one = df.select("poi_id", F.explode_outer("place_type").alias("label")).join(table, "label", "left")
    merged = one.groupBy("poi_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.coalesce("types", F.when(F.col("label").isNotNull(), F.array("label"))))))).alias("new_types"), F.bool_or(F.col("types").isNotNull()).alias("touched"))
    return df.join(merged, "poi_id").withColumn("requires_verification", F.col("requires_verification") & ~F.col("touched")).withColumn("place_type", F.col("new_types")).drop("new_types", "touched")


def checks(df: DataFrame, area: tuple[float, float, float, float], first: str, last: str) -> DataFrame:
    """(check_name, n_bad, n_total): coordinate range, inside the area, missing names, repeated uids, date window."""
    s, w, n, e = area
    bad = {
        "coordinate_range": ~(F.col("lat").between(-90, 90) & F.col("lon").between(-180, 180)),
        "outside_area": ~(F.col("lat").between(s, n) & F.col("lon").between(w, e)),
        "name_missing": F.col("name").isNull(),
        "address_missing": F.col("address").isNull(),
        "date_window": ~F.col("extraction_date").between(F.to_date(F.lit(first)), F.to_date(F.lit(last))),
    }
    one = df.agg(F.count("*").alias("n_total"), (F.count("*") - F.count_distinct("uid")).alias("uid_repeats"), *[F.count_if(c).alias(k) for k, c in bad.items()])
    return one.unpivot(["n_total"], [*bad, "uid_repeats"], "check_name", "n_bad").select("check_name", "n_bad", "n_total")
