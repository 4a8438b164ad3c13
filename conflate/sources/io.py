"""Readers and writers of the formats sources come in."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def read_csv(spark: SparkSession, path: str, schema: StructType | str, mode: str = "PERMISSIVE") -> DataFrame:
    return spark.read.schema(schema).option("header", True).option("mode", mode).csv(path)


def read_json(spark: SparkSession, path: str, schema: StructType | str | None = None, corrupt: str = "_corrupt_record") -> DataFrame:
    """JSON lines; with a schema, broken lines come with their text in ``corrupt`` if the schema has it."""
    r = spark.read.option("columnNameOfCorruptRecord", corrupt)
    return (r.schema(schema) if schema is not None else r).json(path)


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def read_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.orc(path)


def write_unified(df: DataFrame, path: str, side_deg: float = 0.01) -> None:
    """Parquet partitioned by a coarse tile, so that areas prune files; rows are dealt by tile before writing."""
    tile = F.concat(F.floor(F.col("lat") / side_deg).cast("string"), F.lit("_"), F.floor(F.col("lon") / side_deg).cast("string"))
    df.withColumn("tile", tile).repartition("tile").write.mode("overwrite").partitionBy("tile").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose later joins on ``key`` need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def write_geojson(features: DataFrame, path: str) -> None:
    features.select(F.col("feature").alias("value")).write.mode("overwrite").text(path)


def timed_sink(df: DataFrame) -> None:
    """Runs the whole plan and keeps nothing."""
    df.write.format("noop").mode("overwrite").save()
