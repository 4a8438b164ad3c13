"""The one schema every source is brought to, and the unified one."""

from __future__ import annotations

from pyspark.sql import types as T

POINT = T.StructType([T.StructField("type", T.StringType()), T.StructField("lat", T.DoubleType()), T.StructField("lon", T.DoubleType())])
BOUNDS = T.StructType([T.StructField(x, T.DoubleType()) for x in ("south", "west", "north", "east")])
ADDRESS = T.StructType([T.StructField(x, T.StringType()) for x in ("block", "street", "state", "country", "full")])
STRINGS = T.ArrayType(T.StringType())

POI = T.StructType([
    T.StructField("uid", T.StringType(), False), T.StructField("source", T.StringType(), False), T.StructField("rank", T.IntegerType()),
    T.StructField("geometry", POINT), T.StructField("bounds", BOUNDS), T.StructField("name", T.StringType()), T.StructField("address", ADDRESS),
    T.StructField("place_types", STRINGS), T.StructField("source_types", STRINGS), T.StructField("tags", STRINGS),
    T.StructField("extraction_date", T.DateType()), T.StructField("requires_verification", T.BooleanType()),
    T.StructField("verify_reasons", STRINGS), T.StructField("extras", T.MapType(T.StringType(), T.StringType())),
])

UNIFIED = T.StructType([
    T.StructField("poi_id", T.StringType(), False), *[f for f in POI if f.name not in ("uid", "source", "rank")],
    T.StructField("members", STRINGS), T.StructField("sources", STRINGS), T.StructField("n_members", T.LongType()),
])
