"""The domain's functions for SQL users: inlined SQL functions, a Python table function, their registration."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

SQL_FUNCTIONS = {
    "geo_distance_m(lat1 DOUBLE, lon1 DOUBLE, lat2 DOUBLE, lon2 DOUBLE) RETURNS DOUBLE": "12742000D * asin(sqrt(least(1D, power(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * power(sin(radians(lon2 - lon1) / 2), 2))))",
    "token_sorted(x STRING) RETURNS STRING": "array_join(array_sort(split(trim(regexp_replace(lower(x), '[^\\\\p{L}\\\\p{N}]+', ' ')), ' ')), ' ')",
    "name_similarity(a STRING, b STRING) RETURNS DOUBLE": "CASE WHEN a IS NULL OR b IS NULL THEN 0D ELSE coalesce(1 - try_divide(levenshtein(a, b), greatest(char_length(a), char_length(b))), 1D) END",
    "cell_id(lat DOUBLE, lon DOUBLE, side DOUBLE) RETURNS STRING": "concat(cast(floor(radians(lat) * 6371000D / side) AS STRING), ':', cast(floor(radians(lon) * 6371000D * cos(radians(lat)) / side) AS STRING))",
    "vec_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "coalesce(try_divide(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x), sqrt(aggregate(a, 0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0D, (s, x) -> s + x * x))), 0D)",
}


def _ngrams():  # noqa: ANN202
    @udtf(returnType="gram string")
    class Ngrams:
        """Character n-grams of <word>."""

        def eval(self, word: str, lo: int, hi: int):  # noqa: ANN201
            w = f"<{word}>"
            for n in range(lo, hi + 1):
                for i in range(len(w) - n + 1):
                    yield (w[i : i + n],)

    return Ngrams


def _split_box():  # noqa: ANN202
    @udtf(returnType="level int, ix bigint, iy bigint")
    class SplitBox:
        """The four quarters of a box."""

        def eval(self, level: int, ix: int, iy: int):  # noqa: ANN201
            for i in (0, 1):
                for j in (0, 1):
                    yield level + 1, 2 * ix + i, 2 * iy + j

    return SplitBox


def register(spark: SparkSession) -> None:
    for head, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("ngrams", _ngrams())
    spark.udtf.register("split_box", _split_box())
