"""Feature tables of pairs: a name score and an address score by method, and labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.functions.similarity import edit_similarity, token_sort
from conflate.operators import tfidf

#: method -> (name score, address score).
METHODS = {"string": ("edit", "edit"), "tfidf": ("tfidf", "tfidf"), "hybrid": ("edit", "tfidf")}
DIGITS = 6


def build(df: DataFrame, pairs: DataFrame, method: str = "hybrid", metric: str = "lev_max", idf: str = "plain") -> DataFrame:
    """(c, m, dist_m, s_name, s_addr, name_missing, addr_missing); scores have six decimals.

    Token-sorted strings are made once per place and joined, not once per pair.
    """
    name_by, addr_by = METHODS[method]
    p = df.select("uid", "name", "address", token_sort(F.col("name")).alias("tname"), token_sort(F.col("address")).alias("taddr"))
    c, m = (p.select(F.col("uid").alias(x), *[F.col(k).alias(f"{x}_{k}") for k in ("name", "address", "tname", "taddr")]) for x in "cm")
    j = pairs.join(c, "c").join(m, "m")
    missing = [(F.col("c_name").isNull() | F.col("m_name").isNull()).alias("name_missing"), (F.col("c_address").isNull() | F.col("m_address").isNull()).alias("addr_missing")]
    out = j.select("c", "m", "dist_m", edit_similarity(F.col("c_tname"), F.col("m_tname"), metric).alias("s_name"), edit_similarity(F.col("c_taddr"), F.col("m_taddr"), metric).alias("s_addr"), *missing)
    for by, column, text in ((name_by, "s_name", "name"), (addr_by, "s_addr", "address")):
        if by == "tfidf":
            scores = tfidf.local_sim(pairs, df.select("uid", F.col(text).alias("text")), idf).withColumnRenamed("score", f"{column}_local")
            out = out.drop(column).join(scores, ["c", "m"]).withColumnRenamed(f"{column}_local", column)
    return out.select("c", "m", "dist_m", F.round("s_name", DIGITS).alias("s_name"), F.round("s_addr", DIGITS).alias("s_addr"), "name_missing", "addr_missing")


def undirected(features: DataFrame) -> DataFrame:
    """One row a pair, a < b; the two directions' scores are averaged."""
    return features.groupBy(F.least("c", "m").alias("a"), F.greatest("c", "m").alias("b")).agg(F.first("dist_m").alias("dist_m"), F.round(F.avg("s_name"), DIGITS).alias("s_name"), F.round(F.avg("s_addr"), DIGITS).alias("s_addr"), F.max("name_missing").alias("name_missing"), F.max("addr_missing").alias("addr_missing"))


def labelled(features: DataFrame, truth: DataFrame) -> DataFrame:
    """Adds label 1 where both places are one entity; truth (uid, e) covers the labelled region only."""
    ta, tb = truth.select(F.col("uid").alias("a"), F.col("e").alias("ea")), truth.select(F.col("uid").alias("b"), F.col("e").alias("eb"))
    return features.join(ta, "a").join(tb, "b").withColumn("label", (F.col("ea") == F.col("eb")).cast("int")).drop("ea", "eb")
