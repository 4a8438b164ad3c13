"""TF-IDF similarities with the inverse document frequency of a neighbourhood, a cell or everything."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from conflate.functions.similarity import clean


def tf(docs: DataFrame, key: str = "uid", text: str = "text") -> DataFrame:
    """(key, term, tf): share of the term among the document's terms; null and empty texts have none."""
    terms = docs.select(F.col(key).alias("uid"), F.filter(F.split(clean(F.col(text)), " "), lambda t: t != "").alias("ts")).where("size(ts) > 0")
    one = terms.select("uid", F.size("ts").alias("n"), F.explode("ts").alias("term"))
    return one.groupBy("uid", "term").agg((F.count("*") / F.first("n")).alias("tf"))


def _idf(n: Column, df: Column, kind: str) -> Column:
    return F.log(n / df) if kind == "plain" else F.log((n + 1) / (df + 1)) + 1


def local_sim(pairs: DataFrame, docs: DataFrame, idf: str = "plain", corpus: str = "centroid+neighbours") -> DataFrame:
    """(c, m, score) of ordered pairs: cosine of TF-IDF vectors; 0 where a norm is 0 or a text is missing.

    The corpus of a centroid is its neighbours' texts and, by default, its own.  Terms are shuffled once on the
    centroid; frequencies, norms and products all keep that partitioning.  With ``corpus='neighbours'`` terms
    that no neighbour has are left out.
    """
    t = tf(docs)
    held = pairs.select("c", "m").union(pairs.select("c", F.col("c").alias("m")).distinct())
    rows = held.join(t.withColumnRenamed("uid", "m"), "m").repartition("c")
    own = F.col("m") == F.col("c")
    counted = F.lit(1) if corpus == "centroid+neighbours" else F.when(~own, 1).otherwise(0)
    of_term, of_c, of_pair = Window.partitionBy("c", "term"), Window.partitionBy("c"), Window.partitionBy("c", "m").orderBy("term")
    rows = rows.withColumn("df", F.sum(counted).over(of_term)).withColumn("own_tf", F.max(F.when(own, F.col("tf"))).over(of_term))
    rows = rows.withColumn("first", F.row_number().over(of_pair) == 1)
    rows = rows.withColumn("n", F.sum(F.when(F.col("first"), counted).otherwise(0)).over(of_c))
    rows = rows.where("df > 0").withColumn("idf", _idf(F.col("n"), F.col("df"), idf))
    scored = rows.groupBy("c", "m").agg(
        F.sum(F.col("tf") * F.col("idf") * F.coalesce("own_tf", F.lit(0.0)) * F.col("idf")).alias("dot"),
        F.sum(F.pow(F.col("tf") * F.col("idf"), F.lit(2.0))).alias("sq"))
    scored = scored.withColumn("own_sq", F.max(F.when(own, F.col("sq"))).over(of_c))
    score = F.coalesce(F.try_divide(F.col("dot"), F.sqrt("sq") * F.sqrt("own_sq")), F.lit(0.0))
    return pairs.join(scored.where(~own).select("c", "m", score.alias("score")), ["c", "m"], "left").select("c", "m", F.coalesce("score", F.lit(0.0)).alias("score"))


def shared_sim(pairs: DataFrame, docs: DataFrame, group: DataFrame | None = None, idf: str = "plain") -> DataFrame:
    """One IDF for all documents, or per ``group`` (uid, g), each uid in one group or more.

    The score of (c, m) uses the frequencies of c's group.  An approximation of ``local_sim`` (``group`` = grid
    cells) and its ablation (none).
    """
    t = tf(docs)
    if group is None:
        n, g = docs.join(t.select("uid").distinct(), "uid").count(), None
        freq = t.groupBy("term").agg(_idf(F.lit(float(max(n, 1))), F.count("*"), idf).alias("idf"))
        weighted = t.join(freq, "term").select("uid", "term", (F.col("tf") * F.col("idf")).alias("w"))
        a, b = weighted.select(F.col("uid").alias("c"), "term", F.col("w").alias("wc")), weighted.select(F.col("uid").alias("m"), "term", F.col("w").alias("wm"))
        norm = weighted.groupBy("uid").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
        dots = pairs.select("c", "m").join(a, "c").join(b, ["m", "term"]).groupBy("c", "m").agg(F.sum(F.col("wc") * F.col("wm")).alias("dot"))
        out = pairs.select("c", "m").join(dots, ["c", "m"], "left").join(norm.select(F.col("uid").alias("c"), F.col("norm").alias("nc")), "c", "left").join(norm.select(F.col("uid").alias("m"), F.col("norm").alias("nm")), "m", "left")
    else:
        home = group.where("home").select("uid", "g")
        wide = group.join(t, "uid")
        sizes = wide.select("g", "uid").distinct().groupBy("g").agg(F.count("*").alias("n"))
        freq = wide.groupBy("g", "term").agg(F.count("*").alias("df")).join(sizes, "g").select("g", "term", _idf(F.col("n"), F.col("df"), idf).alias("idf"))
        at = pairs.select("c", "m").join(home.withColumnRenamed("uid", "c"), "c")
        both = at.select("c", "m", "g", F.col("c").alias("uid"), F.lit(1).alias("side")).union(at.select("c", "m", "g", "m", F.lit(0)))
        w = both.join(t, "uid").join(freq, ["g", "term"]).withColumn("w", F.col("tf") * F.col("idf"))
        flat = w.groupBy("c", "m", "term").agg(F.max(F.when(F.col("side") == 1, F.col("w"))).alias("wc"), F.max(F.when(F.col("side") == 0, F.col("w"))).alias("wm"))
        out = flat.groupBy("c", "m").agg(F.sum(F.coalesce("wc", F.lit(0.0)) * F.coalesce("wm", F.lit(0.0))).alias("dot"), F.sqrt(F.sum(F.coalesce("wc", F.lit(0.0)) * F.coalesce("wc", F.lit(0.0)))).alias("nc"), F.sqrt(F.sum(F.coalesce("wm", F.lit(0.0)) * F.coalesce("wm", F.lit(0.0)))).alias("nm"))
        out = pairs.select("c", "m").join(out, ["c", "m"], "left")
    return out.select("c", "m", F.coalesce(F.try_divide(F.col("dot"), F.col("nc") * F.col("nm")), F.lit(0.0)).alias("score"))


def top_terms(docs: DataFrame, key: str, group: str, text: str, k: int = 3) -> DataFrame:
    """The k terms of most TF-IDF weight in each document; documents of one ``group`` are one corpus."""
    t = tf(docs, key, text).join(docs.select(F.col(key).alias("uid"), F.col(group).alias("g")), "uid")
    sizes = t.select("g", "uid").distinct().groupBy("g").agg(F.count("*").alias("n"))
    freq = t.groupBy("g", "term").agg(F.count("*").alias("df")).join(sizes, "g")
    w = t.join(freq, ["g", "term"]).select("uid", "term", F.round(F.col("tf") * F.log(F.col("n") / F.col("df")), 6).alias("w"))
    best = Window.partitionBy("uid").orderBy(F.desc("w"), "term")
    return w.withColumn("place", F.row_number().over(best)).where(F.col("place") <= k)
