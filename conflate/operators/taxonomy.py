"""Taxonomy mapping: labels of the sources to a default taxonomy by cosine of word vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from conflate.functions.similarity import cosine
from conflate.operators import skipgram
from conflate.plans.tables import broadcast_if_small

TAU = 0.95
DIM = 64


def components(label: Column) -> Column:
    """Each word of a label and the whole phrase, lower-cased."""
    low = F.lower(F.trim(label))
    return F.array_distinct(F.concat(F.split(low, r"\s+"), F.array(low)))


def _hash_unit(g: Column, dim: int) -> Column:
    """A fixed pseudo-random vector in [-1, 1]^dim of an n-gram: hex digits of chained md5 sums."""
    text = F.concat(*[F.md5(F.concat(F.lit(f"{i}:"), g)) for i in range(-(-dim * 2 // 32))])
    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: (F.conv(F.substring(text, i * 2 + 1, F.lit(2)), 16, 10).cast("double") - 127.5) / 127.5)


def ngram_vectors(terms: DataFrame, lo: int = 3, hi: int = 6, dim: int = DIM) -> DataFrame:
    """(term, vec): the sum of the vectors of the term's character n-grams, with < and > as edges.

    Runs on distinct terms; the n-grams are exploded, made once each, and summed position by position.
    """
    edged = terms.select("term").distinct().withColumn("w", F.concat(F.lit("<"), F.col("term"), F.lit(">")))
    sizes = F.filter(F.sequence(F.lit(lo), F.lit(hi)), lambda n: n <= F.char_length("w"))
    grams = F.flatten(F.transform(sizes, lambda n: F.transform(F.sequence(F.lit(1), F.char_length("w") - n + 1), lambda i: F.substring("w", i, n))))
    one = edged.select("term", F.explode(F.when(F.size(sizes) > 0, grams).otherwise(F.array("w"))).alias("g"))
    vectors = one.select("g").distinct().withColumn("v", _hash_unit(F.col("g"), dim))
    flat = one.join(vectors, "g").select("term", F.posexplode("v").alias("i", "x")).groupBy("term", "i").agg(F.sum("x").alias("x"))
    return flat.groupBy("term").agg(F.array_sort(F.collect_list(F.struct("i", "x"))).alias("s")).select("term", F.transform("s", lambda s: s["x"]).alias("vec"))


def table_vectors(df: DataFrame) -> DataFrame:
    """Vectors given as (term, vec)."""
    return df.select("term", "vec")


def skipgram_vectors(docs: DataFrame, text: str = "text", dim: int = 16, min_count: int = 5, seed: int = 1) -> DataFrame:
    """(term, vec) of a skip-gram model trained on the corpus, with each word's 4-letter openings as extra tokens."""
    return skipgram.vectors(docs, text, dim, min_count, seed)


def map_labels(labels: DataFrame, taxonomy: DataFrame, vectors: DataFrame, tau: float = TAU) -> DataFrame:
    """(label, term, score): canonical terms whose cosine with a component of the label is tau or more.

    Only distinct labels are compared, so the cost doesn't grow with the places; the taxonomy is a small
    dimension and is broadcast.
    """
    parts = labels.select("label").distinct().select("label", F.explode(components(F.col("label"))).alias("part"))
    left = parts.join(vectors.select(F.col("term").alias("part"), F.col("vec").alias("va")), "part")
    right = taxonomy.select("term").join(vectors, "term").select("term", F.col("vec").alias("vb"))
    scored = left.crossJoin(broadcast_if_small(right)).withColumn("score", F.round(cosine(F.col("va"), F.col("vb")), 6)).where(F.col("score") >= tau)
    return scored.groupBy("label", "term").agg(F.max("score").alias("score"))


def map_types(places: DataFrame, taxonomy: DataFrame, vectors: DataFrame, tau: float = TAU, default_source: str = "social_places") -> DataFrame:
    """(uid, place_types, requires_verification): m-to-many; an unmapped label is kept and flagged; the default
    taxonomy's own source is left as it is."""
    one = places.select("uid", "src", F.explode_outer("place_type").alias("label"))
    found = map_labels(one.where(F.col("src") != default_source).select("label"), taxonomy, vectors, tau).groupBy("label").agg(F.array_sort(F.collect_set("term")).alias("terms"))
    j = one.join(broadcast_if_small(found), "label", "left")
    types = F.when((F.col("src") == default_source) | F.col("terms").isNull(), F.array(F.lower("label"))).otherwise(F.col("terms"))
    missing = (F.col("src") != default_source) & F.col("terms").isNull()
    return j.groupBy("uid").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.when(F.col("label").isNotNull(), types))))).alias("place_types"), F.bool_or(missing).alias("requires_verification"))


def exact_map(labels: DataFrame, taxonomy: DataFrame) -> DataFrame:
    """Baseline: equality of normalised labels."""
    return labels.select("label").distinct().withColumn("term", F.lower(F.trim("label"))).join(taxonomy.select("term"), "term").select("label", "term")


def lsh_map(labels: DataFrame, taxonomy: DataFrame, tau: float = TAU, seed: int = 3) -> DataFrame:
    """(label, term, score) for very large taxonomies: bucketed random projections of unit vectors, exact re-check.

    labels and taxonomy: (label | term, vec).  Cosine tau is the distance sqrt(2 - 2 tau) between unit vectors.
    """
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    def unit(df: DataFrame, name: str) -> DataFrame:
        norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
        return df.select(F.col(name).alias("key"), "vec", array_to_vector(F.transform("vec", lambda x: x.cast("double") / norm)).alias("u"))

    a, b = unit(labels, "label"), unit(taxonomy, "term")
    model = BucketedRandomProjectionLSH(inputCol="u", outputCol="h", bucketLength=1.0, numHashTables=6, seed=seed).fit(b)
    pairs = model.approxSimilarityJoin(a, b, (2 - 2 * tau) ** 0.5 + 1e-6, "dist")
    return pairs.select(F.col("datasetA.key").alias("label"), F.col("datasetB.key").alias("term"), F.round(cosine(F.col("datasetA.vec"), F.col("datasetB.vec")), 6).alias("score")).where(F.col("score") >= tau)
