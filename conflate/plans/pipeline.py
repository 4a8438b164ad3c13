"""The conflation pipeline: clean, pair, score, decide, group, unify."""

from __future__ import annotations

from typing import Protocol

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.operators import candidates, cluster, features, procure, taxonomy, unify, verify, wsa
from conflate.plans.tables import materialise


class Matcher(Protocol):
    """Any scorer of pairs: features in, ``score`` (0 to 1) and ``prediction`` (0 or 1) added."""

    def predict(self, features: DataFrame) -> DataFrame: ...


def match_with(places: DataFrame, matcher: Matcher, method: str = "hybrid", r: float = 100.0) -> DataFrame:
    """Ordered decisions by a given matcher, as a trained ensemble is."""
    pairs = materialise(candidates.within_radius(places, r), "pairs")
    return matcher.predict(features.build(places, pairs, method))


def match(places: DataFrame, method: str = "hybrid", r: float = 100.0, params: tuple[float, float, float] | None = None) -> DataFrame:
    """(c, m, ..., score, prediction) of ordered pairs by a weighted-sum decider; pairs are written once, as several
    branches read them."""
    pairs = materialise(candidates.within_radius(places, r), "pairs")
    return wsa.decide(features.build(places, pairs, method), *(params or wsa.PUBLISHED[method]))


def conflate(places: DataFrame, decided: DataFrame, how: str = "any", group: str = "components") -> tuple[DataFrame, DataFrame]:
    """(clusters, unified rows) from ordered decisions."""
    links = materialise(cluster.undirect(decided, how), "matches")
    if group == "star":
        clusters = cluster.star(places, links)
    elif group == "mutual_best":
        clusters = cluster.mutual_best(places, links)
    else:
        clusters = cluster.components(places, links)
    return clusters, unify.merge(places, clusters)


def run(raw: DataFrame, method: str = "hybrid") -> DataFrame:
    places = procure.dedup(raw)
    return conflate(places, match(places, method))[1]


def typed(places: DataFrame, terms: DataFrame) -> DataFrame:
    """``places`` with place types mapped to the default taxonomy and the flag of those that didn't map."""
    terms = materialise(terms, "taxonomy")
    labels = places.where("src <> 'social_places'").select(F.explode("place_type").alias("label")).distinct()
    words = labels.select(F.explode(taxonomy.components(F.col("label"))).alias("term")).union(terms).distinct()
    vectors = materialise(taxonomy.ngram_vectors(words), "vectors")
    mapped = taxonomy.map_types(places, terms, vectors).select("uid", F.col("place_types").alias("place_type"), "requires_verification")
    return places.drop("place_type", "requires_verification").join(mapped, "uid")


def six_steps(sources: list[DataFrame], terms: DataFrame, overrides: DataFrame, params: tuple[float, float, float], method: str = "hybrid") -> DataFrame:
    """Unified places from the sources' rows in the common schema: clean, map types, match, unify, verify.

    ``open_after_review`` marks the flagged places that the overrides leave open; ``place_type`` has the overrides.
    """
    cleaned = materialise(procure.dedup(reduce(DataFrame.unionByName, sources)), "places")
    places = materialise(typed(cleaned, terms), "typed")
    unified = materialise(conflate(places, match(places, method, params=params))[1], "unified")
    reviewed = verify.apply_overrides(unified, overrides).select("poi_id", F.col("place_type").alias("reviewed"), F.col("requires_verification").alias("open_after_review"))
    return unified.join(reviewed, "poi_id").withColumn("place_type", F.col("reviewed")).drop("reviewed")
