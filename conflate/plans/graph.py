"""Connected components by repeated contraction, without driver-side graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.plans.tables import discard, materialise


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) links -> one row (v, root) for every vertex that has a link; root = least vertex.

    Each round points every vertex at its least neighbour, follows the pointers to their end by doubling, and
    contracts the links.  A vertex that is no local minimum disappears, so at least half of them do: O(log n)
    rounds of O(log d) doublings.  Hubs cost no more than their links: the
    minimum is combined on the map side and the relabelling joins are plain equi joins that adaptive
    execution may split.  Null ends and self links are ignored.
    """
    e = (
        edges.select("a", "b").where("a is not null and b is not null and a <> b")
        .select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    )
    e = materialise(e, "links")
    labels = None
    for _ in range(max_rounds):
        if not e.take(1):
            break
        ends = e.select(F.col("a").alias("v"), F.col("b").alias("w")).union(e.select("b", "a"))
        up = materialise(ends.groupBy("v").agg(F.least(F.col("v"), F.min("w")).alias("p")), "pointers")
        # double the pointers until every one ends at a root
        hop = up
        while True:
            nxt = hop.select(F.col("v").alias("p"), F.col("p").alias("q"))
            further = materialise(hop.join(nxt, "p").select("v", F.col("q").alias("p"), (F.col("q") != F.col("p")).alias("moved")), "hops")
            done = not further.where("moved").take(1)
            if hop is not up:
                discard(hop)
            hop = further
            if done:
                break
        to_a = hop.select(F.col("v").alias("a"), F.col("p").alias("pa"))
        to_b = hop.select(F.col("v").alias("b"), F.col("p").alias("pb"))
        smaller = materialise(
            e.join(to_a, "a").join(to_b, "b").where("pa <> pb")
            .select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(),
            "links",
        )
        if labels is None:
            new = hop.select("v", F.col("p").alias("root"))
        else:
            step = hop.select(F.col("v").alias("root"), F.col("p").alias("q"))
            new = materialise(labels.join(step, "root", "left").select("v", F.coalesce("q", "root").alias("root")), "roots")
            discard(labels)
        discard(e)
        discard(up)
        # the labels of the first round still read `hop`; later rounds have their own table
        if labels is not None:
            discard(hop)
        labels, e = new, smaller
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    if labels is None:
        labels = e.select(F.col("a").alias("v"), F.col("b").alias("root"))
    return labels
