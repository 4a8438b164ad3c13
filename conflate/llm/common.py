"""Small pieces that several corpus operators share."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from conflate.plans.graph import components
from conflate.plans.tables import broadcast_if_small, discard, materialise


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: Column) -> Column:
    """A quarter of the rows by their key: never learned from."""
    return F.crc32(doc_id.cast("string")) % 4 == 2


def for_learning(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 != 2, F.lit(False))


def bounded_sample(df: DataFrame, key: str, groups: str, per_group: int, seed: int = 7) -> DataFrame:
    """About ``per_group`` rows of each value of ``groups``, chosen by a hash of the key.

    Counting reads two narrow columns.  Groups below the bound come whole.
    """
    sizes = {r[0]: r[1] for r in df.groupBy(groups).count().collect()}
    share = F.lit(1.0)
    for value, n in sizes.items():
        if n > per_group:
            share = F.when(F.col(groups) == F.lit(value), F.lit(per_group / n)).otherwise(share)
    u = F.pmod(F.xxhash64(F.lit(seed), F.col(key)), F.lit(1_000_003)) / F.lit(1_000_003.0)
    return df.where(u < share)


#: Rows of one Arrow batch at most.  Texts run to hundreds of kilobytes, and both sides hold a batch whole.
ROWS_PER_BATCH = 1_000


def small_batches(spark: SparkSession) -> None:
    """Keep Arrow batches of documents small; a runtime setting, lowered and never raised."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name))
    if now <= 0 or now > ROWS_PER_BATCH:
        spark.conf.set(name, str(ROWS_PER_BATCH))


def text_key(text: Column) -> Column:
    """Hash of a whole text.  With doc_id it tells rows apart: rows alike in both are interchangeable."""
    return F.xxhash64(text)


def _same(left: DataFrame, right: DataFrame) -> Column:
    """A null doc_id equals itself."""
    return left["doc_id"].eqNullSafe(right["doc_id"]) & (left["__th"] == right["th"])


def without(docs: DataFrame, gone: DataFrame, once: DataFrame | None = None) -> DataFrame:
    """``docs`` less the rows whose (doc_id, th) stands in ``gone``; all columns kept.

    Of rows alike in both that stand in ``once``, one stays.  One rule at every size: the join is null-safe
    whether a side is broadcast or not, and copies combine on the map side.
    """
    keyed = docs.withColumn("__th", text_key(F.col("text")))
    gone = broadcast_if_small(gone)
    kept = keyed.join(gone, _same(keyed, gone), "left_anti")
    if once is not None and once.take(1):
        once = broadcast_if_small(once)
        one = kept.join(once, _same(kept, once), "left_semi").dropDuplicates(["doc_id", "__th"])
        kept = kept.join(once, _same(kept, once), "left_anti").unionByName(one)
    return kept.select(*docs.columns)


def keep_decided(docs: DataFrame, decided: DataFrame) -> DataFrame:
    """``docs`` less the rows that ``decided``, (doc_id, th, kept) for each row in a group, doesn't keep."""
    by_key = materialise(decided.groupBy("doc_id", "th").agg(F.bool_or("kept").alias("kept"), F.count("*").alias("n")).where("not kept or n > 1"), "decided")
    return without(docs, by_key.where("not kept").select("doc_id", "th"), by_key.where("kept and n > 1").select("doc_id", "th"))


def apply_per_row(docs: DataFrame, decided: DataFrame, value: str) -> DataFrame:
    """``docs`` with the column ``value`` of ``decided``, (row, doc_id, th, value) for every row of ``docs``.

    Rows alike in doc_id and text are interchangeable: one of them gets the value of the least ``row``, the others
    that of the greatest.  Only such rows are written and numbered.
    """
    by_key = decided.groupBy("doc_id", "th").agg(F.count("*").alias("__n"), F.min_by(value, "row").alias("__first"), F.max_by(value, "row").alias("__rest"))
    by_key = materialise(by_key.where("__n > 1 or __first is not null"), "decisions")
    keyed = docs.withColumn("__th", text_key(F.col("text")))
    side = by_key.withColumnRenamed("doc_id", "__id")
    joined = keyed.join(side, keyed["doc_id"].eqNullSafe(side["__id"]) & (keyed["__th"] == side["th"]), "left")
    columns = [*docs.columns, value]
    out = joined.where("__n is null or __n = 1").withColumn(value, F.col("__first")).select(*columns)
    if by_key.where("__n > 1").take(1):
        alike = materialise(joined.where("__n > 1").withColumn("__at", F.monotonically_increasing_id()), "alike")
        least = alike.groupBy("doc_id", "__th").agg(F.min("__at").alias("__least")).withColumnsRenamed({"doc_id": "__id", "__th": "th"}).select("__id", "th", "__least")
        alike = alike.drop("__id", "th")
        marked = alike.join(least, alike["doc_id"].eqNullSafe(least["__id"]) & (alike["__th"] == least["th"]))
        out = out.unionByName(marked.withColumn(value, F.when(F.col("__at") == F.col("__least"), F.col("__first")).otherwise(F.col("__rest"))).select(*columns))
    return out


#: Lines or texts of a crowded bucket that meet all others in the first round, and the growth from round to round.
PIVOTS, GROWTH = 8, 8


def crowds(members: DataFrame, bucket: list[str], vertex: str, links: Callable[[], DataFrame], near: Callable[[str, str], str] | None = None) -> Iterator[DataFrame]:
    """Pairs (a < b) to test, round by round, until every pair of a bucket was given or is connected.

    ``members`` has a row of each vertex of each bucket; ``links`` gives the links found so far; ``near`` an SQL
    condition on two members x and y.  In a round a hashed share of a bucket's members meet all members of other
    components, and then leave.  The share grows until all are in it, so the rounds end.
    """
    rest, round_ = materialise(members, "crowds"), 0
    while rest.take(1):
        roots = components(links()).select(F.col("v").alias(vertex), "root")
        rooted = rest.join(roots, vertex, "left").withColumn("root", F.coalesce("root", vertex))
        rooted = materialise(rooted, "rooted")
        sizes = rooted.groupBy(*bucket).agg(F.count("*").alias("n"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi")
        share = F.pmod(F.xxhash64(vertex, F.lit(5)), F.lit(1_000_003)) * F.col("n") < F.lit(1_000_003 * PIVOTS * GROWTH**round_)
        live = materialise(rooted.join(sizes.select(*bucket, "n"), bucket).withColumn("pivot", share).drop("n"), "live")
        fields = F.struct(*[c for c in live.columns if c not in bucket])
        two = live.where("pivot").select(*bucket, fields.alias("x")).join(live.select(*bucket, fields.alias("y")), bucket)
        two = two.where("x.root <> y.root").where(f"not y.pivot or x.{vertex} < y.{vertex}")
        two = two.where(near("x", "y")) if near else two
        yield two.select(F.least(f"x.{vertex}", f"y.{vertex}").alias("a"), F.greatest(f"x.{vertex}", f"y.{vertex}").alias("b")).distinct()
        discard(rooted)
        discard(rest)
        rest, round_ = materialise(live.where("not pivot").drop("pivot", "root"), "crowds"), round_ + 1
        discard(live)
