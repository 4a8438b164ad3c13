"""Exact dedup by progressive refinement: length, then prefix hash, then the whole text's hash.

Texts are equal when identical after the ASCII blanks (space, tab, line feed, vertical tab, form feed,
carriage return) are deleted; null counts as empty, so all null, empty and blank texts are one group.  Of equal
texts the row with most code points in the original text stays, then the least doc_id (a null doc_id
sorts after all others), then the least text hash; of rows alike in all that, one stays.  Rows are told apart by their
place in one written scan, so repeated and null doc_ids are rows like any other.  An empty table gives no rows.
Extra columns are never read.

Lengths and prefix hashes are narrow columns made in one scan.  Lengths are counted first, then the prefix hashes of
rows whose length occurs again; only rows that share both with another row go on to the hash of the full content.
Counts combine on the map side, and the joins that carry them back are plain equi joins, which adaptive execution
splits when one group holds a large share of all rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import keep_decided, text_key
from conflate.plans.tables import broadcast_if_small, materialise

PREFIX_CHARS = 64


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", "")


def keys(docs: DataFrame, *more: Column) -> DataFrame:
    """row, doc_id, th, code points, normalised length, prefix hash, and ``more`` made from ``norm``; one scan."""
    t = docs.select("doc_id", text_key(F.col("text")).alias("th"), F.coalesce(F.col("text"), F.lit("")).alias("t"), F.monotonically_increasing_id().alias("row"))
    norm = t.select("row", "doc_id", "th", F.char_length("t").alias("n_chars"), normalised(F.col("t")).alias("norm"))
    return norm.select("row", "doc_id", "th", "n_chars", F.char_length("norm").alias("len"), F.xxhash64(F.substring("norm", 1, PREFIX_CHARS)).alias("prefix"), *more)


def surviving(keyed: DataFrame) -> DataFrame:
    """The rows that share length and prefix hash with another.

    Lengths are counted first, in one number a row; prefix hashes only of rows whose length occurs again.
    """
    lengths = keyed.groupBy("len").agg(F.count("*").alias("n")).where("n > 1").select("len")
    same_length = keyed.join(broadcast_if_small(lengths), "len", "left_semi")
    shared = materialise(same_length.groupBy("len", "prefix").agg(F.count("*").alias("n")).where("n > 1").select("len", "prefix"), "prefixes")
    return same_length.join(broadcast_if_small(shared), ["len", "prefix"], "left_semi")


def _sha() -> Column:
    return F.sha2(F.encode("norm", "UTF-8"), 256)


def decided(docs: DataFrame, all_hashes: bool = True) -> DataFrame:
    """row, doc_id, th, keep_id, group_size, kept and text_sha256 of every row.

    With ``all_hashes`` the full hash is made in the scan that makes the lengths, as every row must report it.
    Without, only the texts of surviving rows are read again and hashed, and text_sha256 is null for the others.
    """
    keyed = materialise(keys(docs, *([_sha().alias("sha")] if all_hashes else [])), "keys")
    alive = surviving(keyed)
    if not all_hashes:
        # rows alike in doc_id and text have one hash; a text is read once for each of its hashes
        wanted = materialise(alive.select("th").distinct(), "alive")
        texts = docs.select(text_key(F.col("text")).alias("th"), normalised(F.col("text")).alias("norm")).join(broadcast_if_small(wanted), "th", "left_semi")
        full = materialise(texts.select("th", _sha().alias("sha")).distinct(), "hashed")
        alive = alive.join(full, "th")
    alive = materialise(alive.select("row", "doc_id", "th", "n_chars", "sha"), "alive")
    sizes = alive.groupBy("sha").agg(F.count("*").alias("size")).where("size > 1")
    order = F.struct((-F.col("n_chars")).alias("c"), F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("id"), "th", "row")
    best = alive.join(sizes.select("sha"), "sha", "left_semi").groupBy("sha").agg(F.min(order).alias("m"))
    best = materialise(sizes.join(best, "sha").select("sha", "size", F.col("m.id").alias("keep"), F.col("m.row").alias("stays")), "best")
    grouped = alive.join(best, "sha").select("row", F.col("sha").alias("group_sha"), "size", "keep", "stays")
    out = keyed.join(grouped, "row", "left")
    alone = F.col("size").isNull()
    return out.select(
        "row", "doc_id", "th", F.when(alone, F.col("doc_id")).otherwise(F.col("keep")).alias("keep_id"), F.coalesce("size", F.lit(1)).cast("long").alias("group_size"),
        (alone | (F.col("row") == F.col("stays"))).alias("kept"), F.col("sha" if all_hashes else "group_sha").alias("text_sha256"),
    )


def decisions(docs: DataFrame, all_hashes: bool = True) -> DataFrame:
    """doc_id, keep_id, group_size, kept (one row of each group) and text_sha256 of every row."""
    return decided(docs, all_hashes).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def dedup(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each group of equal texts; all columns kept."""
    return keep_decided(docs, decided(docs, all_hashes=False).where("group_size > 1").select("doc_id", "th", "kept"))
