"""Places that change over time: update streams, the latest state, incremental conflation."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from conflate.operators.resample import hash32
from conflate.plans.tables import broadcast_if_small

#: What an event type does to its place.
KINDS = {"signup": "add", "click": "rename", "view": "observe", "purchase": "move", "error": "remove"}
UPDATE = "event_id long, uid string, kind string, update_ts timestamp, arrival_ts timestamp, revision long, shift_m double"


def poi_updates(events: DataFrame, n_places: int, repeats: bool = True) -> DataFrame:
    """Updates from events: target place, kind, event time, arrival up to two hours late; every 25th comes twice."""
    key = F.col("event_id").cast("string")
    kind = F.create_map(*[F.lit(x) for kv in KINDS.items() for x in kv])[F.col("event_type")]
    ts = F.col("ts").cast("timestamp")
    late = F.timestamp_micros(F.unix_micros(ts) + (hash32(F.concat(F.lit("late"), key)) % 7200) * 1_000_000)
    u = events.select("event_id", (F.col("event_id") % n_places).cast("string").alias("uid"), kind.alias("kind"), ts.alias("update_ts"), late.alias("arrival_ts"), F.get_json_object("props", "$.k").cast("long").alias("revision"), (F.col("value") % 30).alias("shift_m"))
    if not repeats:
        return u
    again = F.when(hash32(F.concat(F.lit("re"), key)) % 25 == 0, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))
    return u.withColumn("copy", F.explode(again)).drop("copy")


def visits(events: DataFrame, n_places: int) -> DataFrame:
    """(user_id, ts, place, event_id): each user's places, seven at most."""
    return events.select("user_id", F.col("ts").cast("timestamp").alias("ts"), (hash32(F.concat(F.lit("pl"), F.col("user_id").cast("string"), (F.col("event_id") % 7).cast("string"))) % n_places).alias("place"), "event_id")


def stream(spark: SparkSession, folder: str, schema: str = UPDATE, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def deduplicated(updates: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Each event once, as far as the watermark on arrivals reaches back."""
    return updates.withWatermark("arrival_ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(updates: DataFrame, size: str = "1 hour", slide: str | None = None, delay: str = "2 hours") -> DataFrame:
    """Updates by kind and window of event time."""
    w = F.window("update_ts", size, slide) if slide else F.window("update_ts", size)
    return updates.withWatermark("update_ts", delay).groupBy(w.alias("w"), "kind").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "kind", "n")


def latest_batch(updates: DataFrame) -> DataFrame:
    """The last update of each place by (update_ts, event_id); removed places are gone."""
    w = Window.partitionBy("uid").orderBy(F.desc("update_ts"), F.desc("event_id"))
    return updates.withColumn("k", F.row_number().over(w)).where("k = 1 and kind <> 'remove'").select("uid", "kind", "update_ts", "event_id", "revision")


LATEST = "uid string, kind string, update_ts timestamp, event_id long, revision long"


def latest_stateful(updates: DataFrame) -> DataFrame:
    """The same as a stream with state per place: emits a place's row whenever its latest update changes."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best = state.get if state.exists else None
        new = best
        for f in frames:
            for r in f[["update_ts", "event_id", "kind", "revision"]].itertuples(index=False):
                at = (int(pd.Timestamp(r.update_ts).value), int(r.event_id), str(r.kind), int(r.revision))
                if new is None or at[:2] > tuple(new[:2]):
                    new = at
        if new is not None and new != best:
            state.update(new)
            yield pd.DataFrame({"uid": [key[0]], "kind": [new[2]], "update_ts": [pd.Timestamp(new[0])], "event_id": [new[1]], "revision": [new[3]]})

    return updates.groupBy("uid").applyInPandasWithState(step, LATEST, "at long, event_id long, kind string, revision long", "update", GroupStateTimeout.NoTimeout)


def visits_with_places(visit_stream: DataFrame, places: DataFrame) -> DataFrame:
    """Stream-static join: each visit with its place's row; the places are broadcast only behind a count."""
    return visit_stream.join(broadcast_if_small(places), "place")


def moves_after_visits(updates: DataFrame, visit_stream: DataFrame, within: str = "6 hours") -> DataFrame:
    """Stream-stream interval join: updates of a place within some hours of a visit to it."""
    u = updates.withWatermark("update_ts", "2 hours").select(F.col("uid").cast("long").alias("place"), "update_ts", F.col("event_id").alias("update_id"))
    v = visit_stream.withWatermark("ts", "2 hours").select(F.col("place").alias("vplace"), "ts", F.col("event_id").alias("visit_id"))
    return u.join(v, F.expr(f"place = vplace and update_ts >= ts and update_ts <= ts + interval {within}")).select("place", "visit_id", "update_id")


def incremental(apply: Callable[[DataFrame, DataFrame], DataFrame], load: Callable[[], DataFrame], store: Callable[[DataFrame], None]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch handler: upserts a batch of changed places and rebuilds only the clusters it touches.

    load() gives the current places with their poi_id and tile; ``apply(all_rows, touched_tiles)`` re-matches the
    places of the touched tiles and their halo; store() replaces the state.
    """

    def handle(batch: DataFrame, batch_id: int) -> None:
        if batch.isEmpty():
            return
        state = load()
        changed = batch.select("uid").distinct()
        rows = state.join(changed, "uid", "left_anti").unionByName(batch, allowMissingColumns=True)
        touched = state.join(changed, "uid", "left_semi").select("tile").union(batch.select("tile")).distinct()
        store(apply(rows, touched))

    return handle
