import json

import pytest
from pyspark.sql import functions as F

from conflate import fixtures as fx
from conflate.operators import standardise
from conflate.sources import io, paged
from conflate.streaming import updates


def test_formats_round_trip(spark, sf_dir, tmp_path):
    p = fx.poi_raw(spark, sf_dir).select("uid", "src", "lat", "lon", "name")
    want = sorted(map(tuple, p.collect()))
    p.write.option("header", True).csv(str(tmp_path / "csv"))
    p.write.json(str(tmp_path / "json"))
    p.write.orc(str(tmp_path / "orc"))
    schema = "uid string, src string, lat double, lon double, name string"
    assert sorted(map(tuple, io.read_csv(spark, str(tmp_path / "csv"), schema).collect())) == want
    assert sorted(map(tuple, io.read_json(spark, str(tmp_path / "json"), schema).collect())) == want
    assert sorted(map(tuple, io.read_orc(spark, str(tmp_path / "orc")).collect())) == want
    io.write_unified(p, str(tmp_path / "tiles"))
    back = spark.read.parquet(str(tmp_path / "tiles"))
    assert back.count() == len(want) and "tile" in back.columns
    feats = standardise.to_geojson(standardise.standard(fx.poi_raw(spark, sf_dir)))
    io.write_geojson(feats, str(tmp_path / "geojson"))
    assert io.read_lines(spark, str(tmp_path / "geojson")).count() == len(want)
    io.timed_sink(p)


def test_broken_json_line(spark, tmp_path):
    (tmp_path / "x.json").write_text('{"uid": "1"}\n{broken\n')
    rows = io.read_json(spark, str(tmp_path / "x.json"), "uid string, _corrupt_record string").collect()
    assert {(r.uid, r._corrupt_record) for r in rows} == {("1", None), (None, "{broken")}


def test_geometry_kinds(spark):
    df = spark.createDataFrame([([(1.0, 2.0), (3.0, 4.0), (1.0, 2.0)],)], "p array<struct<lat:double,lon:double>>")
    for kind in standardise.GEOMETRIES:
        g = json.loads(df.select(standardise.geometry_json(kind, F.col("p")).alias("g")).collect()[0].g)
        assert g["type"] == kind and str(g["coordinates"]).count("2.0") >= 1
    assert json.loads(df.select(standardise.geometry_json("Point", F.col("p")).alias("g")).collect()[0].g)["coordinates"] == [2.0, 1.0]


def test_paged_source(spark, tmp_path):
    for box, n in (("0_0_0", 45), ("0_1_0", 0), ("0_0_1", 70)):
        (tmp_path / f"{box}.json").write_text("\n".join(json.dumps({"uid": f"{box}-{i:03d}", "lat": 1.0, "lon": 2.0}) for i in range(n)))
    paged.register(spark)
    df = spark.read.format("paged_places").option("path", str(tmp_path)).option("key", "k").load()
    assert {(r.box, r.n, r.pages) for r in df.groupBy("box").agg(F.count("*").alias("n"), F.max("page_no").alias("pages")).collect()} == {("0_0_0", 45, 3), ("0_0_1", 60, 3)}


def batches(spark, sf_dir, tmp_path):
    u = updates.poi_updates(spark.read.parquet(f"{sf_dir}/events.parquet"), 50)
    u.orderBy("arrival_ts").repartitionByRange(4, "arrival_ts").write.parquet(str(tmp_path / "u"))
    return spark.read.parquet(str(tmp_path / "u")), updates.stream(spark, str(tmp_path / "u"), files_per_trigger=4)


def drain(df, name, mode="append", tmp=None):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(180)
    assert q.exception() is None
    return df.sparkSession.table(name)


def test_repeats_are_dropped(spark, sf_dir, tmp_path):
    static, live = batches(spark, sf_dir, tmp_path)
    assert static.count() > 1000
    got = drain(updates.deduplicated(live), "dedup_updates")
    assert got.count() == 1000 == got.select("event_id").distinct().count()


def test_latest_state_equals_batch(spark, sf_dir, tmp_path):
    static, live = batches(spark, sf_dir, tmp_path)
    got = drain(updates.latest_stateful(live), "latest_updates", "update")
    last = updates.latest_batch(got.select("uid", "kind", "update_ts", "event_id", "revision"))
    assert {tuple(r) for r in last.collect()} == {tuple(r) for r in updates.latest_batch(static).collect()}


def test_windows_equal_batch(spark, sf_dir, tmp_path):
    static, live = batches(spark, sf_dir, tmp_path)
    got = drain(updates.windowed_counts(live), "windows_updates", "update").groupBy("start", "kind").agg(F.max("n").alias("n"))
    want = static.groupBy(F.window("update_ts", "1 hour").alias("w"), "kind").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "kind", "n")
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}


def test_joins_of_streams(spark, sf_dir, tmp_path):
    static, live = batches(spark, sf_dir, tmp_path)
    v = updates.visits(spark.read.parquet(f"{sf_dir}/events.parquet"), 50)
    v.write.parquet(str(tmp_path / "v"))
    vs = spark.readStream.schema(v.schema).parquet(str(tmp_path / "v"))
    names = spark.createDataFrame([(i, f"n{i}") for i in range(50)], "place long, name string")
    assert drain(updates.visits_with_places(vs, names), "visits_named").count() == 1000
    got = drain(updates.moves_after_visits(live, vs), "moves")
    want = static.select(F.col("uid").cast("long").alias("place"), "update_ts", F.col("event_id").alias("update_id")).join(v.select("place", "ts", F.col("event_id").alias("visit_id")), "place").where("update_ts >= ts and update_ts <= ts + interval 6 hours").select("place", "visit_id", "update_id")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_incremental_handler(spark):
    box = {"state": spark.createDataFrame([("a", "t1", 1), ("b", "t2", 1)], "uid string, tile string, v int")}
    seen = []

    def apply(rows, touched):
        seen.append({r.tile for r in touched.collect()})
        return rows

    def store(df):
        box["state"] = spark.createDataFrame(df.collect(), df.schema)

    handle = updates.incremental(apply, lambda: box["state"], store)
    handle(spark.createDataFrame([("a", "t3", 2), ("c", "t1", 1)], "uid string, tile string, v int"), 0)
    handle(spark.createDataFrame([], "uid string, tile string, v int"), 1)
    assert {tuple(r) for r in box["state"].collect()} == {("a", "t3", 2), ("b", "t2", 1), ("c", "t1", 1)} and seen == [{"t1", "t3"}]


def test_shared_folder_is_read_from_the_session(spark):
    from conflate.plans import tables

    assert tables.shared_folder(spark) == spark.conf.get("spark.checkpoint.dir").rstrip("/")
    df = tables.materialise(spark.range(5).toDF("a"), "t")
    assert df.count() == 5
    tables.discard(df)
    with pytest.raises(Exception):
        spark.read.parquet(df._conflate_path).count()
