import json

import pytest
from pyspark.sql import functions as F

from conflate import fixtures as fx
from conflate.operators import features, learn, metrics, procure, resample, standardise
from conflate.queries import places as Q

SHAPES = {
    "Point": [1.5, 2.5],
    "MultiPoint": [[1.0, 2.0], [3.0, 4.0]],
    "LineString": [[1.0, 2.0], [3.0, 4.0], [5.0, 6.0]],
    "MultiLineString": [[[1.0, 2.0], [3.0, 4.0]], [[5.0, 6.0], [7.0, 8.0]]],
    "Polygon": [[[0.0, 0.0], [9.0, 0.0], [9.0, 9.0], [0.0, 0.0]], [[1.0, 1.0], [2.0, 1.0], [2.0, 2.0], [1.0, 1.0]]],
    "MultiPolygon": [[[[0.0, 0.0], [9.0, 0.0], [9.0, 9.0], [0.0, 0.0]], [[1.0, 1.0], [2.0, 1.0], [2.0, 2.0], [1.0, 1.0]]], [[[20.0, 20.0], [21.0, 20.0], [21.0, 21.0], [20.0, 20.0]]]],
}


@pytest.mark.parametrize("kind", SHAPES)
def test_geometry_kinds_both_ways(spark, kind):
    """Several parts and holes survive reading and writing."""
    df = spark.createDataFrame([(json.dumps({"type": kind, "coordinates": SHAPES[kind]}),), ("{",), (None,)], "g string")
    read = df.select(standardise.read_shape(F.col("g")).alias("r"))
    back = [r[0] for r in read.select(F.when(F.col("r.shape").isNotNull(), standardise.shape_json(kind, F.col("r.shape")))).collect()]
    assert json.loads(back[0]) == {"type": kind, "coordinates": SHAPES[kind]} and back[1] is None and back[2] is None


def test_boxes_of_two_sides(spark):
    """Leaves of wide boxes tile the area, hold every point once, and are split down to the shorter side's floor."""
    pts = spark.range(500).select(F.col("id").alias("uid"), (F.col("id") * 7919 % 1600 * 1.0).alias("x"), (F.col("id") * 104729 % 1600 * 1.0).alias("y"))
    leaves = procure.adaptive_boxes(pts, 1600.0, (800.0, 400.0), 12, 100.0).collect()
    assert sum(r.n for r in leaves) == 500 and max(r.level for r in leaves) == 2
    assert sum(800 * 400 / 4**r.level for r in leaves) == 1600 * 1600
    same = procure.adaptive_boxes(pts, 1600.0, (800.0, 800.0), 40, 100.0).collect()
    assert sorted(same) == sorted(procure.adaptive_boxes(pts, 1600.0, 800.0, 40, 100.0).collect())


def test_sources_come_in_their_own_fields(spark, sf_dir):
    raw = fx.poi_raw(spark, sf_dir)
    for role, *_ in fx.ROLES:
        one = raw.where(F.col("src") == role)
        own = standardise.own_names(one, role)
        assert "name" not in own.columns and standardise.OWN_FIELDS[role]["name"] in own.columns
        back = standardise.conform(own, role).select(*raw.columns)
        assert back.exceptAll(one).count() == 0 and back.count() == one.count()


def test_learned_decisions_cover_the_test_pairs(spark, sf_dir):
    """Every test pair is decided once, the same on a second run, and the study area shares no place with training."""
    rows = Q.labelled(spark, sf_dir, "hybrid").cache()
    test = {r["label"]: r["count"] for r in rows.where("not train").groupBy("label").count().collect()}
    for learner, rebalanced in (("bag", False),):
        pred = Q.learned(rows, learner, rebalanced).cache()
        m = metrics.accuracy(pred).collect()[0]
        assert m.tp + m.fn == test[1] and m.tn + m.fp == test[0]
        again = Q.learned(rows, learner, rebalanced)
        assert pred.select("a", "b", "prediction").exceptAll(again.select("a", "b", "prediction")).count() == 0
    p = Q.places(spark, sf_dir)
    assert Q.training_region(p).join(Q.study_area(p), "uid").count() == 0


def test_weighted_tuning(spark, sf_dir):
    rows = Q.labelled(spark, sf_dir, "string")
    best, scores = learn.tune(rows.where("train"), "svm", folds=5, weighted=True)
    assert best in learn.GRIDS["svm"] and len(scores) == 2
