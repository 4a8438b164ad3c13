import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from conflate import fixtures as fx
from conflate.functions import domain, geo
from conflate.functions.similarity import clean, edit_similarity, token_sort
from conflate.operators import candidates, cluster, features, kernel, learn, metrics, procure, resample, taxonomy, tfidf, unify, verify, wsa
from conflate.plans import graph


def place(uid, src, lat=1.31, lon=103.92, name="a", address="1 x", rank=1, types=("t",), tags=(), date="2021-07-01", flag=False, bounds=None):
    return uid, src, rank, lat, lon, name, address, list(types), list(tags), bounds, date, flag


SCHEMA = "uid string, src string, rank int, lat double, lon double, name string, address string, place_type array<string>, tags array<string>, bounds struct<south:double,west:double,north:double,east:double>, d string, requires_verification boolean"


def frame(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).withColumn("extraction_date", F.to_date("d"))


def metres(m):
    return math.degrees(m / geo.EARTH_M)


def test_fixture_counts(spark, sf_dir):
    assert fx.poi_raw(spark, sf_dir).count() == 281
    assert candidates.within_radius(fx.poi_raw(spark, sf_dir), ordered=False).count() == 1695


def test_radius_edges(spark):
    rows = [place("a", "s1", 0.0, 10.0), place("b", "s2", metres(99.9), 10.0), place("c", "s2", metres(100.1), 10.0), place("d", "s2", 0.0, 10.0), place("e", "s1", 0.0, 10.0), place("n", "s2", None, None)]
    got = {(r.c, r.m) for r in candidates.within_radius(frame(spark, rows)).collect()}
    assert ("a", "b") in got and ("b", "a") in got and ("a", "d") in got
    assert ("a", "c") not in got and ("a", "e") not in got and all(c != m for c, m in got)


@pytest.mark.parametrize("lat", [0.0, 45.0, -60.0, 75.0])
def test_grid_equals_brute_at_latitudes(spark, lat):
    rng = np.random.default_rng(3)
    scale = 1 / max(0.1, math.cos(math.radians(lat)))
    rows = [place(f"u{i}", f"s{i % 3}", lat + metres(float(y)), 20 + metres(float(x)) * scale) for i, (x, y) in enumerate(rng.uniform(-400, 400, (120, 2)))]
    df = frame(spark, rows)
    want = {(r.c, r.m) for r in candidates.brute(df).collect()}
    assert {(r.c, r.m) for r in candidates.within_radius(df).collect()} == want
    assert {(r.c, r.m) for r in candidates.tile_pairs(df, 300.0).collect()} == want


def test_no_nested_loop_and_pushed_filters(spark, sf_dir, tmp_path):
    fx.poi_raw(spark, sf_dir).write.parquet(str(tmp_path / "p"))
    p = spark.read.parquet(str(tmp_path / "p"))
    plan = candidates.within_radius(p)._jdf.queryExecution().toString()
    assert "NestedLoop" not in plan.split("== Physical Plan ==")[1] and "Cartesian" not in plan
    plan = procure.in_box(p, (1.311, 103.924, 1.32, 103.935)).select("uid")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(lat)" in plan and "name" not in plan.split("ReadSchema")[1]


def test_text_similarity(spark):
    rows = [("b A c", "c b a"), ("Große-Straße", "straße große"), ("", "x"), (None, "x"), ("!!", "")]
    got = spark.createDataFrame(rows, "a string, b string").select(token_sort(F.col("a")).alias("x"), token_sort(F.col("b")).alias("y")).select(edit_similarity(F.col("x"), F.col("y")).alias("s")).collect()
    assert [r.s for r in got] == [1.0, 1.0, 0.0, 0.0, 1.0]


def _lcs(a, b):
    t = np.zeros((len(a) + 1, len(b) + 1), int)
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            t[i + 1, j + 1] = t[i, j] + 1 if x == y else max(t[i, j + 1], t[i + 1, j])
    return int(t[-1, -1])


def test_three_metrics(spark):
    rows = [("kitten", "sitting"), ("abc", "abd"), ("", "")]
    df = spark.createDataFrame(rows, "a string, b string")
    got = df.select(*[edit_similarity(F.col("a"), F.col("b"), m).alias(m) for m in ("lev_max", "lev_sum", "indel")]).collect()
    for (a, b), r in zip(rows, got):
        assert r.indel == pytest.approx(2 * _lcs(a, b) / (len(a) + len(b)) if a else 1.0)
        assert r.lev_sum >= r.lev_max


def _reference_local(docs, pairs):
    near = {}
    for c, m in pairs:
        near.setdefault(c, []).append(m)
    out = {}
    for c, ms in near.items():
        members = [x for x in (c, *ms) if docs.get(x)]
        tf = {x: {k: v / len(docs[x]) for k, v in Counter(docs[x]).items()} for x in members}
        df = Counter(k for x in members for k in tf[x])
        w = {x: {k: v * math.log(len(members) / df[k]) for k, v in tf[x].items()} for x in members}
        for m in ms:
            if c in w and m in w:
                dot = sum(v * w[c].get(k, 0) for k, v in w[m].items())
                norm = math.sqrt(sum(v * v for v in w[c].values())) * math.sqrt(sum(v * v for v in w[m].values()))
                out[c, m] = dot / norm if norm else 0.0
            else:
                out[c, m] = 0.0
    return out


def test_local_tfidf_by_hand(spark):
    docs = {"a": "12 oak road".split(), "b": "12 oak road".split(), "c": "14 oak road".split(), "d": None, "e": "same words".split(), "f": "same words".split()}
    pairs = [("a", "b"), ("a", "c"), ("a", "d"), ("b", "a"), ("e", "f"), ("d", "a")]
    df = spark.createDataFrame([(k, " ".join(v) if v else None) for k, v in docs.items()], "uid string, text string")
    got = {(r.c, r.m): r.score for r in tfidf.local_sim(spark.createDataFrame(pairs, "c string, m string"), df).collect()}
    want = _reference_local(docs, pairs)
    assert got.keys() == want.keys()
    assert all(got[k] == pytest.approx(want[k]) for k in want)
    assert got["e", "f"] == 0.0 and got["a", "b"] == pytest.approx(1.0)  # every term universal; equal and told apart


def test_kernel_equals_frames(spark, sf_dir):
    p = fx.poi_raw(spark, sf_dir)
    a = {tuple(r) for r in features.build(p, candidates.within_radius(p)).select("c", "m", "s_name", "s_addr").collect()}
    b = {tuple(r) for r in kernel.score_tiles(p, 400.0).select("c", "m", "s_name", "s_addr").collect()}
    assert a == b


def test_weighted_sum(spark):
    rows = [(0.85, 0.0, 1), (0.8501, 0.0, 1), (1.0, 1.0, 0), (0.2, 0.9, 0)]
    df = spark.createDataFrame(rows, "s_name double, s_addr double, label int")
    assert [r.prediction for r in wsa.decide(df, 0.85, 1.0, 0.0).collect()] == [0, 1, 1, 0]  # strictly above
    g = wsa.grid(df).collect()
    assert len(g) == 441 and all(r.tp + r.tn + r.fp + r.fn == 4 for r in g)
    assert len(wsa.grid(df, 4, simplex=False).collect()) == 15 * 5
    assert wsa.best(wsa.grid(df)).count() == 1


def test_measures(spark):
    df = spark.createDataFrame([(1, 1)] * 49 + [(1, 0)] + [(0, 0)] * 2066 + [(0, 1)] * 59, "label int, prediction int")
    r = metrics.accuracy(df).collect()[0]
    assert r.balanced == pytest.approx((49 / 50 + 2066 / 2125) / 2, abs=1e-6) and r.balanced_literal == r.overall
    assert metrics.accuracy(spark.createDataFrame([(0, 0)], "label int, prediction int")).collect()[0].balanced is None


def labelled(spark, n1=12, n0=60):
    rng = np.random.default_rng(1)
    rows = [(f"a{i}", f"b{i}", float(rng.normal(0.9, 0.1)), float(rng.normal(0.8, 0.2)), 1) for i in range(n1)] + [(f"c{i}", f"d{i}", float(rng.normal(0.3, 0.15)), float(rng.normal(0.4, 0.2)), 0) for i in range(n0)]
    return spark.createDataFrame(rows, "a string, b string, s_name double, s_addr double, label int")


def test_split_and_folds(spark):
    df = labelled(spark)
    s = resample.split(df)
    assert {(r.label, r.n) for r in s.where("train").groupBy("label").agg(F.count("*").alias("n")).collect()} == {(1, 9), (0, 45)}
    assert {tuple(r) for r in s.repartition(7).select("a", "train").collect()} == {tuple(r) for r in resample.split(df.repartition(3)).select("a", "train").collect()}
    bags = resample.balanced_sets(s.where("train").drop("train"), 2)
    assert {r.n for r in bags.groupBy("bag_id", "label").agg(F.count("*").alias("n")).collect()} == {20}
    major = bags.where("label = 0 and bag_id = 0")
    assert major.select("a").distinct().count() == major.count()
    folded = resample.folds(bags.where("bag_id = 0"), 3)
    assert folded.groupBy("a").agg(F.count_distinct("fold").alias("n")).where("n > 1").count() == 0
    with pytest.raises(ValueError):
        resample.balanced_sets(df.where("label = 0"), 2)


def test_class_weights_sum_to_rows(spark):
    w = resample.class_weights(labelled(spark)).collect()
    assert sum(r.n * r.weight for r in w) == pytest.approx(72, abs=1e-3)


@pytest.mark.parametrize("learner", ["gb", "bag", "rf", "svm"])
def test_learners(spark, learner):
    df = labelled(spark)
    model = learn.fit_rebalanced(df, learner, 2, grid=learn.GRIDS[learner][:1])
    pred = model.predict(df).toPandas()
    assert pred.prob.between(0, 1).all()
    assert learn.balanced_of(spark.createDataFrame(pred[["label", "prob"]])) > 0.8


def test_tuning_picks_a_grid_point(spark):
    best, scores = learn.tune(labelled(spark), "bag", folds=3)
    assert best in learn.GRIDS["bag"] and len(scores) == 2 and all(0 <= s <= 1 for _, s in scores)


def test_reference_booster_lowers_loss():
    rng = np.random.default_rng(0)
    x = rng.uniform(size=(200, 2))
    losses, predict = learn.gb_reference(x, (x.sum(1) > 1).astype(float), 8)
    assert all(b <= a + 1e-9 for a, b in zip(losses, losses[1:])) and ((predict(x) > 0.5) == (x.sum(1) > 1)).mean() > 0.9


def test_components(spark):
    edges = [(i, i + 1) for i in range(200)] + [(500, 501), (501, 502), (900, 901), (901, 900), (7, 7)] + [(1000, i) for i in range(1001, 1300)]
    got = {r.v: r.root for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(201)) and got[502] == 500 and got[901] == 900 and all(got[i] == 1000 for i in range(1001, 1300)) and 7 in got
    assert graph.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_unify_rules(spark):
    box = (0.0, 0.0, 1.0, 1.0), (0.0, 0.0, 2.0, 2.0)
    rows = [
        place("1", "authority_map", 1.0, 1.0, None, "short", 1, ["x"], ["t"], "2021-07-02", False, box[0]), place("2", "authority_map", 3.0, 3.0, None, None, 1, ["y"], [], "2021-07-01", True, None),
        place("3", "open_map", 9.0, 9.0, "name of last", "a longer address", 5, ["x"], ["t", "u"], "2021-08-01", False, box[1]), place("4", "open_map", types=[], tags=[]),
    ]
    p = frame(spark, rows)
    c = spark.createDataFrame([("1", "1"), ("2", "1"), ("3", "1"), ("4", "4")], "uid string, poi_id string")
    u = {r.poi_id: r for r in unify.merge(p, c).collect()}
    assert (u["1"].lat, u["1"].lon) == (2.0, 2.0) and u["1"].name == "name of last" and u["1"].address == "short"
    assert u["1"].place_type == ["x", "y"] and u["1"].tags == ["t", "u"] and str(u["1"].extraction_date) == "2021-08-01" and u["1"].requires_verification
    assert u["1"].bounds.north == 2.0 and u["4"].requires_verification and u["4"].bounds is None
    strict = {r.poi_id: r for r in unify.merge(p, c, fallback=False, bounds="envelope").collect()}
    assert strict["1"].name is None and strict["1"].bounds.east == 2.0


def test_chain_groupings(spark):
    links = spark.createDataFrame([("a", "b", 0.9), ("b", "c", 0.8)], "a string, b string, prob double")
    v = frame(spark, [place("a", "s1", rank=1), place("b", "s2", rank=2), place("c", "s3", rank=3), place("z", "s1", rank=1)])
    assert {r.uid: r.poi_id for r in cluster.components(v, links).collect()} == {"a": "a", "b": "a", "c": "a", "z": "z"}
    assert {r.uid: r.poi_id for r in cluster.mutual_best(v, links).collect()} == {"a": "a", "b": "a", "c": "c", "z": "z"}
    assert {r.uid: r.poi_id for r in cluster.star(v, links).collect()} == {"a": "a", "b": "a", "c": "a", "z": "z"}


def test_adaptive_boxes_tile_the_base(spark):
    rng = np.random.default_rng(5)
    pts = spark.createDataFrame([(f"u{i}", float(x), float(y)) for i, (x, y) in enumerate(np.vstack([rng.uniform(0, 1600, (300, 2)), rng.normal(400, 8, (90, 2))]))], "uid string, x double, y double")
    one = procure.adaptive_boxes(pts, 1600.0, 800.0, 20, 25.0)
    a = {tuple(r) for r in one.collect()}
    assert a == {tuple(r) for r in procure.adaptive_boxes(pts, 1600.0, 800.0, 20, 25.0, mode="levels").collect()}
    assert sum((800 / 2**r[0]) ** 2 for r in a) == 1600.0**2 and sum(r[3] for r in a) == 390
    assert all(r[3] < 20 or r[0] == 5 for r in a) and any(r[4] for r in a)  # the cluster is denser than the cap at the floor
    kept = procure.capped_query(pts, one, 800.0, 20, 20)
    assert kept.count() == sum(min(20, r[3]) for r in a)


def test_polygon_and_box(spark):
    octagon = procure.octagon(10.0)
    df = spark.createDataFrame([(5.0, 5.0), (0.1, 0.1), (9.9, 5.0)], "x double, y double")
    assert [r.p for r in df.select(geo.point_in_polygon(F.col("x"), F.col("y"), octagon).alias("p")).collect()] == [True, False, True]
    boxes = spark.createDataFrame([(0.0, 0.0, 1.0, 1.0), (1.0, 1.0, 2.0, 2.0), (-5.0, -5.0, 20.0, 20.0), (10.0, 4.0, 11.0, 5.0)], "west double, south double, east double, north double")
    assert [(r.west, r.south) for r in procure.touching(boxes, octagon).collect()] == [(1.0, 1.0), (-5.0, -5.0), (10.0, 4.0)]


def test_taxonomy_threshold(spark):
    terms = spark.createDataFrame([("small",), ("ring",)], "term string")
    labels = spark.createDataFrame([("small",), ("smalls",), ("SMALL ring",), ("zebra",)], "label string")
    words = labels.select(F.explode(taxonomy.components(F.col("label"))).alias("term")).union(terms).distinct()
    vectors = taxonomy.ngram_vectors(words)
    got = {(r.label, r.term) for r in taxonomy.map_labels(labels, terms, vectors).collect()}
    assert got == {("small", "small"), ("SMALL ring", "small"), ("SMALL ring", "ring")}
    loose = {(r.label, r.term) for r in taxonomy.map_labels(labels, terms, vectors, 0.4).collect()}
    assert got <= loose and ("smalls", "small") in loose


def test_lsh_recall(spark, sf_dir):
    from conflate.queries.places import synonyms

    labels, terms = synonyms(spark, sf_dir)
    got = {(r.label, r.term) for r in taxonomy.lsh_map(labels, terms).collect()}
    assert len(got & {(f"syn{i}", f"term{i}") for i in range(20)}) >= 18 and not any(a.startswith("near") for a, _ in got)


def test_skipgram(spark):
    docs = spark.createDataFrame([("the small ring and the small gear",)] * 30, "text string")
    v = {r.term: r.vec for r in taxonomy.skipgram_vectors(docs, dim=8).collect()}
    assert "small" in v and "smal*" in v and len(v["ring"]) == 8


def test_missing_place_type_is_queued(spark):
    df = spark.createDataFrame([("1", [], True), ("2", ["odd"], False), ("3", ["ok"], True)], "poi_id string, place_type array<string>, mapped boolean")
    r = verify.reasons(df)
    assert {x.poi_id: x.verify_reasons for x in r.collect()} == {"1": [verify.UNTYPED], "2": [verify.UNMAPPED], "3": []}
    fixed = verify.apply_overrides(r, spark.createDataFrame([("odd", ["even"])], "label string, types array<string>"))
    assert {x.poi_id: (x.place_type, x.requires_verification) for x in fixed.collect()} == {"1": ([], True), "2": (["even"], False), "3": (["ok"], False)}


def test_sql_functions(spark):
    domain.register(spark)
    r = spark.sql("SELECT geo_distance_m(0D, 0D, 0D, 1D) AS d, name_similarity('ab', 'ac') AS s, vec_cosine(array(1D, 0D), array(1D, 0D)) AS c").collect()[0]
    assert r.d == pytest.approx(111194.93, abs=0.1) and r.s == 0.5 and r.c == 1.0
    assert spark.sql("SELECT * FROM ngrams('ab', 3, 4)").count() == 3
    assert spark.sql("SELECT * FROM split_box(0, 1, 1)").count() == 4


def test_conservative_bounds_twin(spark):
    df = spark.createDataFrame([([0.0, 0.0], [0.0, 0.0], [1.0, 2.0], [1.0, 2.0])], "s array<double>, w array<double>, n array<double>, e array<double>")
    assert df.select(unify.most_conservative_bounds("s", "w", "n", "e").alias("b")).collect()[0].b.north == 2.0


def test_clean_keeps_letters(spark):
    assert spark.createDataFrame([("Café--N° 5",)], "x string").select(clean(F.col("x")).alias("y")).collect()[0].y == "café n 5"
    assert unify.RANKS["authority_map"] == 1
