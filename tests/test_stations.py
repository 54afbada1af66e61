import random

import pytest
from conftest import SMALL
from pyspark.sql import functions as F

from stationlink.functions import geo
from stationlink.operators import evaluate, groundtruth, spicing
from stationlink.operators.components import components
from stationlink.plans import experiments, relational


@pytest.fixture(scope="module")
def judged(spark):
    return experiments.pairs(spark, SMALL, 0).persist()


def test_counts_of_the_station_fixture(judged):
    got = {r.truth: r["count"] for r in judged.groupBy("truth").count().collect()}
    assert got == {0: 673, 1: 528, None: 716}


def test_counts_of_the_page_fixture(spark):
    got = {r.truth: r["count"] for r in experiments.pairs(spark, SMALL, 0, "PG").groupBy("truth").count().collect()}
    assert got == {0: 59, 1: 52, None: 90}


def test_radius_pairs_equal_a_nested_loop(spark):
    r = random.Random(3)
    places = [(47 + r.random() * 0.05, 8 + r.random() * 0.05) for _ in range(80)] + [(10.0, 179.9995), (10.0, -179.9995), (89.9999, 0.0), (89.9999, 180.0), (-90.0, 5.0), (-89.9999, 90.0)]
    df = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(places)], "ident_id long, lat double, lon double")
    got = {(x.a_ident_id, x.b_ident_id) for x in groundtruth.radius_pairs(df, 700.0, ("lat", "lon")).collect()}
    a, b = df.toDF("i", "p", "q"), df.toDF("j", "s", "t")
    want = {(x.i, x.j) for x in a.crossJoin(b).where("i < j").where(geo.haversine_m(F.col("p"), F.col("q"), F.col("s"), F.col("t")) <= 700).collect()}
    assert got == want and (80, 81) in got and (82, 83) in got


def test_spiced_labels_are_near_and_not_similar(spark):
    rows = spicing.foreign_labels(experiments.idents(spark, SMALL)).collect()
    assert rows and all(r.dist_m <= 100.5 and r.truth == 0 for r in rows)


def test_sweep_equals_a_recount(judged):
    curve = {r.t: r for r in evaluate.sweep(judged, "dist_m", (10, 50, 100, 400), below=True).collect()}
    for t, r in curve.items():
        again = evaluate.confusion(judged.withColumn("predicted", (F.col("dist_m") < t).cast("int"))).first()
        assert (r.tp, r.fp, r.fn, r.tn) == (again.tp, again.fp, again.fn, again.tn)


def test_no_positives_give_null_recall_and_no_f1(spark):
    df = spark.createDataFrame([(0, 0), (0, 0)], "truth int, predicted int")
    r = evaluate.confusion(df).first()
    assert (r.tp, r.tn, r.rec, r.prec, r.f1) == (0, 2, None, None, 0)


def test_spicing_hurts_distance_and_combination_helps(spark):
    best = {r.part: r.f1 for r in experiments.e_spice_sweep(spark, SMALL).collect()}
    combo = {r.method: r.f1 for r in experiments.e_combo_table(spark, SMALL).collect()}
    assert best["both"] < best["plain"] and combo["P+TFIDF"] > best["both"]


def test_components_equal_union_find(spark):
    r = random.Random(8)
    edges = [(r.randrange(300), r.randrange(300)) for _ in range(180)] + [(k, k + 1) for k in range(400, 440)] + [(7, 7)]
    parent = {}

    def top(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        p, q = top(a), top(b)
        parent[max(p, q)] = min(p, q)
    got = {x.node: x.root for x in components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert got == {x: top(x) for x in parent}


def test_flat_forest_equals_the_library(spark, judged, tmp_path):
    from pyspark.ml.linalg import SparseVector, VectorUDT

    from stationlink.operators.features import vectors
    from stationlink.operators.forest import RandomForestMatcher

    matcher = RandomForestMatcher(trees=4, k=30, max_depth=6).fit(judged)
    scores = lambda m, **kw: {r.pair_id: r.score for r in m.transform(judged, **kw).select("pair_id", "score").collect()}
    matcher.save(spark, str(tmp_path / "forest"))
    assert scores(RandomForestMatcher.load(spark, str(tmp_path / "forest"))) == scores(matcher)
    turned = judged.select(*[F.col(("b" if c[0] == "a" else "a") + c[1:]).alias(c) if c[:2] in ("a_", "b_") else F.col(c) for c in judged.columns])
    there, back = scores(matcher, symmetric=True), {r.pair_id: r.score for r in matcher.transform(turned, symmetric=True).select("pair_id", "score").collect()}
    assert max(abs(there[k] - back[k]) for k in there) < 1e-12
    width = matcher.width
    to_vector = F.udf(lambda i, v: SparseVector(width, i, v), VectorUDT())
    rows = vectors(judged, matcher.dictionary, 2)
    want = {r.pair_id: float(r.probability[1]) for r in matcher.model.transform(rows.select("pair_id", to_vector("index", "value").alias("features"))).collect()}
    got = {r.pair_id: r.score for r in matcher.transform(judged).collect()}
    assert got.keys() == want.keys() and max(abs(got[k] - want[k]) for k in got) < 1e-9
    assert evaluate.confusion(matcher.transform(judged)).first().f1 > 0.9


def test_feeds_keep_broken_rows_apart(spark, tmp_path):
    from stationlink.sources.tables import read_feed

    (tmp_path / "feed.csv").write_text("node_id,area_id,group_id,label,lat,lon\n1,2,,Tor,47.0,8.0\nx,y,,Oops,1,2\n")
    rows = read_feed(spark, str(tmp_path / "feed.csv")).collect()
    assert [r.broken is None for r in rows] == [True, False] and rows[0].label == "Tor"


def test_plans_have_no_cartesian_product(spark):
    plan = experiments.pairs(spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_forest_beats_every_baseline(spark):
    from stationlink.operators.matcher import StationMatcher

    rows = experiments.forest_pairs(spark, "/root/testdata/sf0.01")
    train, test = rows.where("train0"), rows.where("not train0")
    f1 = {m: evaluate.confusion(StationMatcher(m, **kw).fit(train).transform(test)).first().f1 for m, kw in (("RF", {"trees": 20, "k": 200, "max_depth": 15}), ("P", {}), ("P+TFIDF", {}), ("P+BTS", {}))}
    assert f1["RF"] > 0.95 and f1["RF"] > max(f1[m] for m in ("P", "P+TFIDF", "P+BTS"))


def test_exact_combination_sweep_equals_brute_force(spark):
    r = random.Random(3)
    rows = [(r.randint(0, 1), r.random() * 300, r.choice([0.0, 0.5, 0.55, 0.5503, 1.0, r.random()]), [r.random() for _ in range(3)], r.randrange(8)) for _ in range(300)]
    df = spark.createDataFrame(rows, "truth int, dist_m double, a double, b array<double>, test int")
    got = evaluate.combination_curves(df, {"A": "a", "B": "b"}, repeats=3, d_grid=(10, 60, 200), t_grid=(0.05, 0.55, 0.99)).collect()
    assert len(got) == 2 * 3 * 3 * 3

    def rescale(s, t):
        return s / (2 * t) if s <= t else 0.5 + (s - t) / (2 * (1 - t))

    for g in got:
        own = [(y, d, a if g.method == "A" else b[g.repeat]) for y, d, a, b, m in rows if m >> g.repeat & 1]
        hit = [(y, (2 ** (-d / g.d_hat) + rescale(s, g.t)) / 2 > 0.5) for y, d, s in own]
        assert (g.tp, g.fp, g.fn, g.tn) == tuple(sum(x == w for x in hit) for w in ((1, True), (0, True), (1, False), (0, False)))
    single = evaluate.curves(df, {"A": "a", "B": "b"}, repeats=3).collect()
    for g in single:
        own = [(y, d if g.method == "P" else a if g.method == "A" else b[g.repeat]) for y, d, a, b, m in rows if m >> g.repeat & 1]
        assert g.tp == sum(y == 1 and (s < g.t if g.method == "P" else s > g.t) for y, s in own)


def test_foreign_labels_need_no_town_and_lie_outside_the_radius(spark):
    idents = experiments.idents(spark, SMALL)
    bare = spicing.foreign_labels(idents.drop("town"), outside_m=5000.0)
    own = {r.ident_id: (r.lat, r.lon) for r in idents.collect()}
    from math import asin, cos, radians, sin, sqrt

    def metres(a, b):
        (p, q), (x, y) = (map(radians, z) for z in (a, b))
        return 2 * 6371008.8 * asin(sqrt(sin((x - p) / 2) ** 2 + cos(p) * cos(x) * sin((y - q) / 2) ** 2))

    rows = bare.select("a_ident_id", "b_ident_id", "dist_m").collect()
    assert rows and all(metres(own[r.a_ident_id], own[r.b_ident_id]) > 5000 and r.dist_m <= 101 for r in rows)
    each = {}
    for r in rows:
        each.setdefault(r.a_ident_id, []).append(r.b_ident_id)
    assert all(len(x) == len(set(x)) == 5 for x in each.values())


def test_late_rows_of_closed_hours_are_left_out(spark):
    from stationlink.streaming import arrivals

    row = "event_id long, event_type string, ts timestamp"
    at = lambda k, hour, minute: (k, "x", __import__("datetime").datetime(2024, 1, 1, hour, minute))
    first = spark.createDataFrame([at(1, 8, 10), at(2, 10, 20), at(3, 12, 30)], row)
    second = spark.createDataFrame([at(4, 8, 40), at(5, 11, 50), at(6, 20, 0)], row)  # 8:40 is late, 11:50 is not
    got = arrivals.drain_parts([first, second], lambda s: arrivals.tumbling(s, late="1 hour")).collect()
    assert sorted((r.start.hour, r.n) for r in got) == [(8, 1), (10, 1), (11, 1), (12, 1)]


def test_median_has_the_least_sum_of_distances(spark):
    import numpy as np

    from stationlink.sources import fixtures

    found = {r.area_id: r for r in relational.u_median(spark, SMALL).collect()}
    nodes = fixtures.station_nodes(spark, SMALL).where("area_id is not null").toPandas()
    for area, part in nodes.groupby("area_id"):
        x, r = part[["lat", "lon"]].to_numpy(), found[area]
        stretch = np.array([1, np.cos(np.radians(x[0, 0]))])
        cost = lambda p: np.linalg.norm((x - p) * stretch, axis=1).sum()
        around = [cost((r.lat + i * 1e-4, r.lon + j * 1e-4)) for i in (-1, 0, 1) for j in (-1, 0, 1)]
        assert r.n == len(part) and cost((r.lat, r.lon)) <= min(around) + 1e-5 * len(part)


def test_order_of_shared_tokens(spark):
    from stationlink.operators import features

    rows = spark.createDataFrame([("Main Street 5", "Street Main"), ("Main Street", "Old Main Street"), ("", "x"), (None, "x")], "a string, b string")
    assert [r[0] for r in rows.select(features.order_differs("a", "b")).collect()] == [1, 0, 0, None]


def test_spelling_errors_are_one_edit(spark, judged):
    got = spicing.misspelled(judged, 0.5).select("pair_id", F.col("b_label").alias("c")).join(judged, "pair_id").select(F.levenshtein("b_label", "c").alias("e")).groupBy("e").count().collect()
    n = {r.e: r["count"] for r in got}
    assert set(n) == {0, 1} and 0.4 < n[1] / (n[0] + n[1]) < 0.55


def test_forest_with_the_order_feature_is_saved_and_read(spark, judged, tmp_path):
    from stationlink.operators.forest import RandomForestMatcher

    rows = judged.where("truth is not null")
    forest = RandomForestMatcher(trees=5, k=20, max_depth=6, order=True).fit(rows)
    forest.save(spark, str(tmp_path / "f"))
    again = RandomForestMatcher.load(spark, str(tmp_path / "f"))
    score = lambda m: {r.pair_id: r.score for r in m.transform(rows).select("pair_id", "score").collect()}
    assert forest.width == again.width == 7 + 20 and score(forest) == score(again)


def test_pairs_are_of_one_town_where_towns_lie_at_one_place(spark, tmp_path):
    import duckdb

    spark.read.parquet(f"{SMALL}/nation.parquet").write.parquet(str(tmp_path / "nation.parquet"))
    part = spark.read.parquet(f"{SMALL}/part.parquet")  # 1 600 towns of 80 parts later, a town has the same place
    part.unionByName(part.withColumn("p_partkey", F.col("p_partkey") + 1600 * 80)).write.parquet(str(tmp_path / "part.parquet"))
    c = duckdb.connect()
    for t in ("nation", "part"):
        c.sql(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    for name in ("e_dimensions", "e_by_nation_cube"):
        got, want = experiments.QUERIES[name](spark, str(tmp_path)), c.sql(experiments.ORACLES[name])
        assert sorted(map(tuple, got.select(*want.columns).collect())) == sorted(want.fetchall())


def test_worst_mistakes_of_a_forest(spark):
    rows = experiments.forest_worst(spark, SMALL, trees=3, k=20, max_depth=4).collect()
    assert rows and {r.kind for r in rows} <= {"FN", "FP"} and all((r.score > 0.5) == (r.kind == "FP") for r in rows)


def test_levels_of_spice_are_those_of_single_runs(spark):
    own = experiments.idents(spark, SMALL).persist()
    plain = experiments.judged(own)
    got = spicing.spice_levels(own, plain, {"none": (0, 0), "half": (0.5, 0.5), "all": (1, 1)})
    found = {(r.level, r.truth): (r.n, round(r.s, 3)) for r in got.groupBy("level", "truth").agg(F.count("*").alias("n"), F.sum("dist_m").alias("s")).collect()}
    for name, p in (("none", 0), ("half", 0.5), ("all", 1)):
        rows = spicing.spiced_pairs(own, plain, p).where("truth is not null").groupBy("truth").agg(F.count("*").alias("n"), F.sum("dist_m").alias("s")).collect()
        assert {(name, r.truth): (r.n, round(r.s, 3)) for r in rows} == {k: v for k, v in found.items() if k[0] == name}
    curve = {(r.level, r.t): (r.tp, r.fp, r.fn, r.tn) for r in evaluate.sweep(got, "dist_m", (10, 50, 400), below=True, by=("level",)).collect()}
    assert len(curve) == 9 and curve["none", 50] != curve["all", 50]


def test_results_of_forests_are_written_one_by_one(spark):
    got = experiments.forest_rows(spark, SMALL, [(f"k={k}", {"k": k, "trees": 2, "max_depth": 3}) for k in (0, 5)])
    assert "ArrowEvalPython" not in got._jdf.queryExecution().executedPlan().toString()  # no plan holds two forests
    assert sorted(r.setting for r in got.collect()) == ["k=0", "k=5"]


def test_error_lists_score_only_their_measure(spark):
    got = experiments.tested(spark, SMALL, measures=("JAC",), repeats=1)
    assert got.scores.columns == ["a_label", "b_label", "JAC"]


def test_counts_by_label_equal_counts_by_pair(spark):
    got = experiments.tested(spark, SMALL, measures=("ED", "TFIDF"))
    strings = {"ED": "ED", "TFIDF": "TFIDF"}
    plain = evaluate.curves(got.scored_pairs(), strings).collect()
    by_label = evaluate.curves(got.pairs, strings, by_label=got.counted.join(got.scores, ["a_label", "b_label"])).collect()
    assert sorted(plain) == sorted(by_label) and got.counted.count() < got.pairs.count()


def test_no_table_of_nodes_is_sent_through_the_driver(spark):
    """Only the 25 nations may be broadcast; the anchors of all parts may not."""
    from stationlink.sources import fixtures

    plan = fixtures.station_nodes(spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") == 1 and "SortMergeJoin" in plan


def test_exact_quantiles_hold_no_group_in_one_task(spark):
    r = random.Random(5)
    values = {g: [r.choice((0.0, 7.5, r.random() * 1000)) for _ in range(n)] for g, n in ((0, 1), (1, 2), (2, 333), (3, 500))}
    rows = spark.createDataFrame([(g, v) for g, x in values.items() for v in x] + [(2, None), (4, None)], "g int, v double")
    got = {x.g: x for x in evaluate.exact_quantiles(rows, "g", "v", {"lo": 0.0, "mid": 0.5, "hi": 0.9}, 64).collect()}
    want = {x.g: x for x in rows.where("v is not null").groupBy("g").agg(*[F.percentile("v", q).alias(k) for k, q in (("lo", 0.0), ("mid", 0.5), ("hi", 0.9))]).collect()}
    assert got.keys() == want.keys() == values.keys()
    assert all(got[g][k] == pytest.approx(want[g][k], abs=1e-9) for g in want for k in ("lo", "mid", "hi"))
    assert "percentile" not in relational.r_quantile(spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()


def test_vectors_look_at_a_pair_of_labels_once(spark):
    from stationlink.operators import features

    rows = spark.createDataFrame([("1", "ab c", "ab", 5.0), ("2", "ab c", "ab", 6.0), ("3", None, "ab", 7.0)], "pair_id string, a_label string, b_label string, dist_m double")
    rows = rows.withColumns({c: F.lit(1.0) for c in ("a_lat", "a_lon", "b_lat", "b_lon")})
    got = features.vectors(rows, [" ab", "ab "], 1)
    assert got.count() == 3 and "Aggregate [__a" in got._jdf.queryExecution().optimizedPlan().toString()
    assert {x.pair_id: x.value[:2] for x in got.collect()}["2"] == [6.0, 2.0]


def test_vectors_look_up_trigrams_by_label_on_all_cores(spark):
    from stationlink.operators import features

    labels = ["ab ab", "ab", "", "b ab", None]
    rows = spark.createDataFrame([(f"{i}:{j}", a, b, 5.0) for i, a in enumerate(labels) for j, b in enumerate(labels)], "pair_id string, a_label string, b_label string, dist_m double")
    rows = rows.withColumns({c: F.lit(1.0) for c in ("a_lat", "a_lon", "b_lat", "b_lon")})
    dictionary = [" ab", "ab ", "b a"]
    got = features.vectors(rows, dictionary, 0)
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "RepartitionByExpression [label" in plan and "RepartitionByExpression [__a" in plan  # few bytes, so few partitions by size
    cut = lambda x: [f" {x} "[k : k + 3] for k in range(len(x or ""))]
    for r in got.collect():
        x, y = cut(r.a_label), cut(r.b_label)
        want = {2 + k: float(y.count(g) - x.count(g)) for k, g in enumerate(dictionary) if y.count(g) != x.count(g)}
        assert dict(zip(r["index"], r["value"])) == {0: 5.0, 1: float(len(set(x) ^ set(y)))} | want
