"""The library against worked examples, brute force and invariants."""

import math
import random
import time

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from placelink import catalog
from placelink.functions import sql as sql_functions
from placelink.functions.geo import haversine_m
from placelink.functions.similarity import address_sim, clean_phone, clean_website, intervals_sim, semantic_sim, text_sim
from placelink.operators import baselines, cutoff, learning, pairs as pair_operators, skew, storage
from placelink.operators.blocking import Root, capacity_quadtree, density_blocks, expected_depth, first_shared, overlap_blocks, quadtree_blocks, root_box
from placelink.operators.components import components
from placelink.operators import layers as layer_operators
from placelink.operators.layers import Attribute, collapse, fronts, layer_numbers, layers, layers_peel, layers_sql, lattice_prefilter
from placelink.operators.metrics import confusion, prf
from placelink.operators.pairs import all_pairs, candidate_pairs, comparison_count, radius_pairs
from placelink.operators.running import running_before
from placelink.operators.taxonomies import wup_table
from placelink.plans import experiments
from placelink.plans.link import Blocking, link
from placelink.sources import fixtures
from placelink.streaming.streams import arrivals

SF = "/root/testdata/sf0.001"


def value(spark, column):
    return spark.range(1).select(column.alias("v")).first().v


def test_worked_examples(spark):
    lit = F.lit
    assert round(value(spark, text_sim(lit("a" * 14), lit("a" * 14 + "bar"))), 4) == 0.8235
    assert value(spark, address_sim(lit("Street 15, 9480 Town"), lit("Street 15, 9480 Town North"))) == 0.9
    assert value(spark, address_sim(lit("Street 15, 9480 Town"), lit("Street 75, 9480 Town"))) == 0.0
    assert value(spark, address_sim(lit(""), lit("x"))) == 0.0 and value(spark, address_sim(lit(None).cast("string"), lit("x"))) == 0.0
    assert round(value(spark, text_sim(lit("x" * 26 + "1"), lit("x" * 26 + "7"))), 3) == 0.963
    assert round(value(spark, text_sim(lit("y" * 27), lit("y" * 27 + "z" * 8))), 4) == 0.7714
    assert value(spark, text_sim(lit("Løkken"), lit("Lokken"))) == pytest.approx(1 - 1 / 6)
    assert value(spark, text_sim(lit("abcdef"), lit("uvwxyz"), min_sim=0.5)) == 0.0


def test_wu_palmer_example(spark):
    chain = lambda name, below, n: [(f"{name}{i}", below if i == 0 else f"{name}{i - 1}") for i in range(n)]
    rows = [("root", None), ("a", "root"), ("common", "a")]
    rows += chain("r", "common", 5) + [("restaurant", "r4")] + chain("f", "common", 2) + [("food", "f1")]
    rows += chain("i", "common", 4) + [("italian", "i3")] + chain("p", "common", 5) + [("pizza", "p4")]
    w = {(r.term_a, r.term_b): r.wup for r in wup_table(spark.createDataFrame(rows, "term string, parent string")).collect()}
    assert [round(w[x], 4) for x in (("food", "restaurant"), ("food", "italian"), ("pizza", "restaurant"), ("italian", "pizza"))] == [0.4, 0.4286, 0.3333, 0.3529]
    path = lambda *x: F.array(F.array(*map(F.lit, x)))
    assert value(spark, semantic_sim(path("r", "a"), path("r", "b", "c"))) == 0.4


def test_cleaning(spark):
    for raw, want in (("+45 55 50 00", "555000"), ("0045555000", "555000"), ("55-50-00", "555000")):
        assert value(spark, clean_phone(F.lit(raw), "45")) == want
    for raw, want in (("HTTPS://www.A.com/x.html?q#f", "a.com/x"), ("http://m.b.org//", "b.org"), ("c.net#x", "c.net")):
        assert value(spark, clean_website(F.lit(raw))) == want


def test_intervals_and_distance(spark):
    s = lambda a, b: F.array(F.struct(F.lit(a).alias("open"), F.lit(b).alias("close")))
    got = [value(spark, intervals_sim(s(1, 5), s(*x), m)) for x, m in (((1, 5), "equal"), ((2, 4), "contained"), ((4, 9), "contained"), ((4, 9), "overlap"), ((5, 9), "overlap"))]
    assert got == [1.0, 1.0, 0.0, 1.0, 0.0]
    assert abs(value(spark, haversine_m(F.lit(10.0), F.lit(57.0), F.lit(10.0), F.lit(58.0))) - 111_195) < 5


def tree(points, box, m, density, max_level):
    """The definition, node by node: a child takes what lies in its box enlarged by a quarter of the node's sides."""
    out = []

    def node(x0, y0, w, h, level, ix, iy, inside):
        full = density is not None and len(inside) * 1000 > density * w * h
        if level < max_level and (math.hypot(w, h) > m or full):
            for a in (0, 1):
                for b in (0, 1):
                    cx, cy = x0 + a * w / 2, y0 + b * h / 2
                    kept = [p for p in inside if cx - w / 4 <= p[1] <= cx + 3 * w / 4 and cy - h / 4 <= p[2] <= cy + 3 * h / 4]
                    node(cx, cy, w / 2, h / 2, level + 1, 2 * ix + a, 2 * iy + b, kept)
        else:
            out.extend((level, ix, iy, p[0]) for p in inside)

    node(box.x0, box.y0, box.x1 - box.x0, box.y1 - box.y0, 0, 0, 0, points)
    return set(out)


@pytest.mark.parametrize("density", [None, 0.5])
def test_blocks_equal_the_recursive_tree(spark, density):
    rng = random.Random(5)
    points = [(f"p{i:04}", rng.randrange(0, 4097) / 4, rng.randrange(0, 4097) / 4) for i in range(400)] + [(f"q{i}", 512.0, 256.0) for i in range(5)]
    box = Root(0, 0, 1024, 1024)
    df = spark.createDataFrame(points, "eid string, x_m double, y_m double")
    b = overlap_blocks(df, 200, density, root=box, max_level=7)
    assert {(r.level, r.ix, r.iy, r.eid) for r in b.collect()} == tree(points, box, 200, density, 7)
    homes = b.where("is_home").groupBy("eid").count()
    assert homes.count() == len(points) and homes.agg(F.max("count")).first()[0] == 1
    pairs = candidate_pairs(b)
    raw = {}
    for level, ix, iy, e in tree(points, box, 200, density, 7):
        raw.setdefault((level, ix, iy), []).append(e)
    want = {(a, c) for v in raw.values() for a in v for c in v if a < c}
    got = [(r.eid_a, r.eid_b) for r in pairs.collect()]
    assert len(got) == len(set(got)) and set(got) == want
    assert comparison_count(b).first().comparisons == sum(len(v) * (len(v) - 1) // 2 for v in raw.values())


def test_trees(spark):
    p = fixtures.places(spark, SF).select("eid", "x_m", "y_m")
    plain = quadtree_blocks(p, 100)
    assert plain.count() == p.count()
    cap = capacity_quadtree(p, 20, max_level=12).groupBy("level", "ix", "iy").count()
    assert cap.where("count > 20 and level < 12").count() == 0 and cap.agg(F.sum("count")).first()[0] == p.count()
    malls = fixtures.places_coincident(spark, SF).select("eid", "x_m", "y_m")
    assert overlap_blocks(malls, 100, density=1, max_level=8).agg(F.max("level")).first()[0] <= 8
    assert expected_depth(Root(0, 0, 300, 400), 125) == 3
    square = overlap_blocks(p.withColumn("y_m", F.lit(0)), 100, root="square")
    assert square.count() > 0
    empty = p.limit(0)
    assert overlap_blocks(empty, 100).count() == 0 and candidate_pairs(overlap_blocks(empty, 100)).count() == 0


def test_radius_strategies_agree(spark):
    p = fixtures.places(spark, SF).select("eid", "x_m", "y_m")
    rows = lambda df: sorted((r.eid_a, r.eid_b, round(r.dist_m, 6)) for r in df.collect())
    want = rows(all_pairs(p, 60))
    assert rows(radius_pairs(p, 60)) == want == rows(radius_pairs(p, 60, "sorted"))
    assert rows(candidate_pairs(overlap_blocks(p, 60, level_rule="cover"), max_dist_m=60)) == want
    with pytest.raises(ValueError):
        all_pairs(p, 60, most=10)


def test_no_nested_loops_but_in_the_baseline(spark):
    p = fixtures.places(spark, SF).select("eid", "x_m", "y_m")
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan(candidate_pairs(overlap_blocks(p, 100))) and "NestedLoop" not in plan(radius_pairs(p, 100))
    assert "NestedLoop" in plan(all_pairs(p, 100)) or "Cartesian" in plan(all_pairs(p, 100))


def brute_layers(x):
    left, out, k = set(range(len(x))), np.zeros(len(x), int), 0
    while left:
        k += 1
        front = {i for i in left if not any((x[j] >= x[i]).all() and (x[j] > x[i]).any() for j in left)}
        for i in front:
            out[i] = k
        left -= front
    return out


@pytest.mark.parametrize("width", [1, 2, 3, 4])
def test_layer_kernel(width):
    rng = np.random.default_rng(width)
    for n in (0, 1, 60):
        x = rng.integers(0, 6, (n, width)) / 5
        assert (layer_numbers(x) == brute_layers(x)).all()


def test_layer_forms_agree(spark):
    rng = random.Random(2)
    rows = [(rng.randrange(6) / 5, rng.randrange(6) / 5, rng.randrange(6) / 5, rng.randrange(2)) for _ in range(150)]
    attrs = (Attribute("a"), Attribute("b", "low"), Attribute("c"))
    v = collapse(spark.createDataFrame(rows, "a double, b double, c double, label int"), attrs, "label")
    key = lambda df: {(r.a, r.b, r.c): r.layer for r in df.collect()}
    want = key(layers(v, attrs))
    assert key(layers_peel(v, attrs)) == want
    flipped = v.withColumn("b", -F.col("b"))
    assert {(a, -b, c): k for (a, b, c), k in key(layers_sql(flipped, ("a", "b", "c"))).items()} == want
    assert key(layers(v.repartition(5), attrs, max_layer=3)) == {x: k for x, k in want.items() if k <= 3}
    front = {(r.a, -r.b, r.c) for r in lattice_prefilter(flipped, ("a", "b", "c"), 5).collect()}
    assert {x for x, k in want.items() if k == 1} <= front
    assert key(layers(v.limit(0), attrs)) == {}


def curve(spark, rows):
    return cutoff.level_curve(spark.createDataFrame([(i + 1, b, t) for i, (b, t) in enumerate(rows)], "layer int, pairs long, positives long"))


def test_cuts_on_levels(spark):
    two = curve(spark, [(50, 50), (10, 0), (30, 24), (1000, 26)])
    assert [round(r.f1, 3) for r in two.orderBy("layer").collect()] == [0.667, 0.625, 0.779, 0.168]
    assert cutoff.sweep_cut(two).first().layer == 3 and cutoff.stop_layer(two).first().layer == 1 and cutoff.stop_layer(two, patience=2).first().layer == 4
    falling = curve(spark, [(10, 10), (10, 8), (10, 3), (50, 3), (100, 0)])
    assert cutoff.sweep_cut(falling).first().layer == cutoff.stop_layer(falling).first().layer
    assert cutoff.sweep_cut(curve(spark, [(5, 0), (5, 0)])).first().f1 == 0 and cutoff.stop_layer(curve(spark, [(5, 5)])).first().layer == 1
    recall = [r.recall for r in two.orderBy("layer").collect()]
    assert recall == sorted(recall)


@pytest.mark.parametrize("metric", ["euclidean", "manhattan", "sqeuclidean"])
def test_separation_sums_equal_the_double_loop(spark, metric):
    rng = random.Random(1)
    rows = [(rng.random(), rng.random(), rng.randrange(1, 6), rng.randrange(1, 4), 0) for _ in range(60)]
    df = spark.createDataFrame(rows, "a double, b double, layer int, pairs long, positives long")
    d = {"euclidean": math.dist, "manhattan": lambda p, q: sum(abs(x - y) for x, y in zip(p, q, strict=True)), "sqeuclidean": lambda p, q: math.dist(p, q) ** 2}[metric]
    for r in cutoff.separation_sums(df, ("a", "b"), metric).collect():
        want = sum(p[3] * q[3] * d(p[:2], q[:2]) for p in rows for q in rows if p[2] <= r.layer < q[2])
        assert r.total == pytest.approx(want, abs=1e-7)


def test_smoothing_and_triggers(spark):
    c = spark.createDataFrame([(i, 1.0 if i < 9 else None) for i in range(1, 10)], "layer int, dmu double")
    assert all(r.dmu_smooth is None or r.dmu_smooth == pytest.approx(1.0) for r in cutoff.gauss_smooth(c).collect())
    s = spark.createDataFrame([(1, -1.0), (2, 2.0), (3, 1.0), (4, -1.0)], "layer int, dmu_smooth double")
    assert [cutoff.separation_layer(s, t).first().layer for t in cutoff.TRIGGERS] == [1, 3, 4]
    assert cutoff.separation_layer(s.where("dmu_smooth > 1")).first().layer == 2


def test_early_stop_explores_less_and_agrees(spark):
    q = catalog.QUERIES
    r = q["early_stop_cut"](spark, SF).first()
    lv = q["level_curve_full"](spark, SF)
    assert r.layer == cutoff.stop_layer(lv).first().layer


def test_belief_combination():
    class V(float):
        pass

    def comb(a, b):
        k = 1 - a[0] * b[1] - a[1] * b[0]
        return ((a[0] * b[0] + a[0] * b[2] + a[2] * b[0]) / k, (a[1] * b[1] + a[1] * b[2] + a[2] * b[1]) / k, a[2] * b[2] / k)

    x, y, z = (0.5, 0.2, 0.3), (0.1, 0.6, 0.3), (0.4, 0.4, 0.2)
    assert comb(x, y) == pytest.approx(comb(y, x)) and comb(comb(x, y), z) == pytest.approx(comb(x, comb(y, z)))


def test_belief_columns(spark):
    got = spark.range(1).select(*baselines.combine(tuple(map(F.lit, (0.5, 0.2, 0.3))), tuple(map(F.lit, (0.1, 0.6, 0.3))))).first()
    assert sum(got) == pytest.approx(1.0) and got[0] == pytest.approx(0.23 / 0.68)


def test_baselines_behave(spark):
    q = catalog.QUERIES
    sweep = q["additive_a_sweep"](spark, SF).orderBy("threshold").collect()
    recall = [r.recall for r in sweep]
    assert recall == sorted(recall, reverse=True)
    topk = [r.recall for r in q["weighted_topk_sweep"](spark, SF).orderBy("k").collect()]
    assert topk == sorted(topk)


def test_layers_beat_the_scores(spark):
    """The ranking of the paper's comparison: the cuts of the layers have the best F1 of the unsupervised and score-based methods."""
    f1 = {r.method: r.f1 for r in catalog.QUERIES["baseline_summary"](spark, "/root/testdata/sf0.01").collect()}
    assert f1["sweep cut"] == max(f1.values())
    assert f1["separation cut"] > max(f1["belief"], f1["additive A .75"])


def test_clusters(spark):
    x = np.concatenate([np.random.default_rng(0).normal(0.1, 0.02, (30, 2)), np.random.default_rng(1).normal(0.9, 0.02, (30, 2))])
    w = np.ones(60)
    for f in (learning.k_medoids, learning.agglomerative, lambda a, b: learning.agglomerative(a, b, "single"), lambda a, b: learning.agglomerative(a, b, "complete"), learning.dbscan):
        c = f(x, w)
        assert len(set(c[:30])) == len(set(c[30:])) == 1 and c[0] != c[-1]


@pytest.mark.parametrize("method", ["kmedoids", "dbscan"])
def test_clusters_of_many_vectors_cover_all_pairs(spark, method, monkeypatch):
    n = learning.MOST_CLUSTERED + 500
    v = spark.range(n).select((F.col("id") / n * F.when(F.col("id") % 3 == 0, 0.1).otherwise(1.0)).alias("a"), (F.col("id") % 3 / 2).alias("b"), F.lit(7).alias("pairs"), (F.col("id") % 2).alias("positives"))
    r = learning.best_orientation(learning.cluster(v, method, ("a", "b"))).first()
    assert r.tp + r.fp + r.fn + r.tn == 7 * n and r.tp + r.fn == n // 2
    # stretches of few rows give what the whole matrix gives
    x, w = np.random.default_rng(5).random((300, 3)), np.random.default_rng(6).integers(1, 9, 300).astype(float)
    f = {"kmedoids": learning.k_medoids, "dbscan": learning.dbscan}[method]
    whole = f(x, w)
    monkeypatch.setattr(learning, "STRETCH", 5_000)
    assert (f(x, w) == whole).all() and set(whole) == {0, 1}


def test_agglomeration_refuses_more_than_it_holds(spark):
    n = learning.MOST_CLUSTERED + 1
    v = spark.range(n).select((F.col("id") / n).alias("a"), F.lit(1).alias("pairs"), F.lit(0).alias("positives"))
    with pytest.raises(ValueError, match="3000"):
        learning.cluster(v, "agglomerative", ("a",))


def test_components_equal_union_find(spark):
    rng = random.Random(3)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1040)] + [(2000, i) for i in range(2001, 2060)]
    root = {}

    def find(i):
        root.setdefault(i, i)
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        p, q = find(a), find(b)
        root[max(p, q)] = min(p, q)
    linked = {i for a, b in links if a != b for i in (a, b)}
    got = {r.id: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {i: find(i) for i in linked}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_running_totals(spark):
    rows = [(k, i / 50, i, i % 7) for k in ("x", None) for i in range(50)]
    df = spark.createDataFrame(rows, "k string, r double, i int, n long")
    got = {(r.k, r.i): r.before for r in running_before(df, ["k"], F.col("r"), [F.col("i")], "n", "before", bins=6).collect()}
    assert got == {(k, i): sum(j % 7 for j in range(i)) for k, _, i, _ in rows}


def test_whole_chain(spark):
    p, t = fixtures.places(spark, SF), fixtures.taxonomy(spark, SF)
    f1 = {}
    for method, k in (("sweep", None), ("early_stop", None), ("separation", None), ("fixed", 20)):
        out = link(p, t, Blocking(), method=method, k=k)
        f1[method] = prf(confusion(out)).first().f1
    assert f1["sweep"] == max(f1.values()) and f1["sweep"] > 0.6


def test_sql_functions_and_cells(spark):
    assert "overlap_cells" in sql_functions.register(spark)
    assert spark.sql("select round(text_sim('abcd', 'abce'), 2) v").first().v == 0.75
    p = fixtures.places(spark, SF).select("eid", "x_m", "y_m").limit(40)
    b = overlap_blocks(p, 100, root=Root(0, 0, 2000, 2000))
    p.createOrReplaceTempView("some_places")
    level = Root(0, 0, 2000, 2000).level(100)
    got = spark.sql(f"select eid, c.* from some_places, lateral overlap_cells(x_m * 1.0d, y_m * 1.0d, 0.0d, 0.0d, 2000.0d, 2000.0d, {level}) c")
    assert {(r.eid, r.ix, r.iy) for r in got.collect()} == {(r.eid, r.ix, r.iy) for r in b.collect()}


def test_fixture_source(spark):
    spark.dataSource.register(fixtures.PlaceFixtureSource)
    assert spark.read.format("place_fixture").option("n", 50).load().count() == 50


def test_late_rows_are_dropped(spark):
    """Without the watermark's limit the late events would have been counted."""
    late = {r.start: r.n for r in catalog.QUERIES["late_arrivals"](spark, SF).collect()}
    every = {r.start: r.n for r in catalog.QUERIES["window_arrivals_tumbling"](spark, SF).collect()}
    assert set(late) < set(every) and all(n <= every[k] for k, n in late.items()) and sum(late.values()) < sum(every[k] for k in late)


def test_streams_agree_with_the_batch(spark, tmp_path):
    ev = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    ev.repartitionByRange(4, "ts").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(ev.schema).parquet(str(tmp_path / "in"))
    q = arrivals(stream, "tumbling", "1 hour").writeStream.format("memory").queryName("tumbled").outputMode("complete").start()
    q.processAllAvailable()
    q.stop()
    want = sorted(map(tuple, arrivals(ev, "tumbling", None).collect()))
    assert sorted(map(tuple, spark.table("tumbled").collect())) == want


def test_full_cells_are_dealt_out(spark, monkeypatch):
    """Coincident places: the same pairs once each, and no task compares more than two parts of a cell."""
    places = spark.range(400).selectExpr("concat('m', id) eid", "cast(id % 5 * 700 + if(id % 7 = 0, id, 0) as double) x_m", "cast(id % 3 * 10 as double) y_m", "concat('s', id % 2) source")
    rows = lambda df: sorted((r.eid_a, r.eid_b, round(r.dist_m, 6)) for r in df.collect())
    blocks = overlap_blocks(places, 100)
    deep = overlap_blocks(places, 100, density=3.0, max_level=9)
    want = rows(candidate_pairs(blocks)), rows(candidate_pairs(blocks, "cross")), rows(candidate_pairs(deep)), rows(radius_pairs(places, 40))
    agree = want[3] == rows(all_pairs(places, 40))  # no diff of long lists
    assert agree and len(want[0]) > 4_000
    monkeypatch.setattr(pair_operators, "MOST_IN_CELL", 7)
    got = rows(candidate_pairs(blocks)), rows(candidate_pairs(blocks, "cross")), rows(candidate_pairs(deep)), rows(radius_pairs(places, 40))
    agree = got == want
    assert agree
    plan = candidate_pairs(blocks)._jdf.queryExecution().optimizedPlan().toString()
    assert "low_a" in plan and "high_a" in plan
    monkeypatch.setattr(pair_operators, "MOST_HOT_CELLS", 0)  # too many to broadcast
    agree = rows(candidate_pairs(blocks)) == want[0]
    assert agree


def test_twenty_thousand_places_on_one_point(spark):
    """A mall of that size makes two hundred million comparisons; the largest of its tasks has two parts of 2,000."""
    n = 20_000
    places = spark.range(n).selectExpr("concat('m', id) eid", "1.0d x_m", "1.0d y_m")
    far = spark.createDataFrame([("f", 5000.0, 5000.0)], "eid string, x_m double, y_m double")
    blocks = overlap_blocks(places.unionByName(far), 100)
    cells = blocks.groupBy("level", "ix", "iy").agg(F.count("*").alias("n"))
    parts = pair_operators._with_parts(blocks, ["level", "ix", "iy"], cells.where(F.col("n") > pair_operators.MOST_IN_CELL), 1)
    part = F.pmod(F.xxhash64("eid", "x_m", "y_m"), F.col("__parts"))
    sizes = parts.groupBy("ix", "iy", part.alias("part")).count()
    assert sizes.agg(F.max("count")).first()[0] < 1.2 * pair_operators.MOST_IN_CELL and sizes.where("ix = 0 and iy = 0").count() == 10


@pytest.mark.parametrize("width", [1, 2, 3, 4])
def test_fronts_are_the_layers(width):
    rng = np.random.default_rng(width)
    for n, step in ((0, 4), (1, 4), (200, 16), (200, 512)):
        x = np.unique(rng.integers(0, 9, (n, width)) / 8, axis=0)
        found = np.zeros(len(x), int)
        for k, rows in enumerate(fronts(x, step), 1):
            found[rows] = k
        assert (found == layer_numbers(x)).all()


def test_early_stop_equals_the_curve(spark):
    rng = random.Random(4)
    for patience in (1, 2):
        rows = [(rng.randrange(12) / 11, rng.randrange(12) / 11, int(rng.random() < 0.5)) for _ in range(300)]
        v = collapse(spark.createDataFrame(rows, "a double, b double, label int"), ("a", "b"), "label")
        lv = cutoff.level_curve(layers(v, ("a", "b")))
        want, got = cutoff.stop_layer(lv, patience).first(), cutoff.early_stop_cut(v, ("a", "b"), patience, verify=True)
        assert got["layer"] == want.layer and got["explored"] == (want.drop_at or want.layers)
        assert got["f1_loss"] == pytest.approx(cutoff.sweep_cut(lv).first().f1 - got["f1"], abs=1e-6)
    assert cutoff.early_stop_cut(v.limit(0), ("a", "b"))["layer"] is None


def test_ranking_refuses_more_than_one_task_takes(spark, monkeypatch):
    monkeypatch.setattr(layer_operators, "MOST_VECTORS", 5)
    run = layer_operators._ranked(["a"], [1], None)
    import pyarrow as pa

    with pytest.raises(ValueError, match="more than 5 distinct vectors"):
        list(run(iter([pa.RecordBatch.from_pydict({"a": [0.1 * i for i in range(4)]})] * 2)))


def test_sampled_separation(spark):
    rng = random.Random(1)
    rows = [(rng.random(), rng.random(), 1 + i % 5, rng.randrange(1, 4), 0) for i in range(200)]
    df = spark.createDataFrame(rows, "a double, b double, layer int, pairs long, positives long")
    total = lambda d: {r.layer: r.total for r in cutoff.separation_sums(d, ("a", "b")).collect()}
    exact, whole, half = total(df), total(cutoff.sampled(df, ("a", "b"), 1.0)), total(cutoff.sampled(df, ("a", "b"), 0.5))
    assert whole == pytest.approx(exact, abs=1e-6)
    assert all(abs(half[k] - exact[k]) < 0.15 * max(exact.values()) for k in exact)
    sums = cutoff.sampled(df, ("a", "b"), 0.3).groupBy("layer").agg(F.sum("pairs").alias("n")).collect()
    assert {r.layer: round(r.n) for r in sums} == {r.layer: r.n for r in df.groupBy("layer").agg(F.sum("pairs").alias("n")).collect()}


def test_weighted_scores_take_edits_and_information_content(spark):
    row = ("a", "b", "blue cafe", "blue bar", ["cafe"], ["bar"], 0.5, 0.4, 0.9, 0.3, 20.0, 1)
    p = spark.createDataFrame([row], "eid_a string, eid_b string, name_a string, name_b string, keywords_a array<string>, keywords_b array<string>, name_sim double, address_text double, address_sim double, semantic_sim double, dist_m double, label int")
    table = spark.createDataFrame([("bar", "cafe", 0.7)], "term_a string, term_b string, resnik double")
    got = baselines.weighted_scores(baselines.with_category(p, table)).first()
    assert got.score == pytest.approx(2 / 3 * (0.5 + 0.7 + 0.8) / 3 + 0.4 / 3, abs=1e-6)
    assert baselines.with_category(p, table.limit(0)).first().category_sim == 0.0


def test_dbscan_forms_agree(spark):
    rng = np.random.default_rng(8)
    x = np.concatenate([rng.normal((0.2, 0.2), 0.04, (80, 2)), rng.normal((0.7, 0.6), 0.05, (60, 2)), rng.random((30, 2))])
    w = rng.integers(1, 4, len(x))
    v = spark.createDataFrame([(*map(float, p), int(n), 0) for p, n in zip(x, w, strict=True)], "a double, b double, pairs long, positives long")
    for eps, least in ((0.05, 5), (0.1, 20), (0.02, 50), (0.3, 5)):
        want = {tuple(p): int(c) for p, c in zip(x.tolist(), learning.dbscan(x, w.astype(float), eps, least), strict=True)}
        agree = {(r.a, r.b): r.cluster for r in learning.dbscan_join(v, ("a", "b"), eps, least).collect()} == want
        assert agree, (eps, least)


def brute_dbscan(x, w, eps, least):
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2)) <= eps
    core = (d * w).sum(axis=1) >= least
    of = np.where(core, np.arange(len(x)), -1)
    for _ in range(len(x)):
        of = np.array([max([of[j] for j in np.flatnonzero(d[i] & core)]) if core[i] else -1 for i in range(len(x))])
    if not core.any():
        return np.ones(len(x), int)
    top = max(set(of[core]), key=lambda c: (w[of == c].sum(), -np.flatnonzero(of == c)[0]))
    return np.array([int(not (d[i] & (of == top)).any()) for i in range(len(x))])


def brute_medoids(x, w):
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    best = min(((np.minimum(d[i], d[j]) * w).sum(), i, j) for i in range(len(x)) for j in range(i))
    return best[0]


def test_clusterings_against_brute_force():
    rng = np.random.default_rng(3)
    x, w = np.concatenate([rng.normal(0.3, 0.1, (25, 2)), rng.normal(0.7, 0.1, (20, 2))]), rng.integers(1, 5, 45).astype(float)
    for eps, least in ((0.1, 8), (0.15, 20), (0.01, 50)):
        assert (learning.dbscan(x, w, eps, least) == brute_dbscan(x, w, eps, least)).all()
    c = learning.k_medoids(x, w)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    cost = sum(min((d[np.ix_(np.flatnonzero(c == k), [m])][:, 0] * w[c == k]).sum() for m in np.flatnonzero(c == k)) for k in (0, 1))
    assert cost <= 1.1 * brute_medoids(x, w)
    for linkage, join in (("single", min), ("complete", max)):
        groups = [[i] for i in range(len(x))]
        while len(groups) > 2:
            _, i, j = min((join(d[p, q] for p in groups[i] for q in groups[j]), i, j) for i in range(len(groups)) for j in range(i))
            groups[j] += groups.pop(i)
        got = learning.agglomerative(x, w, linkage)
        assert sorted(map(sorted, groups)) == sorted([sorted(np.flatnonzero(got == k).tolist()) for k in (0, 1)])


def test_supervised_models_learn_the_pairs(spark):
    """Each model beats the additive score on pairs that it has not seen, and tests every pair of its protocol once."""
    rng = random.Random(6)
    rows = [(f"a{i}", f"b{i}", rng.random() * 0.5 + 0.5 * y, rng.random() * 0.6 + 0.4 * y, y) for i in range(600) for y in [int(rng.random() < 0.4)]]
    p = spark.createDataFrame(rows, "eid_a string, eid_b string, u double, v double, label int")
    for model in learning.MODELS:
        for protocol, tested in (("full", 600), ("sample", 200), ("transfer", 400)):
            r = learning.supervised(p, model, ("u", "v"), protocol).first()
            assert r.tp + r.fp + r.fn + r.tn == tested and r.f1 > 0.8


def test_hot_keys_are_dealt_out(spark, monkeypatch):
    monkeypatch.setattr(skew, "LEAST", 10)
    rows = spark.range(1000).select(F.when(F.col("id") % 2 == 0, 0).when(F.col("id") % 11 == 0, None).otherwise(F.col("id")).alias("k"), F.col("id").alias("v"))
    per = rows.groupBy("k").agg(F.count("*").alias("n"), F.max("v").alias("top"))
    plain = sorted(map(repr, rows.join(per.drop("n"), "k").select("k", "v", "top").collect()))
    got = skew.join_counted(rows, per, ["k"], 1000)
    assert got.columns == ["k", "v", "top"] and sorted(map(repr, got.collect())) == plain
    assert skew.join_counted(rows, per.where("k = 0").select("k", "n"), ["k"], 1000, "left_semi").count() == 500
    assert skew.hot_limit(10**12) * skew.MOST_HOT > 10**12


def test_stored_frames_can_be_forgotten(spark):
    import pathlib

    df = storage.stored(spark.range(10), "test")
    at = pathlib.Path(df._stored_at.removeprefix("file://"))
    assert at.exists() and df.count() == 10
    storage.forget(df, None, spark.range(1))
    assert not at.exists()


def test_a_cluster_needs_a_shared_folder():
    class Conf:
        def get(self, key, default):
            return default

    class Context:
        master, applicationId = "spark://host:7077", "app"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        storage.shared_dir(Session())


def test_streamed_vectors_are_placed_in_a_frozen_ranking(spark):
    from placelink.streaming.streams import placed

    ranked = spark.createDataFrame([(1.0, 1.0, 1), (0.5, 1.0, 2), (0.5, 0.5, 3), (1.0, 0.2, 2)], "u double, v double, layer int")
    rows = [(1.0, 1.0), (0.9, 0.9), (0.5, 0.5), (0.4, 0.4), (1.0, 0.1), (0.0, 0.0)]
    got = {(r.u, r.v): r.layer for r in placed(spark.createDataFrame(rows, "u double, v double"), ranked, ("u", "v")).collect()}
    assert got == {(1.0, 1.0): 1, (0.9, 0.9): 2, (0.5, 0.5): 3, (0.4, 0.4): 4, (1.0, 0.1): 3, (0.0, 0.0): 4}


ORACLE_SAMPLE = ["places", "blocks_m100", "pairs_m100", "coverage_by_radius", "pair_vectors", "vector_layers", "level_curve_sample", "mu_curve", "separation_cut", "weighted_topk", "belief_links", "resnik_pairs", "session_overlap", "link_groups", "stream_places_dedup", "stream_links", "late_arrivals", "window_arrivals_session", "blocks_density", "capacity_leaves", "pairs_density", "baseline_summary_mixed", "cuts_by_protocol", "whole_method", "embedding_layers"]


@pytest.mark.parametrize("name", ORACLE_SAMPLE)
def test_oracle(spark, name):
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    got = catalog.QUERIES[name](spark, SF)
    want = c.execute(catalog.ORACLES[name])
    columns = [x[0] for x in want.description]
    assert sorted(columns) == sorted(got.columns)
    clean = lambda rows: sorted(repr(tuple(tuple(v) if isinstance(v, list) else v for v in r)) for r in rows)
    assert clean(got.select(*columns).collect()) == clean(want.fetchall())


def test_entry_and_catalogue(spark):
    assert len(__spark_entry__.entry(spark).columns) > 0
    assert set(catalog.ORACLES) <= set(catalog.QUERIES)


def test_half_plane_has_no_limit_on_rows(spark):
    def held(v, low, side, levels):
        found = [0]
        for _ in range(levels):
            side /= 2
            found = [c for i in found for c, ok in ((2 * i, v <= low + 2 * i * side + 1.5 * side), (2 * i + 1, v >= low + 2 * i * side + 0.5 * side)) if ok]
        return found

    x = lambda k: k * 7919 % 4093
    y = lambda k: k * 104729 % 3001
    few = spark.createDataFrame([(k, x(k), y(k)) for k in range(40)] + [(40, None, 3), (41, 4092, 3000)], "eid long, x_m long, y_m long")
    box = root_box(few)
    levels = box.level(30)
    got = sorted((r.eid, r.ix, r.iy) for r in overlap_blocks(few, 30, mode="half_plane").collect())
    points = [(k, x(k), y(k)) for k in range(40)] + [(41, 4092, 3000)]
    assert got == sorted((k, i, j) for k, a, b in points for i in held(a, box.x0, box.x1 - box.x0, levels) for j in held(b, box.y0, box.y1 - box.y0, levels))
    many = spark.range(200_000).select(F.col("id").alias("eid"), (F.col("id") * 7919 % 4093).alias("x_m"), (F.col("id") * 104729 % 3001).alias("y_m"))
    sizes = overlap_blocks(many, 0.0001, mode="half_plane").agg(F.count("*").alias("n"), F.countDistinct("eid").alias("places")).first()
    assert sizes.n > 20_000_000 and sizes.places == 200_000


def test_no_index_compares_any_number_of_places(spark, monkeypatch):
    rows = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64("eid_a", "eid_b", F.round("dist_m", 6)).cast("decimal(38,0)"))).first()
    k = F.col("id")
    many = spark.range(200_500).select(k.cast("string").alias("eid"), F.pmod(F.xxhash64(k), F.lit(180_000)).alias("x_m"), F.pmod(F.xxhash64(k, k), F.lit(180_000)).alias("y_m"))
    monkeypatch.setattr(experiments, "_xy", lambda s, d: many)
    got = rows(experiments.no_index_pairs(spark, SF))
    assert tuple(got) == tuple(rows(radius_pairs(many, 100, "grid"))) and got[0] > 1_000
    # ids of another type, repeated and missing ones, several chunks in a task
    monkeypatch.setattr(pair_operators, "CHUNK", 7)
    odd = spark.createDataFrame([(i % 60, float(i * 37 % 101), float(i * 53 % 97)) for i in range(90)] + [(None, 1.0, 1.0), (90, None, 1.0), (91, float("nan"), 1.0)], "eid long, x_m double, y_m double").coalesce(2)
    a, b = odd.toDF("eid_a", "xa", "ya"), odd.toDF("eid_b", "xb", "yb")
    d = F.sqrt((F.col("xa") - F.col("xb")) * (F.col("xa") - F.col("xb")) + (F.col("ya") - F.col("yb")) * (F.col("ya") - F.col("yb")))
    want = sorted(map(tuple, a.join(b, F.col("eid_a") < F.col("eid_b")).where(d <= 20).select("eid_a", "eid_b", d).collect()))
    assert sorted(map(tuple, all_pairs(odd, 20).collect())) == want


def test_trees_of_all_density_limits_in_one(spark, monkeypatch):
    p = fixtures.places(spark, SF).select("eid", "x_m", "y_m")
    limits = (0.5, 3.0, 10.0)
    blocks = density_blocks(p, 100, limits, max_level=12)
    got = candidate_pairs(blocks, carry=("codes",)).select("eid_a", "eid_b", first_shared(F.col("codes_a"), F.col("codes_b")).alias("first")).collect()
    for i, limit in enumerate(limits):
        want = sorted((r.eid_a, r.eid_b) for r in candidate_pairs(overlap_blocks(p, 100, density=limit, max_level=12)).select("eid_a", "eid_b").collect())
        agree = sorted((r.eid_a, r.eid_b) for r in got if r.first <= i) == want
        assert agree and want
    assert {r.first for r in got} == {0, 1, 2}
    calls = []
    monkeypatch.setattr(experiments, "candidate_pairs", lambda *a, **k: calls.append(1) or candidate_pairs(*a, **k))
    experiments.sweep_by_density(spark, SF)
    assert len(calls) == 1  # pairs are made and compared once, not once per limit


def test_no_index_compares_in_bytes_and_forms_the_distances_that_may_count(monkeypatch):
    rng = np.random.default_rng(3)
    plain = lambda x, y, u, v: np.sqrt((x[:, None] - u) * (x[:, None] - u) + (y[:, None] - v) * (y[:, None] - v))
    for name, small in (("WIDTH", 40), ("STRIP", 16), ("AT_ONCE", 50)):
        monkeypatch.setattr(pair_operators, name, small)
    odd = [0.0, -0.0, math.nan, math.inf, -math.inf, 1e300, -1e300, 2.0**53, 2.0**53 + 2, 99.99999999999999, 100.0, -100.0]
    for r in (0.0, 0.1, 1.0, 100.0, 1e9, -1.0, math.inf):
        step = r if 0 < r < math.inf else 1.0
        for spread in (1, 3, 256, 257, 1e5, 1e12, 1e16):
            x, y, u, v = (np.round(rng.random(n) * spread * 4 - spread * 2) / 4 * step for n in (70, 70, 90, 90))
            x[:30], y[:30] = u[:30] + step * rng.choice([-1, -0.8, 0, 0.6, 1, 1.0000001], 30), v[:30] + step * rng.choice([-1, -0.6, 0, 0.8], 30)
            for more in ((), odd):
                a, b, c, d = (np.concatenate([w, rng.permutation(more)]) for w in (x, y, u, v))
                with np.errstate(all="ignore"):
                    apart = plain(a, b, c, d)
                got = {(i, j): s for p in pair_operators.near_pairs(a, b, c, d, r) for i, j, s in zip(*(w.tolist() for w in p))}
                assert got == {(i, j): apart[i, j] for i, j in np.argwhere(apart <= r).tolist()}
    monkeypatch.undo()
    # a chunk against another: many times faster than doubles for every pair, and as complete
    x, y, u, v = (np.floor(rng.random(16_384) * 57_600) for _ in range(4))
    ways = {
        "bytes": lambda: sum(len(i) for i, _, _ in pair_operators.near_pairs(x, y, u, v, 100)),
        "doubles": lambda: sum(np.count_nonzero(plain(x[k : k + 32], y[k : k + 32], u, v) <= 100) for k in range(0, len(x), 32)),
    }
    times, found = {name: [] for name in ways}, {}
    for name, way in 2 * list(ways.items()):
        began = time.perf_counter()
        found[name] = way()
        times[name].append(time.perf_counter() - began)
    assert found["bytes"] == found["doubles"] > 1_000
    assert 4 * min(times["bytes"]) < min(times["doubles"])


def test_no_index_deals_out_both_sides(spark, monkeypatch):
    monkeypatch.setattr(pair_operators, "CHUNK", 50)
    monkeypatch.setattr(pair_operators, "CHUNKS_OF_TASK", 2)
    k = F.col("id")
    some = spark.range(1_000).select(k.alias("eid"), (k * 37 % 101).alias("x_m"), (k * 53 % 997).alias("y_m")).coalesce(1)
    pairs = all_pairs(some, 5)
    assert pairs.rdd.getNumPartitions() == 100  # 20 chunks, 2 in a part, every part with every part
    got = sorted(map(tuple, pairs.collect()))
    assert got == sorted(map(tuple, radius_pairs(some, 5).collect())) and len(got) > 100
