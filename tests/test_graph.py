import math
import random

import pytest
from pyspark.sql import functions as F

from provgraph import workloads
from provgraph.functions import geometry
from provgraph.operators import components, fusion, graph, identity, provenance, spatial
from provgraph.sources.overlay import Layers

BOX = "id long, city int, x0 long, y0 long, x1 long, y1 long"


def test_flagship(spark, sf):
    r = {x["city"]: x for x in workloads.flagship(spark, sf).collect()}
    assert len(r) == 5 and all(x["covered"] <= x["total"] for x in r.values())


def test_component_counts(spark, sf):
    w = Layers(spark, sf)
    e = fusion.edges(fusion.candidates(w.entity, w.crowd))
    kinds = {r["kind"]: r["n"] for r in fusion.classify(fusion.components_of(e)).groupBy("kind").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert kinds == {"1:1": 42, "1:n": 55, "n:m": 16}
    assert w.entity.count() == 150 and w.crowd.count() == 273 and e.count() == 301


@pytest.mark.parametrize("algo", ["star", "label"])
def test_components_brute(spark, algo):
    rng = random.Random(3)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(45)] + [(7, 7), (100, 101), (101, 102)]
    parent = {}
    find = lambda x: x if parent.setdefault(x, x) == x else find(parent[x])
    for a, b in edges:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = dict(components.connected(spark.createDataFrame(edges, "src long, dst long"), algo=algo).collect())
    assert got == {x: find(x) for x in {v for e in edges for v in e}}
    assert components.connected(spark.createDataFrame([], "src long, dst long"), algo=algo).count() == 0


def test_overlap_strategies_agree(spark):
    rng = random.Random(5)
    make = lambda n: [(i, i % 2, x := rng.randrange(-3000, 3000), y := rng.randrange(-3000, 3000), x + rng.choice([1, 50, 800, 2500]), y + rng.choice([1, 50, 800, 2500])) for i in range(n)]
    a = spark.createDataFrame(make(60), BOX).withColumnRenamed("id", "a")
    b = spark.createDataFrame(make(60) + [(99, None, 0, 0, 9, 9), (98, 0, None, 0, 9, 9)], BOX).withColumnRenamed("id", "b")
    got = {s: sorted(map(tuple, spatial.overlap_join(a, b, strategy=s).select("a", "b", "shared").collect())) for s in ("grid", "levels", "nested")}
    assert got["grid"] == got["levels"] == got["nested"] and got["grid"]


def test_touching_boxes_share_nothing_and_threshold_is_inclusive(spark):
    a = spark.createDataFrame([(1, 0, 0, 0, 100, 100)], BOX).withColumnRenamed("id", "entity_id").withColumn("area", F.lit(10000))
    b = spark.createDataFrame([(1, 0, 100, 0, 200, 100), (2, 0, 70, 0, 170, 100), (3, 0, 71, 0, 171, 100), (4, 0, 10, 10, 20, 20)], BOX).withColumnRenamed("id", "feature_id").withColumn("area", (F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0")))
    e = {r["feature_id"]: r for r in fusion.edges(fusion.candidates(a, b)).collect()}
    assert set(e) == {2, 4} and e[4]["overlap"] == 1.0 and abs(e[4]["jaccard"] - 0.01) < 1e-12


def test_within_boundary(spark):
    a = spark.createDataFrame([(1, 0, 0, 0, 10, 10)], BOX).withColumnRenamed("id", "a")
    b = spark.createDataFrame([(1, 0, 40, 50, 60, 60), (2, 0, 41, 50, 60, 60)], BOX).withColumnRenamed("id", "b")
    assert [r["b"] for r in spatial.within(a, b, 50).collect()] == [1]
    assert spatial.within(a, b, 50, inclusive=False).count() == 0


def test_knn_ties_and_small_sides(spark):
    a = spark.createDataFrame([(1, 0, 0, 0, 1, 1), (2, 1, 0, 0, 1, 1)], BOX).withColumnRenamed("id", "a")
    b = spark.createDataFrame([(i, 0, 100_000, i // 2 * 10, 100_001, i // 2 * 10 + 1) for i in range(6)], BOX).withColumnRenamed("id", "b")
    r = spatial.knn(a, b, 3, a_id="a", b_id="b").orderBy("rank").collect()
    assert [(x["a"], x["b"]) for x in r] == [(1, 0), (1, 1), (1, 2)]


def test_polygons(spark):
    p = lambda *pts: [{"x": float(x), "y": float(y)} for x, y in pts]
    square, moved, hole = p((0, 0), (10, 0), (10, 10), (0, 10)), p((5, 5), (15, 5), (15, 15), (5, 15)), p((6, 6), (6, 8), (8, 8), (8, 6))
    assert abs(geometry.overlap_of([square], [moved]) - 25) < 1e-9
    assert abs(geometry.overlap_of([square, hole], [moved]) - 21) < 1e-9
    assert abs(geometry.overlap_of([square[::-1]], [p((2, -5), (8, 20), (2, 20))]) - geometry.overlap_of([p((2, -5), (8, 20), (2, 20))], [square])) < 1e-6
    df = spark.createDataFrame([([square, hole],), ([],), (None,)], "r array<array<struct<x:double,y:double>>>")
    assert [x[0] for x in df.select(geometry.polygon_area(F.col("r"))).collect()] == [96.0, 0.0, None]


def test_projection_matches_meridian_arc(spark):
    df = spark.range(1).select(*geometry.reproject_tm(F.lit(9.0), F.lit(53.55), lon0=9.0))
    e, n = df.first()
    assert abs(e - 500_000) < 1e-6 and 5_930_000 < n < 5_940_000
    e2 = spark.range(1).select(geometry.reproject_tm(F.lit(10.0), F.lit(53.55), lon0=9.0)[0]).first()[0]
    assert abs((e2 - 500_000) - 66_300) < 100


def test_geometry_hash(spark):
    ring = [(0.0, 0.0), (4.0, 0.0), (4.0, 3.0), (0.0, 3.0)]
    d = lambda r: [[{"x": x, "y": y} for x, y in r]]
    rows = [(d(ring),), (d(ring[2:] + ring[:2]),), (d(ring[::-1]),), (d(ring + ring[:1]),), (d([(0.0, 0.0), (4.0, 0.0), (4.0, 3.0), (0.0, 4.0)]),)]
    h = [r["geom_hash"] for r in identity.geometry_hash(spark.createDataFrame(rows, "r array<array<struct<x:double,y:double>>>"), "r").collect()]
    assert len(set(h[:4])) == 1 and h[4] != h[0]


def test_identity(spark):
    rows = [("a", "x"), ("a", "x"), ("a", "y"), ("b", "x"), (None, "x"), (None, "x"), (None, "z")]
    df = spark.createDataFrame(rows, "id string, c string")
    r = identity.resolve(df, ["id"], ["c"]).collect()
    assert sorted((x["old_id"] or "", x["merged_n"], x["reason"]) for x in r) == [("", 1, "kept"), ("", 2, "merged"), ("a", 1, next(x["reason"] for x in r if x["old_id"] == "a" and x["c"] == "y")), ("a", 2, next(x["reason"] for x in r if x["old_id"] == "a" and x["c"] == "x")), ("b", 1, "kept")]
    named = [x["new_id"] for x in r if x["new_id"]]
    assert len(named) == len(set(named)) == 3
    assert identity.resolve(df, ["id"], ["c"], policy="rename_only").count() == 7


def test_no_overwrite(spark, sf):
    e = Layers(spark, sf).entity
    with pytest.raises(ValueError):
        provenance.attach(e, e, "height", "auth")
    out = provenance.attach(e, e.select("entity_id", F.lit(1).alias("height")), "height", "crowd")
    assert out.select("entity_id", "auth_height").exceptAll(e.select("entity_id", "auth_height")).count() == 0


def test_greedy_is_a_matching(spark, sf):
    w = Layers(spark, sf)
    m = fusion.greedy_match(fusion.edges(fusion.candidates(w.entity, w.crowd)))
    assert m.count() == m.select("entity_id").distinct().count() == m.select("feature_id").distinct().count() > 100


def test_invariants_catch_corruption(spark, sf):
    g = graph.PropertyGraph.from_layers(Layers(spark, sf))
    assert all(r["violations"] == 0 for r in g.invariants().collect()) and all(r["ok"] for r in g.checks().collect())
    bad = graph.PropertyGraph(g.nodes.withColumn("trust", F.when(F.col("node_id") != 1, F.col("trust"))), g.edges.withColumn("jaccard", F.lit(1.5)))
    assert {r["name"] for r in bad.invariants().where("violations > 0").collect()} == {"one_trust_class", "edge_confidence"}


def test_clipping_equals_boxes(spark, sf):
    r = workloads.queries()["udf_polygon_overlap"](spark, sf)
    assert r.where("abs(shared - clipped) > 0.01").count() == 0


def test_fusion_plan_is_native(spark, sf):
    w = Layers(spark, sf)
    plan = fusion.edges(fusion.candidates(w.entity, w.crowd))._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "Python" not in plan and "NestedLoop" not in plan


def test_reprojection_is_finite():
    assert math.isfinite(geometry.overlap_of([[{"x": 0, "y": 0}, {"x": 1, "y": 0}, {"x": 1, "y": 1}]], [[{"x": 0, "y": 0}, {"x": 1, "y": 0}, {"x": 0, "y": 1}]]))


def test_overwriting_is_a_violation(spark, sf):
    g = graph.PropertyGraph.from_layers(Layers(spark, sf))
    bad = graph.PropertyGraph(g.nodes.withColumn("attrs", F.when((F.col("layer") == "crowd") & (F.col("node_id") % 50 == 0), F.create_map(F.lit("storeys"), F.lit("3"))).otherwise(F.col("attrs"))), g.edges)
    planted = g.nodes.where("layer = 'crowd' and node_id % 50 = 0").count()
    assert {r["name"]: r["violations"] for r in bad.invariants().collect()}["no_overwrite"] == planted > 0


def test_external_objects_are_nodes_of_their_own(spark, sf):
    w = Layers(spark, sf)
    g = graph.PropertyGraph.from_layers(w)
    poi = w.poi.withColumn("kind_of", F.lit("shop"))
    more = g.with_external(poi, "poi", "place", "poi_id", ["kind_of"], fusion.poi_inside(w.entity, w.poi).select("city", F.col("entity_id").alias("src"), F.col("poi_id").alias("dst"), F.lit(1.0).alias("jaccard")))
    assert more.nodes.where("layer = 'poi'").count() == poi.count()
    assert more.nodes.count() == g.nodes.count() + poi.count() and {r["violations"] for r in more.invariants().collect()} == {0}
    with pytest.raises(ValueError):
        g.with_external(poi, "auth", "place", "poi_id", [])


def test_sources_are_never_written(spark, sf):
    import os

    stat = lambda: {f: (os.stat(f"{sf}/{f}").st_mtime_ns, os.stat(f"{sf}/{f}").st_size) for f in os.listdir(sf)}
    before = stat()
    for name in ("dup_id_resolved", "fusion_propagated", "ring_violations"):
        workloads.queries()[name](spark, sf).count()
    assert stat() == before


def test_footprints_against_points(spark):
    """Shared areas of turned and notched polygons, against a fine grid of points."""
    import random

    p = lambda *pts: [{"x": float(x), "y": float(y)} for x, y in pts]
    shapes = [
        ([p((0, 0), (10, 0), (10, 5), (5, 5), (5, 10), (0, 10))], [p((3, -2), (12, 6), (5, 12), (-3, 5))]),
        ([p((0, 0), (10, 0), (10, 10), (0, 10)), p((3, 3), (7, 3), (7, 7), (3, 7))], [p((2, 2), (11, 4), (6, 11))]),
        ([p((0, 0), (8, 1), (9, 9), (4, 4), (1, 8))], [p((1, 1), (9, 2), (5, 8)), p((4, 3), (5, 3), (4.5, 4))]),
    ]

    def inside(rings, x, y):
        hit = False
        for r in rings:
            for a, b in zip(r, r[1:] + r[:1]):
                if (a["y"] > y) != (b["y"] > y) and x < (b["x"] - a["x"]) * (y - a["y"]) / (b["y"] - a["y"]) + a["x"]:
                    hit = not hit
        return hit

    r = random.Random(1)
    for a, b in shapes:
        n = 40_000
        got = sum(inside(a, x, y) and inside(b, x, y) for x, y in ((r.uniform(-4, 13), r.uniform(-4, 13)) for _ in range(n))) / n * 17 * 17
        assert abs(geometry.overlap_of(a, b) - got) < 1.0
    df = spark.createDataFrame([([p((0, 0), (4, 0), (4, 4), (0, 4)), p((2, 2), (4, 2), (4, 4), (2, 4))],), (None,)], "r array<array<struct<x:double,y:double>>>")
    c = [x[0] for x in df.select(geometry.polygon_centroid(F.col("r"))).collect()]
    assert abs(c[0]["x"] - 20 / 12) < 1e-9 and abs(c[0]["y"] - 20 / 12) < 1e-9 and c[1] is None


def test_a_component_decides_for_all_its_edges(spark):
    """Entity 1 has one edge, but its component is n:m: ambiguous, though its own edge is one to one by degree on its side."""
    edge = spark.createDataFrame([(0, 1, 10, 0.5), (0, 2, 10, 0.6), (0, 2, 11, 0.7), (0, 3, 12, 0.9)], "city int, entity_id long, feature_id long, jaccard double")
    crowd = spark.createDataFrame([(i, 100 + i, i, "P") for i in (10, 11, 12)], "feature_id long, crowd_height int, levels int, status string")
    got = {r["entity_id"]: (r["kind"], r["shared_feature"], r["ambiguous"]) for r in fusion.propagate(edge, crowd).collect()}
    assert got == {1: ("n:m", True, True), 2: ("n:m", True, True), 3: ("1:1", False, False)}
