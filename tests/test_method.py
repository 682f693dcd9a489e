import duckdb
import pytest
from pyspark.sql import functions as F

from attention_engine.functions.projection import ViewPort, to_geo
from attention_engine.operators import feedback
from attention_engine.operators.density import density_clusters
from attention_engine.operators.matching import match_audit, match_points, match_two_hulls
from attention_engine.operators.quadtree import build_quadtree
from attention_engine.operators.trace import segment_trace, thin_trace
from attention_engine.operators.zones import attention_zones, discover_zones, outlines
from attention_engine.plans import workloads
from attention_engine.plans.queries import ORACLES, QUERIES
from attention_engine.sources.tables import TRACE

SF = "/root/testdata/sf0.001"


def lattice_trace(spark):
    slices = [[(-200, 0), (200, 100)], [(-190, -10), (0, -200)], [(210, 110), (10, -190), (-160, -10)]]
    rows, k = [], 0
    for s, centres in enumerate(slices):
        for cx, cy in centres:
            for i in range(-2, 3):
                for j in range(-2, 3):
                    rows.append((0, k, float(cx + 10 * i), float(cy + 10 * j), s * 15000 + (k % 75) * 200, "m"))
                    k += 1
    return spark.createDataFrame(rows, TRACE)


@pytest.fixture(scope="module")
def micro(spark):
    sliced = segment_trace(lattice_trace(spark), 45000, 3)
    rings = outlines(density_clusters(sliced, 15, 4)).cache()
    places = [(-200, 0), (-190, -10), (-205, -5), (-195, 5), (0, -200), (5, -195), (10, -190), (15, -185), (0, -185), (-175, 0), (-175, -60), (-180, -50), (-170, -70), (-180, 0)]
    points = to_geo(spark.createDataFrame([(i + 1, float(x), float(y)) for i, (x, y) in enumerate(places)], "point_id long, x double, y double"), ViewPort())
    return rings, attention_zones(rings).cache(), points.cache()


def test_micro_zones(micro):
    rings, zones, _ = micro
    assert rings.count() == 7
    assert sorted(round(r.area, 6) for r in zones.collect()) == [400, 900, 900, 900]
    assert attention_zones(rings, recurrence=3).count() == 0


def test_micro_matches(micro):
    rings, zones, points = micro
    want = {1, 2, 3, 4, 5, 6, 7, 8, 9, 10}
    for strategy in ("exhaustive", "bbox", "quadtree", "pushdown"):
        found = match_points(points, zones, strategy, capacity=1, max_depth=8)
        assert {r.point_id for r in found.collect()} == want, strategy
    assert {r.point_id for r in match_two_hulls(points, rings).collect()} == want
    assert match_points(points, zones, "exhaustive", closed=True).where("point_id = 14").count() == 2
    status = {r.point_id: r.status for r in match_audit(points, zones, capacity=1, max_depth=8).collect()}
    assert all(status[i] == "untested" for i in (11, 13)) and status[14] == "outside"


def test_toy_vector(spark):
    got = {(r.attr, r.val): round(r.weight, 4) for r in workloads.toy_vector(spark).collect()}
    assert got == {("beds", "1"): 0.1875, ("beds", "2"): 0.0625, ("balcony", "yes"): 0.25, ("air", "yes"): 0.0625, ("air", "no"): 0.1875, ("rating", "4"): 0.0625, ("rating", "5"): 0.1875}
    assert {(r.attr, r.val): round(r.weight, 9) for r in workloads.toy_vector(spark, delta=7.0).collect()} == {(r.attr, r.val): round(r.weight, 9) for r in workloads.toy_vector(spark).collect()}
    soft = workloads.toy_vector(spark, how="softmax_touched").agg(F.sum("weight")).first()[0]
    assert abs(soft - 1) < 1e-12


def test_delta_matters_from_the_second_update(spark):
    points = spark.createDataFrame([(1, "a"), (2, "b")], "point_id long, kind string")
    facets = feedback.facetize(points, [feedback.Facet("kind", "kind")])
    seen = lambda i: spark.createDataFrame([(0, i)], "session_id long, point_id long")
    weights = []
    for delta in (1.0, 9.0):
        v = feedback.update_feedback(feedback.update_feedback(None, seen(1), facets, delta), seen(2), facets, delta)
        weights.append({r.val: r.weight for r in v.collect()})
    assert weights[0] == {"a": 0.5, "b": 0.5} and abs(weights[1]["b"] - 0.9) < 1e-12


def test_clusterings_agree(spark):
    sliced = segment_trace(lattice_trace(spark), 45000, 3).cache()
    want = {(r.seg, r.sample_id, r.cluster_id, r.role) for r in density_clusters(sliced, 15, 4).collect()}
    assert {(r.seg, r.sample_id, r.cluster_id, r.role) for r in density_clusters(sliced, 15, 4, strategy="grid").collect()} == want


def test_degenerate_traces(spark):
    empty = spark.createDataFrame([], TRACE)
    assert discover_zones(empty, 1000).count() == 0
    one = spark.createDataFrame([(0, 1, 0.0, 0.0, 5, "m")], TRACE)
    assert discover_zones(one, 1000, every_ms=None).count() == 0
    still = spark.createDataFrame([(0, k, 1.0, 1.0, k, "m") for k in range(30)], TRACE)
    assert discover_zones(still, 30, every_ms=None).count() == 0
    line = spark.createDataFrame([(0, k, float(k), 0.0, k, "m") for k in range(30)], TRACE)
    assert discover_zones(line, 30, every_ms=None).count() == 0


def test_thinning(spark):
    gaps = spark.createDataFrame([(0, i, 0.0, 0.0, t, "m") for i, t in enumerate([0, 199, 200, 399, 401])], TRACE)
    assert [r.t_ms for r in thin_trace(gaps, 200).orderBy("t_ms").collect()] == [0, 200, 401]
    assert [r.t_ms for r in thin_trace(gaps, 200, "min_gap").orderBy("t_ms").collect()] == [0, 200, 401]
    once = thin_trace(gaps, 200)
    assert thin_trace(once, 200).count() == once.count()


def test_quadtree_partitions_points(spark):
    points = spark.createDataFrame([(i, float((i * 37) % 101), float((i * i) % 97)) for i in range(500)], "point_id long, x double, y double")
    keyed, cells = build_quadtree(points, (0.0, 0.0, 128.0, 128.0), 10, 7)
    assert keyed.count() == 500 and cells.agg(F.sum("n")).first()[0] == 500
    assert cells.where("n > 10 and depth < 7").count() == 0
    box = keyed.join(cells, "cell").where("x < bbox.x0 or x >= bbox.x1 or y < bbox.y0 or y >= bbox.y1")
    assert box.count() == 0



@pytest.mark.parametrize("name", ["trace_view", "trace_segments_printed", "points_customer", "outline_area", "zone_area", "match_pushdown", "feedback_softmax", "neighbour_list_signature", "distance_minkowski"])
def test_against_sql(spark, name):
    con = duckdb.connect()
    for t in ("events", "part", "customer", "supplier", "nation", "region"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.sql(ORACLES[name])
    cols = sorted(want.columns)
    text = lambda rows: sorted(tuple(f"{v:.6f}" if isinstance(v, float) else str(v) for v in row) for row in rows)
    got = QUERIES[name](spark, SF).select(cols)
    assert sorted(got.columns) == cols
    assert text(map(tuple, got.collect())) == text(want.select(*[duckdb.ColumnExpression(c) for c in cols]).fetchall())


def test_similar_plans(spark):
    plan = QUERIES["match_bbox"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
