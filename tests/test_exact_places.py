"""Points on the lines of the pointer's lattice and of the index."""

import duckdb
import pytest
from pyspark.sql import functions as F

from attention_engine.functions.geometry import contains
from attention_engine.operators.density import density_clusters
from attention_engine.operators.quadtree import build_quadtree, cells_for_zones
from attention_engine.operators.zones import attention_zones, drawn_zones, outlines
from attention_engine.plans.queries import ORACLES, QUERIES
from attention_engine.sources import tables as T

SF = "/root/testdata/sf0.01"


def test_screen_places_are_exact(spark):
    """x -300 came back from degrees as -300.00000000000006, in the next cell."""
    rows = T.load(spark, SF, "part").select(F.col("p_partkey").alias("k"), F.regexp_extract("p_brand", r"(\d+)", 1).cast("int").alias("b")).collect()
    want = {r.k: (-500.0 + 200.0 * ((r.b - 1) % 5) + 200.0 * (r.k * 7919 % 1000 / 1000.0) * (r.k * 7919 % 1000 / 1000.0), -350.0 + 140.0 * ((r.b - 1) // 5) + 140.0 * (r.k * 104729 % 997 / 997.0)) for r in rows}
    assert {r.point_id: (r.x, r.y) for r in T.points_part(spark, SF).collect()} == want


def test_zones_touch_cells(spark):
    """a zone that ends on a cell's line, or 7e-15 short of it by rounding, touches that cell."""
    points = spark.createDataFrame([(1, -4.0, 4.0), (2, 4.0, 4.0), (3, -4.0, -4.0), (4, 4.0, -4.0)], "point_id long, x double, y double")
    box = (-8.0, -8.0, 8.0, 8.0)
    _, cells = build_quadtree(points, box, 1, 3)
    zones = drawn_zones([(0, "on", [(0, 1), (3, 1), (3, 3), (0, 3)]), (0, "near", [(7e-15, 1), (3, 1), (3, 3), (7e-15, 3)]), (0, "off", [(1, 1), (3, 1), (3, 3), (1, 3)])], spark)
    hit = cells_for_zones(cells, zones, box, 3).groupBy("zone_id").agg(F.count_distinct("cell").alias("n"))
    assert {r.zone_id: r.n for r in hit.collect()} == {"on": 2, "near": 2, "off": 1}


def test_zones_keep_the_edges_of_their_outlines(spark):
    """Inside a zone is inside both outlines, whose corners are samples and so exact."""
    spots = [(0, 0.1, 0.1), (0, 3.3, 0.7), (0, 2.9, 3.1), (0, 0.3, 2.7), (1, 0.1, 1.3), (1, 1.7, 0.2), (1, 4.1, 1.9), (1, 1.1, 4.3)]
    rows = [(0, i, x, y, i, "m", s) for i, (s, x, y) in enumerate(spots)]
    trace = spark.createDataFrame(rows, T.TRACE + ", seg int")
    rings = outlines(density_clusters(trace, 10, 3))
    edges = [{tuple(e) for e in r.edges} for r in rings.collect()]
    zone = attention_zones(rings).first()
    assert {tuple(e) for e in zone.edges} == edges[0] | edges[1]
    near = [(float(i), zone.ring[i % len(zone.ring)].x + dx, zone.ring[i % len(zone.ring)].y + dy) for i in range(len(zone.ring)) for dx in (-1e-3, 0.0, 1e-3) for dy in (-1e-3, 0.0, 1e-3)]
    places = spark.createDataFrame(near, "i double, px double, py double")
    both = {(r.i, r.px, r.py) for r in places.crossJoin(rings.select("edges")).where(contains(F.col("px"), F.col("py"), F.col("edges"))).groupBy("i", "px", "py").count().where("count = 2").collect()}
    got = {(r.i, r.px, r.py) for r in places.crossJoin(attention_zones(rings).select("edges")).where(contains(F.col("px"), F.col("py"), F.col("edges"))).collect()}
    assert got == both


@pytest.mark.parametrize("name", ["matched_set", "feedback_softmax"])
def test_point_on_the_edge_of_an_outline(spark, tmp_path, name):
    """part 38000 lies at x -300, on an edge of an outline of session 1; taken back from degrees it lay inside."""
    con, big = duckdb.connect(), "/root/testdata/sf0.1"
    con.sql(f"COPY (SELECT event_id + k * 100000 AS event_id, user_id + k * 1503 AS user_id, event_type, ts, value, props FROM '{big}/events.parquet', range(5) r(k) WHERE (user_id + k * 1503) % 20 = 1) TO '{tmp_path}/events.parquet'")
    con.sql(f"COPY (SELECT p_partkey + 20000 AS p_partkey, * EXCLUDE (p_partkey) FROM '{big}/part.parquet' WHERE p_partkey % 20 = 0) TO '{tmp_path}/part.parquet'")
    for t in ("events", "part"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
    want = con.sql(ORACLES[name])
    got = QUERIES[name](spark, str(tmp_path)).select(want.columns)
    assert want.fetchall() and sorted(map(tuple, got.collect())) == sorted(want.fetchall())
