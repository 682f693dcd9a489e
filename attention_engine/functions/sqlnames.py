"""Names for SQL users: column formulas as SQL functions, table functions, and a mergeable hull."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .distance import EARTH_KM
from .geometry import RING, _array, _clip_rings, as_ring, quickhull



def haversine(lat1: str, lon1: str, lat2: str, lon2: str) -> str:
    """The distance as SQL text; functions can't be called within a lambda."""
    return f"2 * {EARTH_KM} * asin(least(1.0D, sqrt(pow(sin(radians({lat2} - {lat1}) / 2), 2) + cos(radians({lat1})) * cos(radians({lat2})) * pow(sin(radians({lon2} - {lon1}) / 2), 2))))"


#: name, arguments, result, body
FORMULAS = [
    ("ae_distance", "lat1 DOUBLE, lon1 DOUBLE, lat2 DOUBLE, lon2 DOUBLE", "DOUBLE", haversine("lat1", "lon1", "lat2", "lon2")),
    ("ae_ring_area", f"ring {RING}", "DOUBLE", "aggregate(transform(sequence(0, size(ring) - 1), i -> ring[i].x * ring[(i + 1) % size(ring)].y - ring[(i + 1) % size(ring)].x * ring[i].y), 0.0D, (a, v) -> a + v) / 2"),
    ("ae_contains", f"ring {RING}, px DOUBLE, py DOUBLE", "BOOLEAN", "forall(sequence(0, size(ring) - 1), i -> (ring[(i + 1) % size(ring)].x - ring[i].x) * (py - ring[i].y) - (ring[(i + 1) % size(ring)].y - ring[i].y) * (px - ring[i].x) > 0)"),
    ("ae_morton", "ix BIGINT, iy BIGINT, depth INT", "BIGINT", "aggregate(sequence(0, 30), 0L, (a, k) -> a + CASE WHEN k < depth THEN shiftleft((shiftright(ix, k) & 1L), 2 * k) + shiftleft((shiftright(iy, k) & 1L), 2 * k + 1) ELSE 0L END) + shiftleft(1L, 2 * depth)"),
    ("ae_diversity", "places ARRAY<STRUCT<lat:DOUBLE,lon:DOUBLE>>", "DOUBLE", f"coalesce(aggregate(flatten(transform(sequence(0, size(places) - 1), i -> transform(slice(places, i + 2, size(places)), q -> {haversine('places[i].lat', 'places[i].lon', 'q.lat', 'q.lon')}))), 0.0D, (a, v) -> a + v) / nullif(size(places) * (size(places) - 1) / 2, 0), 0.0D)"),
]
#: name, arguments, columns, query
TABLES = [
    ("ae_quadtree_cover", "x0 BIGINT, y0 BIGINT, x1 BIGINT, y1 BIGINT, depth INT", "cell BIGINT, ix BIGINT, iy BIGINT", "SELECT ae_morton(a.ix, b.iy, ae_quadtree_cover.depth), a.ix, b.iy FROM explode(sequence(ae_quadtree_cover.x0, ae_quadtree_cover.x1)) a(ix), explode(sequence(ae_quadtree_cover.y0, ae_quadtree_cover.y1)) b(iy)"),
    ("ae_resample", "x1 DOUBLE, y1 DOUBLE, t1 BIGINT, x2 DOUBLE, y2 DOUBLE, t2 BIGINT, step BIGINT", "t_ms BIGINT, x DOUBLE, y DOUBLE", "SELECT s.t, ae_resample.x1 + (ae_resample.x2 - ae_resample.x1) * (s.t - ae_resample.t1) / nullif(ae_resample.t2 - ae_resample.t1, 0), ae_resample.y1 + (ae_resample.y2 - ae_resample.y1) * (s.t - ae_resample.t1) / nullif(ae_resample.t2 - ae_resample.t1, 0) FROM explode(sequence(ae_resample.t1, ae_resample.t2 - 1, ae_resample.step)) s(t)"),
]


def register(spark: SparkSession) -> list[str]:
    """Makes all names known to the session's SQL; returns them."""
    for name, arguments, result, body in FORMULAS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {result} RETURN {body}")
    for name, arguments, columns, query in TABLES:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS TABLE ({columns}) RETURN {query}")
    spark.udf.register("ae_clip", F.pandas_udf(_clip_rings, RING))
    return [x[0] for x in (*FORMULAS, *TABLES)] + ["ae_clip"]


def hulls(points: DataFrame, by: list[str], x: str = "x", y: str = "y") -> DataFrame:
    """(by, ring): the hull of each group, from hulls of parts, which merge in any order."""
    shape = ", ".join(f"`{c}` {points.schema[c].dataType.simpleString()}" for c in by) + f", ring {RING}"

    def parts(frames):
        for pdf in frames:
            rows = [(*(k if isinstance(k, tuple) else (k,)), as_ring(quickhull(g[["x", "y"]].to_numpy(float)))) for k, g in pdf.groupby(by, dropna=False)]
            yield pd.DataFrame(rows, columns=[*by, "ring"])

    def merged(pdf: pd.DataFrame) -> pd.DataFrame:
        ring = quickhull(np.concatenate([_array(r) for r in pdf["ring"]]))
        return pd.DataFrame([(*(pdf[c].iloc[0] for c in by), as_ring(ring))], columns=[*by, "ring"])

    placed = points.where(F.col(x).isNotNull() & F.col(y).isNotNull()).select(*by, F.col(x).cast("double").alias("x"), F.col(y).cast("double").alias("y"))
    return placed.mapInPandas(parts, shape).groupBy(*by).applyInPandas(merged, shape)
