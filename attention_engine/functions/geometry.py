"""Convex rings: counter-clockwise vertices, not closed. Column functions, and kernels for grouped maps."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

RING = "array<struct<x:double,y:double>>"
EDGES = "array<struct<x:double,y:double,dx:double,dy:double>>"


def _turned(ring: Column) -> Column:
    """The ring from its second vertex on."""
    return F.concat(F.slice(ring, 2, F.size(ring)), F.slice(ring, 1, 1))


def ring_edges(ring: Column) -> Column:
    return F.zip_with(ring, _turned(ring), lambda p, q: F.struct(p["x"].alias("x"), p["y"].alias("y"), (q["x"] - p["x"]).alias("dx"), (q["y"] - p["y"]).alias("dy")))


def ring_area(ring: Column) -> Column:
    """By the first vertex as origin, which keeps small rings far from the centre exact."""
    x0, y0 = ring[0]["x"], ring[0]["y"]
    parts = F.zip_with(ring, _turned(ring), lambda p, q: (p["x"] - x0) * (q["y"] - y0) - (q["x"] - x0) * (p["y"] - y0))
    return F.when(F.size(ring) > 2, F.aggregate(parts, F.lit(0.0), lambda a, x: a + x) / 2).otherwise(F.lit(0.0))


def ring_perimeter(ring: Column) -> Column:
    parts = F.zip_with(ring, _turned(ring), lambda p, q: F.hypot(q["x"] - p["x"], q["y"] - p["y"]))
    return F.aggregate(parts, F.lit(0.0), lambda a, x: a + x)


def ring_centroid(ring: Column) -> Column:
    """Centre of the area; NaN-free only for rings with area."""
    x0, y0 = ring[0]["x"], ring[0]["y"]

    def moment(name: str, origin: Column) -> Column:
        parts = F.zip_with(ring, _turned(ring), lambda p, q: ((p["x"] - x0) * (q["y"] - y0) - (q["x"] - x0) * (p["y"] - y0)) * (p[name] + q[name] - 2 * origin))
        return F.try_divide(F.aggregate(parts, F.lit(0.0), lambda a, x: a + x), 6 * ring_area(ring)) + origin

    return F.struct(moment("x", x0).alias("x"), moment("y", y0).alias("y"))


def ring_bbox(ring: Column) -> Column:
    xs, ys = F.transform(ring, lambda p: p["x"]), F.transform(ring, lambda p: p["y"])
    return F.struct(F.array_min(xs).alias("x0"), F.array_min(ys).alias("y0"), F.array_max(xs).alias("x1"), F.array_max(ys).alias("y1"))


def contains(x: Column, y: Column, edges: Column, closed: bool = False) -> Column:
    """Whether a place lies inside all edges; places on an edge only if ``closed``."""

    def side(e: Column) -> Column:
        return e["dx"] * (y - e["y"]) - e["dy"] * (x - e["x"])

    return F.forall(edges, lambda e: side(e) >= 0 if closed else side(e) > 0)


def in_bbox(x: Column, y: Column, bbox: Column) -> Column:
    return (x >= bbox["x0"]) & (x <= bbox["x1"]) & (y >= bbox["y0"]) & (y <= bbox["y1"])


def bboxes_meet(a: Column, b: Column) -> Column:
    return (a["x0"] <= b["x1"]) & (b["x0"] <= a["x1"]) & (a["y0"] <= b["y1"]) & (b["y0"] <= a["y1"])


def wkt(ring: Column) -> Column:
    closed = F.concat(ring, F.slice(ring, 1, 1))
    return F.concat(F.lit("POLYGON(("), F.concat_ws(", ", F.transform(closed, lambda p: F.concat_ws(" ", p["x"], p["y"]))), F.lit("))"))


def geojson(ring: Column) -> Column:
    closed = F.transform(F.concat(ring, F.slice(ring, 1, 1)), lambda p: F.array(p["x"], p["y"]))
    return F.to_json(F.struct(F.lit("Polygon").alias("type"), F.array(closed).alias("coordinates")))


def _cross(o: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a[..., 0] - o[..., 0]) * (b[..., 1] - o[..., 1]) - (a[..., 1] - o[..., 1]) * (b[..., 0] - o[..., 0])


def quickhull(points: np.ndarray) -> np.ndarray:
    """Strict vertices, counter-clockwise from the lowest x: the farthest point of a side divides it."""
    points = np.unique(points, axis=0)
    if len(points) < 3:
        return points

    def side(a: np.ndarray, b: np.ndarray, rest: np.ndarray) -> list[np.ndarray]:
        """Vertices strictly right of a->b, from a to b."""
        away = -_cross(a, b, rest)
        rest, away = rest[away > 0], away[away > 0]
        if not len(rest):
            return []
        top = np.flatnonzero(away == away.max())
        along = rest[top] @ (b - a)
        far = rest[top[np.argmin(along)]]
        return [*side(a, far, rest), far, *side(far, b, rest)]

    low, high = points[0], points[-1]
    ring = np.array([low, *side(low, high, points), high, *side(high, low, points)])
    return strict(ring)


def strict(ring: np.ndarray) -> np.ndarray:
    """The ring without vertices at which it doesn't turn left."""
    while len(ring) > 2:
        turn = _cross(np.roll(ring, 1, axis=0), ring, np.roll(ring, -1, axis=0)) > 0
        if turn.all():
            return ring
        if not turn.any():
            return ring[[0, -1]] if len(ring) > 2 else ring
        ring = ring[turn]
    return ring


def chain_hull(points: np.ndarray) -> np.ndarray:
    """The same vertices by sorting and two chains."""
    points = np.unique(points, axis=0)
    if len(points) < 3:
        return points

    def half(rows: np.ndarray) -> list[np.ndarray]:
        out: list[np.ndarray] = []
        for p in rows:
            while len(out) > 1 and _cross(out[-2], out[-1], p) <= 0:
                out.pop()
            out.append(p)
        return out

    lower, upper = half(points), half(points[::-1])
    return np.array(lower[:-1] + upper[:-1])


HULLS = {"quickhull": quickhull, "chain": chain_hull}


def clip(ring: np.ndarray, by: np.ndarray) -> np.ndarray:
    """The overlap of two convex rings; fewer than three rows if they have no common area."""
    out = ring
    for a, b in zip(by, np.roll(by, -1, axis=0), strict=True):
        if not len(out):
            break
        d = (b[0] - a[0]) * (out[:, 1] - a[1]) - (b[1] - a[1]) * (out[:, 0] - a[0])
        rows = []
        for k in range(len(out)):
            p, q, dp, dq = out[k - 1], out[k], d[k - 1], d[k]
            if (dp < 0 < dq) or (dq < 0 < dp):
                rows.append(p + (q - p) * (dp / (dp - dq)))
            if dq >= 0:
                rows.append(q)
        out = np.array(rows).reshape(-1, 2)
    if len(out):
        out = out[np.r_[True, (np.diff(out, axis=0) != 0).any(axis=1)]]
        if len(out) > 1 and (out[0] == out[-1]).all():
            out = out[:-1]
    return out


def area_np(ring: np.ndarray) -> float:
    if len(ring) < 3:
        return 0.0
    x, y = (ring - ring[0]).T
    return float((x * np.roll(y, -1) - np.roll(x, -1) * y).sum() / 2)


def as_ring(rows: np.ndarray) -> list[dict]:
    return [{"x": float(x), "y": float(y)} for x, y in rows]


def _array(ring: object) -> np.ndarray:
    return np.array([(p["x"], p["y"]) for p in ring], float).reshape(-1, 2)


def _clip_rings(a: pd.Series, b: pd.Series) -> pd.Series:
    out = []
    for p, q in zip(a, b, strict=True):
        ring = clip(_array(p), _array(q)) if p is not None and q is not None and len(p) > 2 and len(q) > 2 else np.zeros((0, 2))
        out.append(as_ring(ring) if area_np(ring) > 0 else None)
    return pd.Series(out, dtype=object)


def clip_convex(a: Column | str, b: Column | str) -> Column:
    """Overlap of two rings as a ring; null without common area."""
    return F.pandas_udf(_clip_rings, RING)(a, b)
