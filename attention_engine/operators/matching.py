"""Which points lie in which zones, by several strategies that give the same rows.

exhaustive: every point against every zone (the baseline, for small sets of zones); bbox:
boxes before edges; quadtree: an equi-join on the cells that meet a zone, points of other
cells are never tested; pushdown: literal ranges of the zones' boxes that reach the scan;
two_hulls: inside both outlines of a pair instead of their overlap. A point without a place
is in no zone. Strategies that compare points with zones without a key take at most
``MAX_BROADCAST_ZONES`` zones, which are counted; beyond that bbox and pushdown go by cells
and exhaustive is refused. auto: bbox for up to ``FEW_ZONES`` zones, else quadtree.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import bboxes_meet, contains, in_bbox
from ..functions.projection import ViewPort, to_screen
from .quadtree import HOT, Bounds, build_quadtree, cells_for_zones, data_bounds, placed, points_in_cells

#: Zones travel to every task only up to so many; more are dealt by cell.
MAX_BROADCAST_ZONES = 50_000
#: So few zones are compared with every point in less time than an index takes to build.
FEW_ZONES = 2_000
STRATEGIES = ("auto", "exhaustive", "bbox", "quadtree", "pushdown", "two_hulls")


def _few(zones: DataFrame, most: int = MAX_BROADCAST_ZONES) -> bool:
    return zones.limit(most + 1).count() <= most


def match_points(points: DataFrame, zones: DataFrame, strategy: str = "quadtree", closed: bool = False, capacity: int = 64, max_depth: int = 10, bounds: Bounds | None = None, index: tuple[DataFrame, DataFrame] | None = None, view: ViewPort | None = None, accept_full_cells: bool = False, hot: int = HOT) -> DataFrame:
    """(session_id, zone_id, point_id). ``points`` carry screen x, y (pushdown: lat, lon, and x, y or else those projected). ``index``: build_quadtree's result, with the bounds it was built for."""
    if strategy not in STRATEGIES or strategy == "two_hulls":
        raise ValueError(f"unknown strategy {strategy!r}; one of {STRATEGIES}, two_hulls by match_two_hulls")
    x, y = F.col("x"), F.col("y")
    points = points.where(placed()) if {"x", "y"} <= set(points.columns) else points.where(placed("lon", "lat"))
    shape = zones.select("session_id", "zone_id", F.col("edges").alias("z_edges"), F.col("bbox").alias("z_box"))
    out = ["session_id", "zone_id", "point_id"]
    inside = contains(x, y, F.col("z_edges"), closed)
    if strategy == "auto":
        strategy = "bbox" if index is None and not accept_full_cells and _few(zones, FEW_ZONES) else "quadtree"
    elif strategy != "quadtree" and not _few(zones):
        if strategy == "exhaustive":
            raise ValueError(f"more than {MAX_BROADCAST_ZONES} zones; use another strategy")
        strategy = "quadtree"
    if strategy == "exhaustive":
        return points.select("point_id", "x", "y").join(F.broadcast(shape), inside).select(out)
    if strategy == "bbox":
        return points.select("point_id", "x", "y").join(F.broadcast(shape), in_bbox(x, y, F.col("z_box")) & inside).select(out)
    if strategy == "quadtree":
        bounds = bounds or data_bounds(points)
        keyed, cells = index or build_quadtree(points, bounds, capacity, max_depth)
        hit = cells_for_zones(cells, zones, bounds, max_depth)
        met = points_in_cells(keyed.select("point_id", "x", "y", "cell", "leaf_n"), hit, hot).join(shape, ["session_id", "zone_id"])
        return met.where(F.col("full") | inside if accept_full_cells else inside).select(out)
    view = view or ViewPort()
    boxes = zones.agg(F.min("bbox.x0").alias("x0"), F.min("bbox.y0").alias("y0"), F.max("bbox.x1").alias("x1"), F.max("bbox.y1").alias("y1")).first()
    if boxes.x0 is None:
        return points.select("point_id").limit(0).select(F.lit(0).cast("long").alias("session_id"), F.lit("").alias("zone_id"), "point_id")
    slack = 1e-9
    near = points.where(F.col("lon").between(view.lon(boxes.x0) - slack, view.lon(boxes.x1) + slack) & F.col("lat").between(view.lat(boxes.y0) - slack, view.lat(boxes.y1) + slack))
    on_screen = near.select("point_id", "x", "y") if {"x", "y"} <= set(points.columns) else to_screen(near.select("point_id", "lat", "lon"), view)
    return on_screen.join(F.broadcast(shape), in_bbox(x, y, F.col("z_box")) & inside).select(out)


def match_two_hulls(points: DataFrame, rings: DataFrame, closed: bool = False, bounds: Bounds | None = None) -> DataFrame:
    """Inside two outlines of different slices: the same as inside their overlap, without clipping."""
    named = rings.select("session_id", F.concat_ws(".", "seg", "cluster_id").alias("zone_id"), "seg", "cluster_id", "edges", "bbox")
    inside = match_points(points, named, "bbox" if _few(named) else "quadtree", closed, bounds=bounds).join(named.drop("edges"), ["session_id", "zone_id"])
    a, b = (inside.select("session_id", "point_id", F.col("seg").alias(f"seg_{k}"), F.col("cluster_id").alias(f"c_{k}"), F.col("bbox").alias(f"box_{k}")) for k in (1, 2))
    pairs = a.join(b, ["session_id", "point_id"]).where((F.col("seg_1") < F.col("seg_2")) & bboxes_meet(F.col("box_1"), F.col("box_2")))
    return pairs.select("session_id", F.concat_ws("+", F.concat_ws(".", "seg_1", "c_1"), F.concat_ws(".", "seg_2", "c_2")).alias("zone_id"), "point_id")


def matched(found: DataFrame, multiplicity: str = "set") -> DataFrame:
    """set: a point counts once a session; per_zone: once for each zone."""
    if multiplicity == "set":
        return found.select("session_id", "point_id").distinct()
    if multiplicity == "per_zone":
        return found.select("session_id", "point_id", "zone_id").distinct()
    raise ValueError(f"unknown multiplicity {multiplicity!r}")


def match_audit(points: DataFrame, zones: DataFrame, capacity: int = 64, max_depth: int = 10, bounds: Bounds | None = None) -> DataFrame:
    """(point_id, status): inside some zone, tested and outside all, or never tested (points without a place included)."""
    bounds = bounds or data_bounds(points)
    keyed, cells = build_quadtree(points, bounds, capacity, max_depth)
    hit = cells_for_zones(cells, zones, bounds, max_depth).select("cell").distinct().withColumn("hit", F.lit(True))
    inside = match_points(points, zones, "quadtree", max_depth=max_depth, bounds=bounds, index=(keyed, cells)).select("point_id").distinct().withColumn("inside", F.lit(True))
    status = F.when(F.col("inside"), "inside").when(F.col("hit"), "outside").otherwise("untested")
    of = keyed.select("point_id", "cell").join(hit, "cell", "left").select("point_id", "hit")
    return points.select("point_id").join(of, "point_id", "left").join(inside, "point_id", "left").select("point_id", status.alias("status"))


def pruning(points: DataFrame, zones: DataFrame, capacity: int = 64, max_depth: int = 10, bounds: Bounds | None = None, found: DataFrame | None = None) -> DataFrame:
    """(session_id, points, cells, cells_hit, tested, matched, pruned): how many points of how many cells the index tests for a session's zones, and which share it spares. ``found``: match_points' rows, if known."""
    bounds = bounds or data_bounds(points)
    keyed, cells = build_quadtree(points, bounds, capacity, max_depth)
    hit = cells_for_zones(cells, zones, bounds, max_depth).select("session_id", "cell", "n").distinct()
    tested = hit.groupBy("session_id").agg(F.count("*").alias("cells_hit"), F.sum("n").alias("tested"))
    found = match_points(points, zones, "quadtree", max_depth=max_depth, bounds=bounds, index=(keyed, cells)) if found is None else found.join(points.select("point_id"), "point_id", "left_semi")
    inside = found.select("session_id", "point_id").distinct().groupBy("session_id").agg(F.count("*").alias("matched"))
    sizes = cells.agg(F.count("*").alias("cells"), F.coalesce(F.sum("n"), F.lit(0)).alias("points"))  # one row
    out = zones.select("session_id").distinct().join(tested, "session_id", "left").join(inside, "session_id", "left").join(F.broadcast(sizes))
    out = out.na.fill(0, ["cells_hit", "tested", "matched"])
    return out.select("session_id", "points", "cells", "cells_hit", "tested", "matched", F.round(1 - F.try_divide(F.col("tested").cast("double"), F.col("points")), 6).alias("pruned"))
