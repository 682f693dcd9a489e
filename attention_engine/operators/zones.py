"""Outlines of clusters, and attention zones: overlaps of outlines of different slices."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import HULLS, RING, _array, area_np, as_ring, bboxes_meet, clip, clip_convex, ring_area, ring_bbox, ring_edges
from .density import by_slices, density_clusters
from .trace import clip_trace, segment_trace, thin_trace

KEY = ["session_id", "seg", "cluster_id"]

def partial_rings(clusters: DataFrame, algo: str = "quickhull") -> DataFrame:
    """A ring per cluster and Arrow batch: hulls of parts, which can be merged."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            rows = [(*k, len(g), as_ring(HULLS[algo](g[["x", "y"]].to_numpy(float)))) for k, g in pdf.groupby(KEY)]
            yield pd.DataFrame(rows, columns=[*KEY, "n", "ring"])

    members = clusters.where("cluster_id is not null").select(*KEY, "x", "y")
    return members.mapInPandas(run, f"session_id long, seg int, cluster_id long, n long, ring {RING}")

def outlines(clusters: DataFrame, algo: str = "quickhull", two_stage: bool = False) -> DataFrame:
    """(session_id, seg, cluster_id, n, ring, area, bbox, edges); clusters without area have no outline."""
    if two_stage:
        parts = partial_rings(clusters, algo)
        members = parts.select(*KEY, "n", F.posexplode("ring").alias("k", "p")).select(*KEY, F.when(F.col("k") == 0, F.col("n")).otherwise(0).alias("n"), F.col("p.x").alias("x"), F.col("p.y").alias("y"))
    else:
        members = clusters.where("cluster_id is not null").select(*KEY, F.lit(1).cast("long").alias("n"), "x", "y")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = []
        xy, n = pdf[["x", "y"]].to_numpy(float), pdf["n"].to_numpy()
        for key, at in pdf.groupby(KEY).indices.items():
            ring = HULLS[algo](xy[at])
            if area_np(ring) > 0:
                rows.append((*key, n[at].sum(), as_ring(ring)))
        return pd.DataFrame(rows, columns=[*KEY, "n", "ring"])

    rings = by_slices(members, run, f"session_id long, seg int, cluster_id long, n long, ring {RING}")
    return with_shape(rings)

def with_shape(rings: DataFrame) -> DataFrame:
    return rings.withColumns({"area": ring_area(F.col("ring")), "bbox": ring_bbox(F.col("ring")), "edges": ring_edges(F.col("ring"))})

def slice_outlines(segments: DataFrame) -> DataFrame:
    """One outline per slice, whatever its density (an ablation)."""
    return outlines(segments.withColumn("cluster_id", F.lit(0).cast("long")))

def attention_zones(rings: DataFrame, recurrence: int = 2, min_area: float = 0.0, ordered: bool = False) -> DataFrame:
    """Overlaps of ``recurrence`` outlines of different slices: (session_id, zone_id, parents, ring, area, bbox, edges).

    ``edges`` are those of the parents: inside all of them is inside the overlap, and unlike
    the overlap's corners they aren't rounded, so points on an outline are told exactly.
    """
    parent = F.struct("seg", "cluster_id")
    found = rings.select("session_id", "seg", F.array(parent).alias("parents"), "ring", "bbox", "edges")
    one = found.select("session_id", *[F.col(c).alias(f"{c}2") for c in ("seg", "parents", "ring", "bbox", "edges")])
    for _ in range(recurrence - 1):
        apart = F.col("seg") != F.col("seg2") if ordered else F.col("seg") < F.col("seg2")
        met = found.join(one, "session_id").where(apart & bboxes_meet(F.col("bbox"), F.col("bbox2")))
        clipped = met.select("session_id", F.col("seg2").alias("seg"), F.concat("parents", "parents2").alias("parents"), F.concat("edges", "edges2").alias("edges"), clip_convex("ring", "ring2").alias("ring"))
        found = clipped.where("ring is not null").withColumn("bbox", ring_bbox(F.col("ring")))
    zones = with_shape(found.select("session_id", "parents", "ring", F.col("edges").alias("sides"))).withColumn("edges", F.col("sides")).where(F.col("area") > min_area)
    zone_id = F.concat_ws("+", F.transform("parents", lambda p: F.concat_ws(".", p["seg"], p["cluster_id"])))
    return zones.select("session_id", zone_id.alias("zone_id"), "parents", "ring", "area", "bbox", "edges")

def drawn_zones(rows: list[tuple[int, str, list[tuple[float, float]]]], spark) -> DataFrame:
    """Zones that an analyst drew: (session, name, convex ring counter-clockwise)."""
    data = [(s, z, [], [{"x": float(x), "y": float(y)} for x, y in ring]) for s, z, ring in rows]
    zones = with_shape(spark.createDataFrame(data, f"session_id long, zone_id string, parents array<struct<seg:int,cluster_id:long>>, ring {RING}"))
    return zones.select("session_id", "zone_id", "parents", "ring", "area", "bbox", "edges")

def merge_zones(zones: DataFrame) -> DataFrame:
    """Adds zone_group: the smallest zone_id among zones connected by overlaps; a session has few zones, so a group is one session."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("zone_id")

        rings, up = [_array(r) for r in pdf["ring"]], list(range(len(pdf)))

        def find(i: int) -> int:
            while up[i] != i:
                i = up[i]
            return i

        for i in range(len(rings)):
            for j in range(i):
                if area_np(clip(rings[i], rings[j])) > 0:
                    a, b = find(i), find(j)
                    up[max(a, b)] = min(a, b)
        names = pdf["zone_id"].to_numpy()
        return pd.DataFrame({"session_id": pdf["session_id"], "zone_id": names, "zone_group": names[[find(i) for i in range(len(rings))]] if len(rings) else names})

    return zones.groupBy("session_id").applyInPandas(run, "session_id long, zone_id string, zone_group string")

def discover_zones(trace: DataFrame, t_c: int, g: int = 3, eps: float = 20, min_pts: int = 5, every_ms: int | None = 200, recurrence: int = 2, min_area: float = 0.0, segments: str = "half_open", strategy: str = "local", cluster: str = "density", thin: str = "bucket", algo: str = "quickhull", eps_t: float | None = None, t_0: int | None = None) -> DataFrame:
    """From a trace to its attention zones. One shuffle by session serves thinning, slicing and local clusters."""
    return attention_zones(discover_outlines(trace, t_c, g, eps, min_pts, every_ms, segments, strategy, cluster, thin, algo, eps_t, t_0), recurrence, min_area)

def discover_outlines(trace: DataFrame, t_c: int, g: int = 3, eps: float = 20, min_pts: int = 5, every_ms: int | None = 200, segments: str = "half_open", strategy: str = "local", cluster: str = "density", thin: str = "bucket", algo: str = "quickhull", eps_t: float | None = None, t_0: int | None = None) -> DataFrame:
    """Outlines of the clusters of each slice of (t_0, t_c]."""
    sliced = segment_trace(thin_trace(clip_trace(trace, t_c).repartition("session_id"), every_ms, thin), t_c, g, segments, t_0=t_0)
    if cluster == "none":
        return slice_outlines(sliced)
    return outlines(density_clusters(sliced, eps, min_pts, eps_t, strategy), algo, two_stage=strategy == "grid")

