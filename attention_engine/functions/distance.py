"""Distances between places, as columns and as numpy twins, and diversity."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EARTH_KM = 6371.0
METRICS = ("haversine", "cosine_law", "equirect", "l1", "l2", "linf", "lp")


def geo_distance(lat1: Column, lon1: Column, lat2: Column, lon2: Column, metric: str = "haversine", p: float = 3.0) -> Column:
    """Kilometres for the spherical metrics, degrees for the Minkowski family."""
    dlat, dlon = lat2 - lat1, lon2 - lon1
    if metric == "haversine":
        a = F.pow(F.sin(F.radians(dlat) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(dlon) / 2), 2)
        return 2 * EARTH_KM * F.asin(F.least(F.lit(1.0), F.sqrt(a)))
    if metric == "cosine_law":
        c = F.sin(F.radians(lat1)) * F.sin(F.radians(lat2)) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.cos(F.radians(dlon))
        return EARTH_KM * F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), c)))
    if metric == "equirect":
        x = F.radians(dlon) * F.cos(F.radians((lat1 + lat2) / 2))
        return EARTH_KM * F.sqrt(x * x + F.radians(dlat) * F.radians(dlat))
    if metric == "l1":
        return F.abs(dlat) + F.abs(dlon)
    if metric == "l2":
        return F.sqrt(dlat * dlat + dlon * dlon)
    if metric == "linf":
        return F.greatest(F.abs(dlat), F.abs(dlon))
    if metric == "lp":
        return F.pow(F.pow(F.abs(dlat), p) + F.pow(F.abs(dlon), p), 1 / p)
    raise ValueError(f"unknown metric {metric!r}; one of {METRICS}")


def geo_distance_np(lat1, lon1, lat2, lon2, metric: str = "haversine", p: float = 3.0):
    dlat, dlon = np.subtract(lat2, lat1), np.subtract(lon2, lon1)
    r1, r2 = np.radians(lat1), np.radians(lat2)
    if metric == "haversine":
        a = np.sin(np.radians(dlat) / 2) ** 2 + np.cos(r1) * np.cos(r2) * np.sin(np.radians(dlon) / 2) ** 2
        return 2 * EARTH_KM * np.arcsin(np.minimum(1.0, np.sqrt(a)))
    if metric == "cosine_law":
        return EARTH_KM * np.arccos(np.clip(np.sin(r1) * np.sin(r2) + np.cos(r1) * np.cos(r2) * np.cos(np.radians(dlon)), -1, 1))
    if metric == "equirect":
        return EARTH_KM * np.hypot(np.radians(dlon) * np.cos((r1 + r2) / 2), np.radians(dlat))
    if metric == "l1":
        return np.abs(dlat) + np.abs(dlon)
    if metric == "l2":
        return np.hypot(dlat, dlon)
    if metric == "linf":
        return np.maximum(np.abs(dlat), np.abs(dlon))
    if metric == "lp":
        return (np.abs(dlat) ** p + np.abs(dlon) ** p) ** (1 / p)
    raise ValueError(f"unknown metric {metric!r}; one of {METRICS}")


def diversity(points: DataFrame, by: str = "session_id", metric: str = "haversine") -> DataFrame:
    """(by, diversity_km): mean distance of all pairs of a set; 0 for fewer than two. Sets are answers of a few points."""
    a, b = (points.select(by, *[F.col(c).alias(f"{c}_{s}") for c in ("point_id", "lat", "lon")]) for s in ("a", "b"))
    pairs = a.join(b, by).where("point_id_a < point_id_b")
    mean = pairs.groupBy(by).agg(F.avg(geo_distance(F.col("lat_a"), F.col("lon_a"), F.col("lat_b"), F.col("lon_b"), metric)).alias("d"))
    return points.select(by).distinct().join(mean, by, "left").select(by, F.coalesce("d", F.lit(0.0)).alias("diversity_km"))


def diversity_np(lat: np.ndarray, lon: np.ndarray, metric: str = "haversine") -> float:
    if len(lat) < 2:
        return 0.0
    i, j = np.triu_indices(len(lat), 1)
    return float(np.mean(geo_distance_np(lat[i], lon[i], lat[j], lon[j], metric)))
