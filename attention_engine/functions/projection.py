"""Between the interaction layer (pixels from the screen's centre, y to the north) and the spatial layer (degrees)."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class ViewPort:
    """The part of the map on the screen; one pixel is ``deg_per_px`` degrees of latitude."""

    center_lat: float = 48.8566
    center_lon: float = 2.3522
    deg_per_px: float = 1e-4
    width: int = 1000
    height: int = 700

    def __post_init__(self) -> None:
        self.validate()

    def validate(self) -> None:
        if not abs(self.center_lat) < 90:
            raise ValueError("the centre must lie between the poles")
        if self.deg_per_px <= 0:
            raise ValueError("deg_per_px must be positive")

    @property
    def shrink(self) -> float:
        return math.cos(math.radians(self.center_lat))

    def lon(self, x: Column | float) -> Column | float:
        return x * self.deg_per_px / self.shrink + self.center_lon

    def lat(self, y: Column | float) -> Column | float:
        return y * self.deg_per_px + self.center_lat

    def x(self, lon: Column | float) -> Column | float:
        return (lon - self.center_lon) * self.shrink / self.deg_per_px

    def y(self, lat: Column | float) -> Column | float:
        return (lat - self.center_lat) / self.deg_per_px


def to_geo(df: DataFrame, view: ViewPort, x: str = "x", y: str = "y") -> DataFrame:
    return df.withColumns({"lon": view.lon(F.col(x)), "lat": view.lat(F.col(y))})


def to_screen(df: DataFrame, view: ViewPort, lon: str = "lon", lat: str = "lat") -> DataFrame:
    return df.withColumns({"x": view.x(F.col(lon)), "y": view.y(F.col(lat))})


def to_geo_by_view(df: DataFrame, views: DataFrame) -> DataFrame:
    """Each row by its own view; ``views``: (view_id, center_lat, center_lon, deg_per_px), one row per view shown."""
    shrink = F.cos(F.radians("center_lat"))
    out = df.join(views, "view_id").withColumns({"lon": F.col("x") * F.col("deg_per_px") / shrink + F.col("center_lon"), "lat": F.col("y") * F.col("deg_per_px") + F.col("center_lat")})
    return out.drop("center_lat", "center_lon", "deg_per_px")


def center_pixels(df: DataFrame, view: ViewPort, px: str = "px", py: str = "py") -> DataFrame:
    """Device pixels (from the top left, downwards) to pixels from the centre."""
    return df.withColumns({"x": F.col(px) - view.width / 2, "y": view.height / 2 - F.col(py)})


def zones_to_geo(zones: DataFrame, view: ViewPort) -> DataFrame:
    """Rings in degrees (x: longitude, y: latitude); an affine map keeps them convex."""
    ring = F.transform("ring", lambda p: F.struct(view.lon(p["x"]).alias("x"), view.lat(p["y"]).alias("y")))
    return zones.withColumn("geo_ring", ring)


def split_antimeridian(zones: DataFrame, ring: str = "geo_ring") -> DataFrame:
    """Longitude ranges of zones that leave [-180, 180], as one or two rows (west, east)."""
    low, high = F.array_min(F.transform(ring, lambda p: p["x"])), F.array_max(F.transform(ring, lambda p: p["x"]))

    def part(west: Column, east: Column) -> Column:
        return F.struct(west.cast("double").alias("west"), east.cast("double").alias("east"))

    whole = F.array(part(low, high))
    parts = F.when(low < -180, F.array(part(low + 360, F.lit(180.0)), part(F.lit(-180.0), high))).when(high > 180, F.array(part(low, F.lit(180.0)), part(F.lit(-180.0), high - 360))).otherwise(whole)
    return zones.withColumn("part", F.explode(parts)).select("*", "part.*").drop("part")


def samples_for_distance(cm: float, dpi: float = 1600) -> int:
    """Pixels that a pointer of so many dots per inch passes on a way."""
    return int(round(cm * dpi / 2.54))
