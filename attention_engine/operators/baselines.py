"""What the method is compared with, and ablations of its observations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import geo_distance
from .feedback import Facet, signature_name, signature, signature_similarity, signatures


def topk_highlights(prefix: DataFrame, k: int) -> DataFrame:
    """The first k rows of a list: what the search gives without any budget."""
    return prefix.where(F.col("rank") <= k).select("session_id", (F.col("rank") - 1).cast("int").alias("slot"), "point_id", "sim")


def topk_to_vector(points: DataFrame, vector: DataFrame, spec: list[Facet], k: int, **how) -> DataFrame:
    """The k points most similar to the vector; only the first k points of a signature can be among them."""
    w = Window.partitionBy("sig").orderBy("point_id")
    few = points.select("point_id", signature_name(signature(spec)).alias("sig")).withColumn("r", F.row_number().over(w)).where(F.col("r") <= k)
    scored = signature_similarity(signatures(points, spec), vector, **how).join(few, "sig")
    rank = F.row_number().over(Window.partitionBy("session_id").orderBy(F.col("sim").desc(), "point_id"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k).select("session_id", "rank", "point_id", "sim")


def passive_highlights(points: DataFrame, where: Column, k: int) -> DataFrame:
    """What a query gives to an analyst whose feedback is ignored."""
    return points.where(where).orderBy("point_id").limit(k).select("point_id")


def random_highlights(points: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """k points in the order of a digest of seed and id, which is the same everywhere."""
    return points.select("point_id").orderBy(F.md5(F.concat(F.lit(f"{seed}-"), F.col("point_id").cast("string"))), "point_id").limit(k)


def spread_highlights(points: DataFrame, k: int, metric: str = "haversine") -> DataFrame:
    """Farthest-point picks from the smallest id on, whatever the similarity; one small action a pick."""
    spark = points.sparkSession
    first = points.select("point_id", "lat", "lon").orderBy("point_id").limit(1).collect()
    chosen = list(first)
    while chosen and len(chosen) < k:
        gaps = [geo_distance(F.col("lat"), F.col("lon"), F.lit(p.lat), F.lit(p.lon), metric) for p in chosen]
        gap = F.round(F.least(*gaps) if len(gaps) > 1 else gaps[0], 9)
        nxt = points.where(~F.col("point_id").isin([p.point_id for p in chosen])).select("point_id", "lat", "lon", gap.alias("gap")).orderBy(F.col("gap").desc(), "point_id").limit(1).collect()
        if not nxt:
            break
        chosen += nxt
    return spark.createDataFrame([(i, p.point_id) for i, p in enumerate(chosen)], "slot int, point_id long")


def heat_cells(trace: DataFrame, size: float = 50.0, top: int = 10) -> DataFrame:
    """The busiest square tiles of the screen, instead of clusters."""
    tx, ty = F.floor(F.col("x") / size).cast("long"), F.floor(F.col("y") / size).cast("long")
    n = trace.groupBy("session_id", tx.alias("tx"), ty.alias("ty")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("session_id").orderBy(F.col("n").desc(), "tx", "ty")
    return n.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= top)
