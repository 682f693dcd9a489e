"""Connected components over edge tables that never leave the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """One star step: neighbours of a node move to the smallest of them."""
    if large:
        sym = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        sym = edges
    least = sym.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    joined = sym.join(least, "u")
    if large:
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
    return out.where("u > v").distinct()


def connected_components(edges: DataFrame, u: str = "u", v: str = "v", max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node that has an edge and isn't the smallest of its component.

    ``edges`` holds two LONG columns in either order; loops, repeats and rows with a
    null end are ignored. Alternates large-star and small-star steps, each written to
    the shared folder, until an edge table repeats; the driver sees two sums a round.
    """
    now = edges.where(F.col(u).isNotNull() & F.col(v).isNotNull()).select(F.greatest(u, v).alias("u"), F.least(u, v).alias("v")).where("u > v").distinct()
    now, seen = materialise(now, "edges"), None
    for _ in range(max_rounds):
        now = materialise(_stars(_stars(now, True), False), "edges")
        state = tuple(now.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.xxhash64("v", "u").cast("decimal(38,0)"))).first())
        if state == seen or state[0] == 0:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen = state
    raise RuntimeError("components did not settle")
