"""Cost and accuracy measures."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.distance import diversity, geo_distance_np
from .zones import outlines


def sessions_of(trace: DataFrame) -> DataFrame:
    return trace.select("session_id").distinct()


def _per_session(rows: DataFrame, sessions: DataFrame, name: str) -> DataFrame:
    return sessions.join(rows.groupBy("session_id").agg(F.count("*").alias(name)), "session_id", "left").withColumn(name, F.coalesce(name, F.lit(0).cast("long")))


def region_count(rings: DataFrame, sessions: DataFrame) -> DataFrame:
    return _per_session(rings, sessions, "regions")


def zone_count(zones: DataFrame, sessions: DataFrame) -> DataFrame:
    return _per_session(zones, sessions, "zones")


def matched_count(found: DataFrame, sessions: DataFrame) -> DataFrame:
    return _per_session(found.select("session_id", "point_id").distinct(), sessions, "points")


def points_per_zone(found: DataFrame, zones: DataFrame, sessions: DataFrame) -> DataFrame:
    """Mean points of a session's zones, empty ones included."""
    n = zones.select("session_id", "zone_id").join(found.groupBy("session_id", "zone_id").agg(F.count("*").alias("n")), ["session_id", "zone_id"], "left")
    return sessions.join(n.groupBy("session_id").agg(F.avg(F.coalesce("n", F.lit(0))).alias("per_zone")), "session_id", "left").withColumn("per_zone", F.coalesce("per_zone", F.lit(0.0)))


def stats_table(rings: DataFrame, zones: DataFrame, found: DataFrame, sessions: DataFrame, sizes: list[int], available: int | None = None) -> DataFrame:
    """(n, regions, zones, points, pct): means over sessions for the first n points, and the unweighted average row (n null)."""
    r, z = region_count(rings, sessions).agg(F.avg("regions").alias("regions")), zone_count(zones, sessions).agg(F.avg("zones").alias("zones"))
    total = sessions.agg(F.count("*").alias("s"))
    spark = sessions.sparkSession
    ns = spark.createDataFrame([(n,) for n in sizes if available is None or n <= available], "n long")
    hits = ns.join(found.select("session_id", "point_id").distinct(), F.col("point_id") < F.col("n")).groupBy("n").agg(F.count("*").alias("hits"))
    rows = ns.join(hits, "n", "left").join(r).join(z).join(total)
    points = F.coalesce("hits", F.lit(0)) / F.col("s")
    rows = rows.select("n", "regions", "zones", points.alias("points"), (100.0 * points / F.col("n")).alias("pct"))
    means = rows.groupingSets([[F.col("n")], []], "n").agg(*[F.round(F.avg(c), 6).alias(c) for c in ("regions", "zones", "points", "pct")])
    return means


def study_table(log: DataFrame) -> DataFrame:
    """(role, task, start, seconds, interactions, reached): means over runs with all margins (null: all); reached: the share of runs that met the goal, the others count as long as they were watched."""
    ends = log.groupBy("role", "task", "start", "run").agg(F.max("seconds").alias("seconds"), F.max("iter").alias("iters"), F.max(F.col("done").cast("int")).alias("done"))
    return ends.cube("role", "task", "start").agg(F.round(F.avg("seconds"), 6).alias("seconds"), F.round(F.avg("iters"), 6).alias("interactions"), F.round(F.avg("done"), 6).alias("reached"))


def study_gaps(log: DataFrame) -> DataFrame:
    ends = log.groupBy("role", "task", "start", "run").agg(F.max("seconds").alias("s"))

    def mean(col: str, value: str):
        return F.avg(F.when(F.col(col) == value, F.col("s")))

    return ends.agg(
        F.round(mean("role", "novice") - mean("role", "expert"), 6).alias("novice_minus_expert"),
        F.round(mean("task", "T1") - mean("task", "T2"), 6).alias("t1_minus_t2"),
        F.round(mean("start", "I1") - mean("start", "I2"), 6).alias("i1_minus_i2"),
    )


def thinning_report(raw: DataFrame, kept: DataFrame) -> DataFrame:
    a, b = raw.groupBy("session_id").agg(F.count("*").alias("raw")), kept.groupBy("session_id").agg(F.count("*").alias("kept"))
    return a.join(b, "session_id", "left").select("session_id", "raw", F.coalesce("kept", F.lit(0).cast("long")).alias("kept"), F.round(F.try_divide(F.col("raw").cast("double"), F.col("kept")), 6).alias("factor"))


def index_report(cells: DataFrame) -> DataFrame:
    return cells.groupBy("depth").agg(F.count("*").alias("cells"), F.sum("n").alias("points"), F.max("n").alias("fullest"))


def agreement(got: DataFrame, want: DataFrame) -> DataFrame:
    """(missing, extra, precision, recall) of two row sets."""
    g, w = got.distinct(), want.distinct()
    both = g.intersect(w).agg(F.count("*").alias("both"))
    sizes = g.agg(F.count("*").alias("got")).join(w.agg(F.count("*").alias("want"))).join(both)
    return sizes.select((F.col("want") - F.col("both")).alias("missing"), (F.col("got") - F.col("both")).alias("extra"), F.coalesce(F.try_divide(F.col("both").cast("double"), F.col("got")), F.lit(1.0)).alias("precision"), F.coalesce(F.try_divide(F.col("both").cast("double"), F.col("want")), F.lit(1.0)).alias("recall"))


def list_recall(got: DataFrame, want: DataFrame) -> DataFrame:
    """Share of the true list entries that approximate lists hold, by owner."""
    hit = want.select("owner", "point_id").join(got.select("owner", "point_id", F.lit(1).alias("hit")), ["owner", "point_id"], "left")
    return hit.groupBy("owner").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def mean_similarity(chosen: DataFrame) -> DataFrame:
    return chosen.groupBy("session_id").agg(F.round(F.avg("sim"), 9).alias("mean_sim"))


def optimality(greedy: DataFrame, best: DataFrame) -> DataFrame:
    a, b = (x.groupBy("session_id").agg(F.max("diversity_km").alias(n)) for x, n in ((greedy, "greedy_km"), (best, "best_km")))
    return a.join(b, "session_id").withColumn("ratio", F.coalesce(F.try_divide("greedy_km", "best_km"), F.lit(1.0)))


def diversity_norm(chosen: DataFrame, candidates: DataFrame, metric: str = "haversine", reference: DataFrame | None = None) -> DataFrame:
    """best_found: divided by ``reference`` (session_id, best_km); without it max_pair: by the largest distance between two candidates, which are corners of their outline."""
    mine = diversity(chosen, metric=metric)
    if reference is not None:
        return mine.join(reference, "session_id").select("session_id", "diversity_km", F.coalesce(F.try_divide("diversity_km", "best_km"), F.lit(0.0)).alias("diversity_norm"))

    def widest(pdf: pd.DataFrame) -> pd.DataFrame:
        lat, lon = pdf["lat"].to_numpy(float), pdf["lon"].to_numpy(float)
        far = 0.0
        for a in range(0, len(lat), 512):
            far = max(far, float(geo_distance_np(lat[a : a + 512, None], lon[a : a + 512, None], lat[None, :], lon[None, :], metric).max()))
        return pd.DataFrame({"session_id": [pdf["session_id"].iloc[0]], "far": [far]})

    # the farthest two of a small area are corners of its outline
    corners = outlines(candidates.select("session_id", F.lit(0).alias("seg"), F.lit(0).cast("long").alias("cluster_id"), F.col("lon").alias("x"), F.col("lat").alias("y")), two_stage=True)
    rim = corners.select("session_id", F.explode("ring").alias("p")).select("session_id", F.col("p.x").alias("lon"), F.col("p.y").alias("lat"))
    flat = candidates.join(corners.select("session_id"), "session_id", "left_anti").select("session_id", "lon", "lat")  # in one line: no outline
    ends = flat.groupBy("session_id").agg(F.min(F.struct("lon", "lat")).alias("a"), F.max(F.struct("lon", "lat")).alias("b"))
    rim = rim.unionByName(ends.select("session_id", "a.*")).unionByName(ends.select("session_id", "b.*"))
    most = rim.groupBy("session_id").applyInPandas(widest, "session_id long, far double")
    return mine.join(most, "session_id").select("session_id", "diversity_km", F.coalesce(F.try_divide("diversity_km", "far"), F.lit(0.0)).alias("diversity_norm"))
