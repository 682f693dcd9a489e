"""The experiments on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.projection import to_geo
from ..keep import keep, shared_path
from ..operators import feedback, highlights, measures
from ..operators.feedback import Facet
from ..operators.matching import match_points, pruning
from ..operators.zones import attention_zones, discover_outlines
from ..sources import tables as T
from ..streaming import live
from .local import LocalPoints, simulated_run

SIZES = [100, 1000, 2000, 4000]


def lattice_trace(spark: SparkSession) -> DataFrame:
    """A hand-made session of 45 seconds: dwells of 5 by 5 samples, two or three in each third of the time."""
    thirds = [[(-200, 0), (200, 100)], [(-190, -10), (0, -200)], [(210, 110), (10, -190), (-160, -10)]]
    spots = [(s, cx + 10 * i, cy + 10 * j) for s, dwells in enumerate(thirds) for cx, cy in dwells for i in range(-2, 3) for j in range(-2, 3)]
    return spark.createDataFrame([(0, k, float(x), float(y), s * 15000 + (k % 75) * 200, "m") for k, (s, x, y) in enumerate(spots)], T.TRACE)


PLACES = [(-200, 0), (-190, -10), (-205, -5), (-195, 5), (0, -200), (5, -195), (10, -190), (15, -185), (0, -185), (-175, 0), (-175, -60), (-180, -50), (-170, -70), (-180, 0)]


def running_example(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    """(zones, points) of the example: g = 3 and four zones, one of which holds no point."""
    zones = attention_zones(discover_outlines(lattice_trace(spark), 45000, 3, 15, 4, None))
    places = spark.createDataFrame([(i + 1, float(x), float(y)) for i, (x, y) in enumerate(PLACES)], "point_id long, x double, y double")
    return zones, to_geo(places, T.VIEW)


#: All cells of the toy vector, of which five stay untouched.
TOY_DOMAIN = [("beds", "1"), ("beds", "2"), ("beds", "+2"), ("balcony", "yes"), ("balcony", "no"), ("air", "yes"), ("air", "no"), *(("rating", str(k)) for k in range(1, 6))]


def toy_vector(spark: SparkSession, delta: float = 1.0, how: str = "share") -> DataFrame:
    """Four homes whose prices aren't facets."""
    homes = spark.createDataFrame([(1, "1", "yes", "yes", "5"), (2, "1", "yes", "no", "5"), (3, "2", "yes", "no", "5"), (4, "1", "yes", "no", "4")], "point_id long, beds string, balcony string, air string, rating string")
    spec = [Facet(x, x) for x in ("beds", "balcony", "air", "rating")]
    found = homes.select(F.lit(0).cast("long").alias("session_id"), "point_id")
    return feedback.update_feedback(None, found, feedback.facetize(homes, spec), delta, how, spark.createDataFrame(TOY_DOMAIN, "attr string, val string"))


def four_homes(points: DataFrame, how: str = "share") -> DataFrame:
    """The toy vector's job on stored points: each analyst met four homes, whose prices aren't facets."""
    spec = [f for f in T.PART_SPEC if f.attr != "price"]
    found = points.select(F.floor(F.col("point_id") / 4).alias("session_id"), "point_id")
    return feedback.update_feedback(None, found, feedback.facetize(points, spec), 1.0, how, feedback.facet_domain(points, spec))


def statistics(spark: SparkSession, sf_dir: str, points: DataFrame, eps: float = 20, min_pts: int = 5, g: int = 3) -> DataFrame:
    """Regions, zones and matched points by number of points, 20 pooled sessions."""
    trace = T.trace_view(spark, sf_dir)
    rings = keep(discover_outlines(trace, T.T_C, g, eps, min_pts, T.TICK))
    zones = keep(attention_zones(rings))
    found = match_points(points, zones, "auto")
    return measures.stats_table(rings, zones, found, measures.sessions_of(trace), SIZES, points.count())


def diversity_by_budget(lists: DataFrame, ks: tuple = (5, 10, 20), scans: tuple = (0, 10, 100, 1000), times_ms: tuple | None = None) -> DataFrame:
    """Diversity, its share of the whole list's, and similarity, by k and by scans or milliseconds (-1: the whole list); means over sessions."""
    by = "scans" if times_ms is None else "time_ms"
    rows = highlights.budget_curve(lists, list(ks), list(scans), None if times_ms is None else [float(t) for t in times_ms])
    return rows.groupBy("k", by).agg(*[F.round(F.avg(c), 6).alias(c) for c in ("diversity_km", "diversity_norm", "mean_sim")])


SWEEP = [(2, 20, 5), (3, 20, 5), (4, 20, 5), (5, 20, 5), (6, 20, 5), (3, 12, 5), (3, 28, 5), (3, 20, 4), (3, 20, 7)]


def parameter_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean regions and zones by g, eps and min_pts, one changed at a time."""
    trace = T.trace_view(spark, sf_dir)
    sessions, out = measures.sessions_of(trace), None
    for g, eps, min_pts in SWEEP:
        rings = keep(discover_outlines(trace, T.T_C, g, eps, min_pts, T.TICK))
        a = measures.region_count(rings, sessions).agg(F.round(F.avg("regions"), 6).alias("regions"))
        b = measures.zone_count(attention_zones(rings), sessions).agg(F.round(F.avg("zones"), 6).alias("zones"))
        row = a.join(F.broadcast(b)).select(F.lit(g).alias("g"), F.lit(float(eps)).alias("eps"), F.lit(min_pts).alias("min_pts"), "regions", "zones")
        out = row if out is None else out.unionByName(row)
    return out


DELTAS = (0.25, 0.5, 1.0, 2.0, 4.0)


def delta_sweep(found: DataFrame, facets: DataFrame, deltas: tuple = DELTAS) -> DataFrame:
    """By delta: how far a second update on another set of points moves the vector from the first (sum of absolute changes), mean over sessions.

    The first update sees the matched points of even id, the second those of odd id.
    """
    even, odd = (found.where(F.col("point_id") % 2 == k) for k in (0, 1))
    out = None
    for d in deltas:
        one = feedback.update_feedback(None, even, facets, d)
        two = feedback.update_feedback(one, odd, facets, d)
        both = two.select("session_id", "attr", "val", F.col("weight").alias("after")).join(one.select("session_id", "attr", "val", F.col("weight").alias("before")), ["session_id", "attr", "val"], "left")
        moved = both.groupBy("session_id").agg(F.sum(F.abs(F.col("after") - F.coalesce("before", F.lit(0.0)))).alias("moved"))
        row = moved.join(even.select("session_id").distinct(), "session_id").agg(F.round(F.avg("moved"), 6).alias("moved")).select(F.lit(float(d)).alias("delta"), "moved")
        out = row if out is None else out.unionByName(row)
    return out


def k_sweep(lists: DataFrame, ks: tuple = (2, 3, 5, 10, 20), scans: int = 1000) -> DataFrame:
    """Diversity and similarity by k at one budget."""
    return diversity_by_budget(lists, ks, (scans,)).where(F.col("scans") >= 0)


def pruning_sweep(points: DataFrame, zones: DataFrame, cases: tuple = ((100, 16), (1000, 16), (2000, 16), (2000, 64), (2000, 256)), bounds=None) -> DataFrame:
    """(n, capacity, cells, tested, pruned): means over sessions with zones, by number of points and cell capacity."""
    out, found = None, keep(match_points(points, zones, "auto"))
    for n, c in cases:
        some = T.first_n(points, n)
        if some.count() < n:
            continue
        row = pruning(some, zones, c, bounds=bounds, found=found).agg(F.max("cells").alias("cells"), F.round(F.avg("tested"), 6).alias("tested"), F.round(F.avg("pruned"), 6).alias("pruned"))
        row = row.select(F.lit(n).cast("long").alias("n"), F.lit(c).alias("capacity"), "cells", "tested", "pruned")
        out = row if out is None else out.unionByName(row)
    return out


def sessions_at_scale(spark: SparkSession, sf_dir: str, times: int) -> DataFrame:
    """Zones per session of traces repeated under new session numbers, one session per user."""
    trace = T.trace_view(spark, sf_dir, pooled=None, mapping="raw")
    many = trace.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).withColumn("session_id", F.col("session_id") * times + F.col("copy")).drop("copy")
    return measures.zone_count(attention_zones(discover_outlines(many, T.T_C, 3, 20, 4, T.TICK)), measures.sessions_of(many))


def study_log(spark: SparkSession, sf_dir: str, runs: int = 5, most: int = 12) -> DataFrame:
    """Simulated analysts over the first 1000 points: (role, task, start, run, iter, seconds, done).

    A stand-in, not a replication: nobody was watched. T1: be shown a place of the requested
    brand area; T2: be shown a place of a profile (a kind and the lowest price bin). I1 starts
    near the goal, I2 far. Each iteration is a burst of samples of 200 ms about where the
    analyst looks, followed by one iteration of the method itself on all samples so far (zones,
    vector, anchor, search); then the analyst turns towards the goal, an expert with less
    error than a novice. A run ends when a highlight meets the goal, or after ``most`` bursts.
    """
    points = T.first_n(T.points_part(spark, sf_dir), 1000)
    rows = points.select("point_id", "x", "y", "lat", "lon", feedback.signature(T.PART_SPEC).alias("facets"), "kind", "price", "brand").orderBy("point_id").toPandas()  # 1000 at most
    cases = [(role, task, start, run) for role in ("novice", "expert") for task in ("T1", "T2") for start in ("I1", "I2") for run in range(runs)]
    told = spark.createDataFrame(cases, "role string, task string, start string, run int")

    def simulate(frames):
        held = LocalPoints(rows)
        for pdf in frames:
            out = []
            for case in pdf.itertuples(index=False):
                out += [(*case, k, s, d) for k, s, d in simulated_run(held, rows, *case, most)]
            yield pd.DataFrame(out, columns=["role", "task", "start", "run", "iter", "seconds", "done"])

    return told.repartition(min(len(cases), 32), "role", "task", "start", "run").mapInPandas(simulate, "role string, task string, start string, run int, iter int, seconds double, done boolean")


#: The stored table may be read in files of any order, so nothing of its 30 days is late.
LATENESS = "31 days"


def _event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.live_samples(T.event_samples(T.stream_events(spark, f"{sf_dir}/events.parque[t]")), LATENESS)


def stream_thin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ticks of the live trace in one pass over what there is. Windows start at the epoch as ticks do; a tick's last state counts."""
    out = shared_path(spark, "stream")

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/rows/batch={number}")

    query = live.live_thin(_event_stream(spark, sf_dir)).writeStream.outputMode("update").option("checkpointLocation", f"{out}/log").foreachBatch(write).trigger(availableNow=True).start()
    live.finished(query)
    rows = spark.read.parquet(f"{out}/rows")
    last = F.max_by(F.struct("sample_id", "t_ms"), "batch")
    return rows.groupBy("session_id", F.floor(F.col("t_ms") / T.TICK).alias("tick")).agg(last.alias("s")).select("session_id", "s.sample_id", "s.t_ms")


def stream_zones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Zones of elastic slices at the end of the stream: the last batch's rows of each session."""
    out = shared_path(spark, "stream")

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/rows/batch={number}")

    query = live.elastic_zones(_event_stream(spark, sf_dir), T.TICK, t_end=T.T_C, cap_ms=T.T_C).writeStream.outputMode("update").option("checkpointLocation", f"{out}/log").foreachBatch(write).trigger(availableNow=True).start()
    live.finished(query)
    rows = spark.read.schema(f"{live.ZONES}, batch int").parquet(f"{out}/rows")
    newest = rows.groupBy("session_id").agg(F.max("batch").alias("batch"))
    return rows.join(newest, ["session_id", "batch"]).select("session_id", "zone_id")


