"""Preparing pointer traces: clip, thin, slice."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def clip_trace(trace: DataFrame, t_c: int) -> DataFrame:
    """Samples up to now."""
    return trace.where(F.col("t_ms") <= t_c)


def use_modalities(trace: DataFrame, weights: dict[str, float]) -> DataFrame:
    """Samples of the modalities named, with their weight."""
    pairs = F.create_map(*[F.lit(x) for kv in weights.items() for x in kv])
    return trace.where(F.col("modality").isin(list(weights))).withColumn("weight", pairs[F.col("modality")].cast("double"))


def thin_trace(trace: DataFrame, every_ms: int | None = 200, mode: str = "bucket") -> DataFrame:
    """At most one sample per tick: the first of each bucket, or those at least a tick after the last kept."""
    if every_ms is None:
        return trace
    if mode == "bucket":
        cols = [c for c in trace.columns if c != "session_id"]
        first = F.min_by(F.struct(*cols), F.struct("t_ms", "sample_id"))
        kept = trace.groupBy("session_id", F.floor(F.col("t_ms") / every_ms).alias("bucket")).agg(first.alias("s"))
        return kept.select("session_id", *[F.col(f"s.{c}") for c in cols]).select(trace.columns)
    if mode == "min_gap":

        def keep(pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values(["t_ms", "sample_id"], kind="stable")
            t, last, rows = pdf["t_ms"].to_numpy(), None, []
            at = 0
            while at < len(t):
                rows.append(at)
                last = t[at]
                at = int(np.searchsorted(t, last + every_ms, "left")) if every_ms else at + 1
                at = max(at, rows[-1] + 1)
            return pdf.iloc[rows]

        return trace.groupBy("session_id").applyInPandas(keep, trace.schema)
    raise ValueError(f"unknown mode {mode!r}")


def segment_trace(trace: DataFrame, t_c: int | None = None, g: int = 3, mode: str = "half_open", width_ms: int | None = None, t_0: int | None = None) -> DataFrame:
    """Adds ``seg``; with ``t_0`` only samples after it count, and the slices begin there. half_open: g slices, the last closed at t_c; printed: g + 1 slices closed at both ends; ntile: g slices of equal counts; fixed: slices of ``width_ms``."""
    if mode == "fixed" or width_ms is not None:
        return trace.withColumn("seg", F.floor(F.col("t_ms") / width_ms).cast("int"))
    if mode == "ntile":
        w = Window.partitionBy("session_id").orderBy("t_ms", "sample_id")
        return trace.withColumn("seg", (F.ntile(g).over(w) - 1).cast("int"))
    if not t_c or t_c <= 0:
        return trace.withColumn("seg", F.lit(0))
    trace, since = clip_trace(trace, t_c), t_0 or 0
    if t_0 is not None:
        trace = trace.where(F.col("t_ms") > t_0)
    scaled, span = (F.col("t_ms") - since) * g, t_c - since
    if span <= 0:
        return trace.limit(0).withColumn("seg", F.lit(0))
    if mode == "half_open":
        return trace.withColumn("seg", F.least(F.floor(scaled / span), F.lit(g - 1)).cast("int"))
    if mode == "printed":
        seg = F.floor(scaled / span).cast("int")
        both = F.when((F.pmod(scaled, F.lit(span)) == 0) & (F.col("t_ms") > since), F.array(seg - 1, seg)).otherwise(F.array(seg))
        return trace.withColumn("seg", F.explode(both))
    raise ValueError(f"unknown mode {mode!r}")


def densify_trace(trace: DataFrame, step_ms: int) -> DataFrame:
    """Samples every ``step_ms`` on the straight way between neighbours: a stand-in for raw device rates."""
    w = Window.partitionBy("session_id").orderBy("t_ms", "sample_id")
    nxt = trace.withColumns({"t2": F.lead("t_ms").over(w), "x2": F.lead("x").over(w), "y2": F.lead("y").over(w)})
    steps = F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0).cast("long"), F.floor((F.coalesce("t2", "t_ms") - F.col("t_ms") - 1) / step_ms).cast("long")))
    on = nxt.withColumn("k", F.explode(steps)).withColumn("r", F.coalesce(F.try_divide(F.col("k") * step_ms, (F.col("t2") - F.col("t_ms")).cast("double")), F.lit(0.0)))
    return on.select("session_id", "sample_id", (F.col("x") + F.coalesce((F.col("x2") - F.col("x")) * F.col("r"), F.lit(0.0))).alias("x"), (F.col("y") + F.coalesce((F.col("y2") - F.col("y")) * F.col("r"), F.lit(0.0))).alias("y"), (F.col("t_ms") + F.col("k") * step_ms).alias("t_ms"), "modality")


def speed(trace: DataFrame) -> DataFrame:
    """Gap, way and speed from the sample before."""
    w = Window.partitionBy("session_id").orderBy("t_ms", "sample_id")
    gap = F.col("t_ms") - F.lag("t_ms").over(w)
    way = F.sqrt(F.pow(F.col("x") - F.lag("x").over(w), 2) + F.pow(F.col("y") - F.lag("y").over(w), 2))
    return trace.select("session_id", "sample_id", gap.alias("gap_ms"), way.alias("way_px"), F.try_divide(way, gap.cast("double")).alias("px_per_ms"))


def views_in_force(trace: DataFrame, changes: DataFrame) -> DataFrame:
    """Adds the view shown at each sample: the last (session_id, t_ms, view_id) not after it."""
    marks = changes.select("session_id", "t_ms", F.lit(-1).cast("long").alias("sample_id"), "view_id", F.lit(True).alias("mark"))
    both = trace.withColumns({"view_id": F.lit(None).cast(changes.schema["view_id"].dataType), "mark": F.lit(False)}).unionByName(marks, allowMissingColumns=True)
    w = Window.partitionBy("session_id").orderBy("t_ms", F.col("mark").desc(), "sample_id").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("view_id", F.last("view_id", ignorenulls=True).over(w)).where("not mark").drop("mark")


