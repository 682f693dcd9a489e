"""The live trace: thinning in windows, sliding attention, sessions, and elastic slices in state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import area_np, as_ring, clip, quickhull
from ..operators.density import label

ZONES = "session_id long, t_c long, zone_id string, area double, ring array<struct<x:double,y:double>>"


def live_samples(samples: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Trace rows with event time ``at`` and a watermark."""
    return samples.withWatermark("at", lateness)


def live_thin(samples: DataFrame, tick: str = "72 minutes") -> DataFrame:
    """The first sample of each tick, final once the watermark has passed it."""
    first = F.min_by(F.struct("sample_id", "x", "y", "t_ms", "modality"), F.struct("t_ms", "sample_id"))
    return samples.groupBy("session_id", F.window("at", tick).alias("tick")).agg(first.alias("s")).select("session_id", "s.*")


def fixed_segments(samples: DataFrame, width: str = "10 days") -> DataFrame:
    """Counts and extents of slices of fixed width, whose edges don't move with the present."""
    return samples.groupBy("session_id", F.window("at", width).alias("w")).agg(F.count("*").alias("n"), F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1")).select("session_id", F.col("w.start").alias("start"), "n", "x0", "x1", "y0", "y1")


def sliding_attention(samples: DataFrame, size: float = 50.0, length: str = "2 days", step: str = "1 day") -> DataFrame:
    """How often each tile was visited within the last stretch of time."""
    tile = [F.floor(F.col(c) / size).cast("long").alias(f"t{c}") for c in ("x", "y")]
    return samples.groupBy("session_id", F.window("at", length, step).alias("w"), *tile).agg(F.count("*").alias("n")).select("session_id", F.col("w.start").alias("start"), "tx", "ty", "n")


def visits(samples: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Stretches without a pause longer than ``gap``."""
    return samples.groupBy("session_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("n")).select("session_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def rings_and_zones(samples: pd.DataFrame, t_c: int, g: int, eps: float, min_pts: int) -> tuple[list, list[tuple[str, float, np.ndarray]]]:
    """Outlines (slice, cluster, ring) and zones (name, area, ring) of one session's thinned samples, the slices being cut at t_c."""
    rings = []
    seg = np.minimum(samples["t_ms"].to_numpy().astype(np.int64) * g // max(t_c, 1), g - 1)
    for s in range(g):
        part = samples[seg == s]
        ids, x, y = (part[c].to_numpy() for c in ("sample_id", "x", "y"))
        if not len(ids):
            continue
        root, _, _ = label(ids, x, y, eps, min_pts)
        for r in np.unique(root[root >= 0]):
            ring = quickhull(np.stack([x[root == r], y[root == r]], axis=1))
            if area_np(ring) > 0:
                rings.append((s, int(ids[r]), ring))
    out = []
    for i, (s, a, p) in enumerate(rings):
        for t, b, q in rings[i + 1 :]:
            if s < t and area_np(z := clip(p, q)) > 0:
                out.append((f"{s}.{a}+{t}.{b}", area_np(z), z))
    return rings, out


def elastic_zones(samples: DataFrame, tick_ms: int, g: int = 3, eps: float = 20, min_pts: int = 5, t_end: int | None = None, cap_ms: int | None = None, expire_ms: int | None = None) -> DataFrame:
    """Zones of slices whose edges move with the present.

    State per session: its thinned samples. Each batch adds its samples and cuts the slices
    anew at the latest time (or ``t_end``), so zones of earlier batches are replaced, not
    extended. ``cap_ms`` is the longest session: later samples don't count, so a state holds
    cap_ms / tick_ms + 1 samples at most. A state that the watermark has left ``expire_ms``
    (default cap_ms) behind its newest sample is dropped. Output mode update.
    """
    state = "ids array<long>, xs array<double>, ys array<double>, ts array<long>, at long"
    columns = ["sample_id", "x", "y", "t_ms"]
    wait = expire_ms if expire_ms is not None else cap_ms

    def run(key: tuple, frames: Iterator[pd.DataFrame], held) -> Iterator[pd.DataFrame]:
        if held.hasTimedOut:
            held.remove()
            return
        *old, newest = held.get if held.exists else ([], [], [], [], 0)
        rows = pd.DataFrame(dict(zip(columns, old, strict=True)))
        parts = [f.dropna(subset=["sample_id", "t_ms", "at"]) for f in frames]
        new = pd.concat([x for x in (rows, *(f[columns] for f in parts)) if len(x)] or [rows])
        new = new[new["t_ms"] <= cap_ms] if cap_ms is not None else new
        newest = max([newest, *(int(f["at"].max().timestamp() * 1000) for f in parts if len(f))])
        new = new.sort_values(["t_ms", "sample_id"]).drop_duplicates("sample_id")
        kept = new[~(new["t_ms"] // tick_ms).duplicated()]
        kept = kept.astype({"sample_id": "int64", "t_ms": "int64"})
        held.update((*(kept[c].tolist() for c in columns), newest))
        if wait is not None:
            held.setTimeoutTimestamp(max(newest + wait, held.getCurrentWatermarkMs() + 1))
        if not len(kept):
            return
        t_c = t_end if t_end is not None else int(kept["t_ms"].max())
        found = rings_and_zones(kept, t_c, g, eps, min_pts)[1]
        yield pd.DataFrame([(key[0], t_c, z, a, as_ring(r)) for z, a, r in found], columns=["session_id", "t_c", "zone_id", "area", "ring"])

    return samples.groupBy("session_id").applyInPandasWithState(run, ZONES, state, "update", "NoTimeout" if wait is None else "EventTimeTimeout")


def late_rows(query) -> int:
    """Rows that the watermark has dropped so far."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def finished(query) -> None:
    """Wait for a query over stored tables; rows of those can't be late, so dropped ones are an error."""
    query.awaitTermination()
    if n := late_rows(query):
        raise RuntimeError(f"{n} rows came later than the watermark allows")


def replay(trace: DataFrame, step_ms: int, per_batch: int = 1) -> DataFrame:
    """A stored trace as a stream: each micro-batch brings the samples of the next ``per_batch`` stretches of ``step_ms``, with ``at``. The same batches come again after a restart."""
    spark = trace.sparkSession
    clock = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", per_batch).option("numPartitions", 1).option("startTimestamp", 0).option("advanceMillisPerBatch", step_ms * per_batch).load()
    rows = trace.withColumn("stretch", F.floor(F.col("t_ms") / step_ms).cast("long"))
    return clock.select(F.col("value").alias("stretch")).join(rows, "stretch").withColumn("at", F.timestamp_millis("t_ms")).drop("stretch")


def update_on_batch(step, path: str):
    """A foreachBatch function that writes ``step(batch)`` under its batch id, so a replay changes nothing."""

    def run(batch: DataFrame, batch_id: int) -> None:
        step(batch).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return run
