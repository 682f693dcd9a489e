"""Density clusters of the samples of a slice.

A sample with at least ``min_pts`` samples within ``eps`` (itself included) is a core;
cores within ``eps`` of each other share a cluster, which is named by its smallest core; a
border sample goes to the cluster of its nearest core (ties: smallest id).

Samples whose place or time is null are noise. An empty trace gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..keep import keep

ADDED = {"cluster_id": "long", "role": "string"}


def _schema(df: DataFrame) -> str:
    return ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields] + [f"{k} {v}" for k, v in ADDED.items()])


def _apart(x: np.ndarray, y: np.ndarray, metric: str, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """A value that orders pairs by distance; squared for l2."""
    dx, dy = x[rows][:, None] - x[cols][None, :], y[rows][:, None] - y[cols][None, :]
    if metric == "l2":
        return dx * dx + dy * dy
    return np.abs(dx) + np.abs(dy) if metric == "l1" else np.maximum(np.abs(dx), np.abs(dy))


#: Distances that are in memory at once.
CELLS = 1 << 22


def label(ids: np.ndarray, x: np.ndarray, y: np.ndarray, eps: float, min_pts: int, t: np.ndarray | None = None, eps_t: float | None = None, metric: str = "l2") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place of the labelling core or -1, is core, is border) of one slice; a stripe of the distance matrix is held at a time."""
    n, limit = len(ids), eps * eps if metric == "l2" else eps
    stripe = max(1, CELLS // max(n, 1))

    def near(rows: np.ndarray, cols: np.ndarray):
        """(rows, distances, is near) for stripes of rows."""
        for a in range(0, len(rows), stripe):
            r = rows[a : a + stripe]
            d = _apart(x, y, metric, r, cols)
            close = d <= limit
            if eps_t is not None:
                close &= np.abs(t[r][:, None] - t[cols][None, :]) <= eps_t
            yield r, d, close

    every, core = np.arange(n), np.zeros(n, bool)
    for r, _, close in near(every, every):
        core[r] = close.sum(axis=1) >= min_pts
    root = np.full(n, -1)
    left = np.flatnonzero(core)
    for seed in (order := np.argsort(ids, kind="stable"))[core[order]]:
        if root[seed] >= 0:
            continue
        wave = np.array([seed])
        while len(wave):
            root[wave] = seed
            left = left[root[left] < 0]
            hit = np.zeros(len(left), bool)
            for _, _, close in near(wave, left):
                hit |= close.any(axis=0)
            wave = left[hit]
    border, cores = np.zeros(n, bool), np.flatnonzero(core)
    cores = cores[np.argsort(ids[cores], kind="stable")]  # ties of distance go to the smallest id
    for r, d, close in near(np.flatnonzero(~core), cores):
        d = np.where(close, d, np.inf)
        some = close.any(axis=1)
        border[r] = some
        if some.any():
            root[r[some]] = root[cores[d[some].argmin(axis=1)]]
    return root, core, border


def drift_guard(root: np.ndarray, ids: np.ndarray, value: np.ndarray, most: float) -> np.ndarray:
    """Members taken in id order; one whose value is further than ``most`` from the mean so far becomes noise."""
    out = root.copy()
    for r in np.unique(root[root >= 0]):
        total = count = 0
        for k in np.flatnonzero(root == r)[np.argsort(ids[root == r])]:
            if count and abs(value[k] - total / count) > most:
                out[k] = -1
                continue
            total, count = total + value[k], count + 1
    return out


def by_slices(rows: DataFrame, run: Callable[[pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
    """Hands whole slices to ``run``, many small ones at once: a call per slice costs more than its work. The rows of a slice that goes on in the next batch wait for it."""
    key = ["session_id", "seg"]

    def each(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        waiting: list[pd.DataFrame] = []
        for pdf in frames:
            if not len(pdf):
                continue
            if waiting and pd.concat([waiting[-1][key].tail(1), pdf[key].head(1)]).drop_duplicates().shape[0] > 1:
                yield run(pd.concat(waiting, ignore_index=True))
                waiting = []
            same = pdf.groupby(key, dropna=False, sort=False).ngroup().to_numpy()
            last = int(np.flatnonzero(same == same[-1])[0])
            if last:
                yield run(pd.concat([*waiting, pdf.iloc[:last]], ignore_index=True))
                waiting = []
            waiting.append(pdf.iloc[last:])
        if waiting:
            yield run(pd.concat(waiting, ignore_index=True))

    return rows.repartition("session_id").sortWithinPartitions(*key).mapInPandas(each, schema)


def density_clusters(trace: DataFrame, eps: float = 20, min_pts: int = 5, eps_t: float | None = None, strategy: str = "local", metric: str = "l2", delta_mean: float | None = None, value_col: str = "t_ms") -> DataFrame:
    """Adds cluster_id (null: noise) and role. local: one group per slice; grid: joins of cells, for slices of any size (without the guard of ``delta_mean``)."""
    if strategy == "grid":
        if delta_mean is not None:
            raise ValueError("the guard on the mean goes through a cluster in order; use strategy='local'")
        return grid_clusters(trace, eps, min_pts, eps_t, metric)
    if strategy != "local":
        raise ValueError(f"unknown strategy {strategy!r}")
    if metric not in SIDES:
        raise ValueError(f"unknown metric {metric!r}; one of {sorted(SIDES)}")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, x, y, t = pdf["sample_id"].to_numpy(), *(pdf[c].to_numpy(float) for c in ("x", "y", "t_ms"))
        value = None if delta_mean is None else pdf[value_col].to_numpy(float)
        root, core, border = np.full(len(ids), -1), np.zeros(len(ids), bool), np.zeros(len(ids), bool)
        at = pdf.groupby(["session_id", "seg"], dropna=False, sort=False).ngroup().to_numpy()
        starts = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
        for a, b in zip(starts, np.r_[starts[1:], len(ids)], strict=True):
            if b - a < min_pts:  # no core, so all are noise
                continue
            with np.errstate(invalid="ignore"):
                own, core[a:b], border[a:b] = label(ids[a:b], x[a:b], y[a:b], eps, min_pts, t[a:b], eps_t, metric)
            if value is not None:
                own = drift_guard(own, ids[a:b], value[a:b], delta_mean)
            root[a:b] = np.where(own >= 0, own + a, -1)
        inside = root >= 0
        cluster = pd.Series(np.where(inside, ids[root], 0), index=pdf.index, dtype="Int64").mask(~inside)
        return pdf.assign(cluster_id=cluster, role=np.where(inside & core, "core", np.where(inside & border, "border", "noise")))

    return by_slices(trace, run, _schema(trace))


def neighbour_pairs(trace: DataFrame, eps: float, eps_t: float | None = None) -> DataFrame:
    """Ordered pairs (i, j, d2) within ``eps``, self included; each sample is sent to its 9 tiles on one side only."""
    tile = lambda c: F.floor(F.col(c) / eps).cast("long")
    around = F.array(*[F.lit(k).cast("long") for k in (-1, 0, 1)])
    home = trace.select("session_id", "seg", F.col("sample_id").alias("i"), F.col("x").alias("xi"), F.col("y").alias("yi"), F.col("t_ms").alias("ti"), tile("x").alias("tx"), tile("y").alias("ty"))
    sent = trace.select("session_id", "seg", F.col("sample_id").alias("j"), F.col("x").alias("xj"), F.col("y").alias("yj"), F.col("t_ms").alias("tj"), F.explode(F.transform(around, lambda k: k + tile("x"))).alias("tx"), tile("y").alias("ty0"))
    sent = sent.withColumn("ty", F.explode(F.transform(around, lambda k: k + F.col("ty0")))).drop("ty0")
    d2 = (F.col("xi") - F.col("xj")) * (F.col("xi") - F.col("xj")) + (F.col("yi") - F.col("yj")) * (F.col("yi") - F.col("yj"))
    pairs = home.join(sent, ["session_id", "seg", "tx", "ty"]).withColumn("d2", d2).where(F.col("d2") <= eps * eps)
    if eps_t is not None:
        pairs = pairs.where(F.abs(F.col("ti") - F.col("tj")) <= eps_t)
    return pairs.select("session_id", "seg", "i", "j", "d2")


def neighbour_counts(trace: DataFrame, eps: float, eps_t: float | None = None) -> DataFrame:
    return neighbour_pairs(trace, eps, eps_t).groupBy("session_id", "seg", F.col("i").alias("sample_id")).agg(F.count("*").alias("neighbours"))


#: Side of a cell whose samples are all within 1 of each other, by metric.
SIDES = {"l2": 0.5**0.5, "l1": 0.5, "linf": 1.0}


def _distance(metric: str) -> Column:
    """A value that orders pairs (x1, y1), (x2, y2) by distance; squared for l2."""
    dx, dy = F.col("x1") - F.col("x2"), F.col("y1") - F.col("y2")
    if metric == "l2":
        return dx * dx + dy * dy
    return F.abs(dx) + F.abs(dy) if metric == "l1" else F.greatest(F.abs(dx), F.abs(dy))


def _settle(edges: DataFrame, nodes: DataFrame, key: list[str], max_rounds: int) -> DataFrame:
    """(key, cell, top) for all nodes: the smallest cell of each one's component, by spreading minima with pointer jumping."""
    edges = keep(edges.unionByName(edges.select(*key, F.col("b").alias("a"), F.col("a").alias("b"))).unionByName(nodes.select(*key, F.col("cell").alias("a"), F.col("cell").alias("b"))).distinct(), "edges")
    tops = keep(edges.groupBy(*key, F.col("a").alias("cell")).agg(F.min("b").alias("top")), "tops")
    for _ in range(max_rounds):
        around = edges.join(tops.select(*key, F.col("cell").alias("b"), "top"), [*key, "b"]).groupBy(*key, F.col("a").alias("cell")).agg(F.min("top").alias("top"))
        jump = around.join(tops.select(*key, F.col("cell").alias("top"), F.col("top").alias("further")), [*key, "top"], "left")
        nxt = keep(jump.select(*key, "cell", F.least("top", F.coalesce("further", "top")).alias("top")), "tops")
        if nxt.join(tops.withColumnRenamed("top", "old"), [*key, "cell"]).where("top <> old").isEmpty():
            return nxt
        tops = nxt
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def grid_clusters(trace: DataFrame, eps: float, min_pts: int, eps_t: float | None = None, metric: str = "l2", max_rounds: int = 100) -> DataFrame:
    """Clusters by cells so small that the samples of one are all neighbours (and, with ``eps_t``, as short in time).

    A cell with ``min_pts`` samples holds cores only, so pairs are formed just for the samples
    of the other cells, of which a cell has fewer than ``min_pts``: their number grows with
    the samples. Two full cells near each other are compared as wholes, no pair leaves that
    comparison. Components are those of cells, not of samples.
    """
    if metric not in SIDES:
        raise ValueError(f"unknown metric {metric!r}; one of {sorted(SIDES)}")
    key, side, limit = ["session_id", "seg"], eps * SIDES[metric], eps * eps if metric == "l2" else eps
    reach = 1 if metric == "linf" else 2
    spot = F.array(F.floor(F.col("x") / side).cast("long"), F.floor(F.col("y") / side).cast("long"), (F.floor(F.col("t_ms") / eps_t) if eps_t else F.lit(0)).cast("long"))
    some = F.col("x").isNotNull() & F.col("y").isNotNull() & F.col("t_ms").isNotNull()
    rows = trace.where(some).select(*key, F.col("sample_id").alias("i"), F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), F.col("t_ms").alias("t"), spot.alias("cell"))
    sizes = rows.groupBy(*key, "cell").agg(F.count("*").alias("in_cell"))
    rows = keep(rows.join(sizes, [*key, "cell"]), "cells")
    full = rows.where(F.col("in_cell") >= min_pts)
    steps = [(a, b, c) for a in range(-reach, reach + 1) for b in range(-reach, reach + 1) for c in ((-1, 0, 1) if eps_t else (0,))]
    around = F.array(*[F.array(F.col("cell")[0] + a, F.col("cell")[1] + b, F.col("cell")[2] + c) for a, b, c in steps])
    sparse = rows.where(F.col("in_cell") < min_pts).select(*key, F.col("i").alias("i"), F.col("x").alias("x1"), F.col("y").alias("y1"), F.col("t").alias("t1"), F.col("cell").alias("home"), F.explode(around).alias("cell"))
    met = sparse.join(rows.select(*key, "cell", F.col("i").alias("j"), F.col("x").alias("x2"), F.col("y").alias("y2"), F.col("t").alias("t2"), "in_cell"), [*key, "cell"]).withColumn("d", _distance(metric)).where(F.col("d") <= limit)
    if eps_t:
        met = met.where(F.abs(F.col("t1") - F.col("t2")) <= eps_t)
    met = keep(met.select(*key, "i", "j", "d", "home", "cell", "in_cell"), "pairs")
    few = met.groupBy(*key, "i").agg(F.count("*").alias("n")).where(F.col("n") >= min_pts).select(*key, "i")
    cores = keep(full.select(*key, "i", "cell").unionByName(rows.where(F.col("in_cell") < min_pts).join(few, [*key, "i"], "left_semi").select(*key, "i", "cell")), "cores")
    core_j = cores.select(*key, F.col("i").alias("j"))
    to_core = met.join(core_j, [*key, "j"], "left_semi")
    edges = to_core.join(few, [*key, "i"], "left_semi").select(*key, F.col("home").alias("a"), F.col("cell").alias("b")).distinct()
    dense = full.select(*key, "cell").distinct()
    forward = F.array(*[F.array(F.col("cell")[0] + a, F.col("cell")[1] + b, F.col("cell")[2] + c) for a, b, c in steps if (a, b, c) > (0, 0, 0)])
    pairs = dense.select(*key, F.col("cell").alias("a"), F.explode(forward).alias("b")).join(dense.withColumnRenamed("cell", "b"), [*key, "b"])
    left = full.select(*key, F.col("cell").alias("a"), "x", "y", "t").join(pairs, [*key, "a"]).withColumn("first", F.lit(True))
    right = full.select(*key, F.col("cell").alias("b"), "x", "y", "t").join(pairs, [*key, "b"]).withColumn("first", F.lit(False))

    def touch(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y, t = (pdf[c].to_numpy(float) for c in ("x", "y", "t"))
        one, two = np.flatnonzero(pdf["first"]), np.flatnonzero(~pdf["first"])
        for k in range(0, len(one), max(1, CELLS // max(len(two), 1))):
            r = one[k : k + max(1, CELLS // max(len(two), 1))]
            near = _apart(x, y, metric, r, two) <= limit
            if eps_t:
                near &= np.abs(t[r][:, None] - t[two][None, :]) <= eps_t
            if near.any():
                return pdf.iloc[:1][[*key, "a", "b"]]
        return pdf.iloc[:0][[*key, "a", "b"]]

    shape = [*key, "a", "b", "x", "y", "t", "first"]
    kind = {f.name: f.dataType.simpleString() for f in trace.schema.fields}
    touching = left.select(shape).unionByName(right.select(shape)).groupBy(*key, "a", "b").applyInPandas(touch, ", ".join(f"{c} {kind[c]}" for c in key) + ", a array<long>, b array<long>")
    tops = _settle(edges.unionByName(touching), cores.select(*key, "cell").distinct(), key, max_rounds)
    named = cores.join(tops, [*key, "cell"])
    names = named.groupBy(*key, "top").agg(F.min("i").alias("cluster_id"))
    named = keep(named.join(names, [*key, "top"]).select(*key, "i", "cluster_id"), "named")
    edge = to_core.join(few, [*key, "i"], "left_anti").join(named.select(*key, F.col("i").alias("j"), "cluster_id"), [*key, "j"])
    border = edge.groupBy(*key, "i").agg(F.min_by("cluster_id", F.struct("d", "j")).alias("cluster_id"))
    found = named.select(*key, "i", "cluster_id", F.lit("core").alias("role")).unionByName(border.select(*key, "i", "cluster_id", F.lit("border").alias("role"))).withColumnRenamed("i", "sample_id")
    return trace.join(found, [*key, "sample_id"], "left").withColumn("role", F.coalesce("role", F.lit("noise"))).select(*trace.columns, "cluster_id", "role")


def cluster_stats(clusters: DataFrame) -> DataFrame:
    """Size, centre, extent and time span of each cluster."""
    return clusters.where("cluster_id is not null").groupBy("session_id", "seg", "cluster_id").agg(
        F.count("*").alias("n"), F.count(F.when(F.col("role") == "core", 1)).alias("cores"), F.avg("x").alias("cx"), F.avg("y").alias("cy"),
        (F.max("x") - F.min("x")).alias("width"), (F.max("y") - F.min("y")).alias("height"), (F.max("t_ms") - F.min("t_ms")).alias("span_ms"),
    )
