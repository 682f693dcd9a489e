"""Operators without SQL against plain renderings, and what the strategies must agree on."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from attention_engine.functions.distance import diversity_np, geo_distance_np
from attention_engine.functions.geometry import as_ring, clip, ring_area, ring_centroid, ring_perimeter
from attention_engine.functions.projection import ViewPort, split_antimeridian, zones_to_geo
from attention_engine.operators import feedback, highlights, measures
from attention_engine.operators.density import density_clusters, drift_guard, label
from attention_engine.operators.matching import match_audit, match_points, match_two_hulls
from attention_engine.operators.trace import thin_trace
from attention_engine.operators.zones import attention_zones, discover_zones, drawn_zones, merge_zones, with_shape
from attention_engine.plans import workloads
from attention_engine.plans.local import LocalPoints, iterate
from attention_engine.plans.pipeline import Params, State, explore, run_iteration
from attention_engine.sources import tables as T

RNG = np.random.default_rng(11)


def plain_search(lat, lon, k, scans=None, swap="first", sim=None, min_sim=None, patience=None):
    """One candidate after the other, all sums afresh."""
    def total(at):
        return sum(geo_distance_np(lat[a], lon[a], lat[b], lon[b]) for i, a in enumerate(at) for b in at[:i])

    at, done, swaps, idle = list(range(min(k, len(lat)))), 0, 0, 0
    if len(at) < 2:
        return at, 0, 0
    for c in range(k, len(lat)):
        if (scans is not None and done >= scans) or (min_sim is not None and sim[c] < min_sim) or (patience is not None and idle >= patience):
            break
        done, idle = done + 1, idle + 1
        now = total(at)
        gains = [total(at[:s] + [c] + at[s + 1 :]) - now for s in range(k)]
        better = [s for s in range(k) if gains[s] > 1e-9]
        if swap == "worst_out":
            far = [sum(geo_distance_np(lat[a], lon[a], lat[b], lon[b]) for b in at) for a in at]
            better = [s for s in better if s == int(np.argmin(far))]
        if better:
            slot = max(better, key=lambda s: gains[s]) if swap == "best" else better[0]
            at[slot], swaps, idle = c, swaps + 1, 0
    return at, done, swaps


@pytest.mark.parametrize("swap", ["first", "best", "worst_out"])
def test_search_in_blocks_is_the_plain_search(swap, monkeypatch):
    monkeypatch.setattr(highlights, "BLOCK", 16)
    for n, k, scans, patience, low in [(0, 3, None, None, None), (2, 5, None, None, None), (90, 4, None, None, None), (90, 5, 37, None, None), (120, 3, None, 11, None), (120, 3, None, None, 0.4), (40, 1, None, None, None)]:
        lat, lon, sim = 48 + RNG.random(n), 2 + RNG.random(n), np.sort(RNG.random(n))[::-1]
        got = highlights.greedy(lat, lon, k, scans, None, swap, sim=sim, min_sim=low, patience=patience)
        assert got == plain_search(lat, lon, k, scans, swap, sim, low, patience)


def test_curve_and_optimum(spark):
    lat, lon = 48 + RNG.random(60), 2 + RNG.random(60)
    rows = spark.createDataFrame([(0, i + 1, i, float(lat[i]), float(lon[i]), 1 - i / 60) for i in range(60)], "session_id long, rank int, point_id long, lat double, lon double, sim double")
    got = {(r.k, r.scans): (r.diversity_km, r.diversity_norm, r.mean_sim) for r in highlights.budget_curve(rows, [3, 5], [0, 7, 30]).collect()}
    for k in (3, 5):
        whole = diversity_np(*(x[plain_search(lat, lon, k)[0]] for x in (lat, lon)))
        for scans in (0, 7, 30, -1):
            at = plain_search(lat, lon, k, None if scans < 0 else scans)[0]
            km = diversity_np(lat[at], lon[at])
            assert np.allclose(got[k, scans], (km, km / whole, np.mean([1 - i / 60 for i in at])))
    few = rows.where("rank <= 9")
    from itertools import combinations
    sets = [(diversity_np(lat[list(c)], lon[list(c)]), np.mean([1 - i / 60 for i in c]), c) for c in combinations(range(9), 3)]
    far = max(s[0] for s in sets)
    assert {r.point_id for r in highlights.exhaustive_highlights(few, 3).collect()} == set(max(sets, key=lambda s: s[0])[2])
    assert {r.point_id for r in highlights.exhaustive_highlights(few, 3, "both", 0.3).collect()} == set(max(sets, key=lambda s: 0.3 * s[1] + 0.7 * s[0] / far)[2])
    ratio = measures.optimality(highlights.greedy_highlights(few, 3, None), highlights.exhaustive_highlights(few, 3)).first().ratio
    assert 0.5 < ratio <= 1 and np.isclose(ratio, diversity_np(*(x[plain_search(lat[:9], lon[:9], 3)[0]] for x in (lat, lon))) / far)


def plain_clusters(rows, eps, min_pts, metric, eps_t):
    def near(a, b):
        dx, dy = abs(a[1] - b[1]), abs(a[2] - b[2])
        d = {"l2": (dx * dx + dy * dy) ** 0.5, "l1": dx + dy, "linf": max(dx, dy)}[metric]
        return d <= eps and (eps_t is None or abs(a[3] - b[3]) <= eps_t), d

    core = {a[0] for a in rows if sum(near(a, b)[0] for b in rows) >= min_pts}
    name = {i: i for i in core}
    by = {r[0]: r for r in rows}
    while True:
        nxt = {i: min(name[j] for j in core if near(by[i], by[j])[0]) for i in core}
        if nxt == name:
            break
        name = nxt
    out = {}
    for a in rows:
        if a[0] in core:
            out[a[0]] = (name[a[0]], "core")
        else:
            around = sorted((near(a, by[j])[1], j) for j in core if near(a, by[j])[0])
            out[a[0]] = (name[around[0][1]], "border") if around else (None, "noise")
    return out


@pytest.mark.parametrize(("metric", "eps_t"), [("l2", None), ("l1", None), ("linf", None), ("l2", 40)])
def test_clusters(spark, metric, eps_t):
    rng = np.random.default_rng(5)
    rows = [(k, float(x), float(y), int(t)) for k, (x, y, t) in enumerate(zip(rng.integers(0, 90, 170), rng.integers(0, 60, 170), rng.integers(0, 100, 170), strict=True))]
    rows += [(170 + k, 30.0 + k % 3, 20.0 + k % 2, k) for k in range(40)]  # full cells
    want = plain_clusters(rows, 8, 4, metric, eps_t)
    trace = spark.createDataFrame([(0, i, x, y, t, "m", 0) for i, x, y, t in rows] + [(0, 999, None, 1.0, 5, "m", 0)], T.TRACE + ", seg int")
    for strategy in ("local", "grid"):
        got = {r.sample_id: (r.cluster_id, r.role) for r in density_clusters(trace, 8, 4, eps_t, strategy, metric).collect()}
        assert got.pop(999) == (None, "noise") and got == want, strategy


def test_stripes_and_drift_guard(monkeypatch):
    from attention_engine.operators import density

    ids, x, y = np.arange(300)[::-1].copy(), RNG.random(300) * 60, RNG.random(300) * 60
    whole = label(ids, x, y, 5, 4)
    monkeypatch.setattr(density, "CELLS", 700)
    assert all((a == b).all() for a, b in zip(whole, label(ids, x, y, 5, 4), strict=True))
    root, value = np.array([0, 0, 0, 0, -1, 5, 5]), np.array([1.0, 2, 9, 1, 5, 3, 3])
    assert drift_guard(root, np.arange(7), value, 3.0).tolist() == [0, 0, -1, 0, -1, 5, 5]


def test_min_gap(spark):
    times = np.cumsum(RNG.integers(0, 120, 200)).tolist()
    want, last = [], None
    for t in times:
        if last is None or t >= last + 200:
            want.append(t)
            last = t
    trace = spark.createDataFrame([(0, i, 0.0, 0.0, t, "m") for i, t in enumerate(times)], T.TRACE)
    assert sorted(r.t_ms for r in thin_trace(trace, 200, "min_gap").collect()) == want


def square(x, y, side):
    return [(x, y), (x + side, y), (x + side, y + side), (x, y + side)]


def test_zones_of_squares(spark):
    """Three squares that share 2 by 2, merged groups, measures of rings, drawn zones and degrees."""
    rings = [(0, 0, 1, square(0, 0, 10)), (0, 1, 2, square(8, 8, 10)), (0, 2, 3, square(0, 8, 10)), (0, 2, 4, square(100, 100, 5))]
    df = spark.createDataFrame([(s, g, c, 4, [{"x": float(x), "y": float(y)} for x, y in r]) for s, g, c, r in rings], "session_id long, seg int, cluster_id long, n long, ring array<struct<x:double,y:double>>")
    shaped = with_shape(df)
    assert [(r.zone_id, r.area) for r in attention_zones(shaped, 3).collect()] == [("0.1+1.2+2.3", 4.0)]
    pairs = attention_zones(shaped)
    assert sorted((r.zone_id, r.area) for r in pairs.collect()) == [("0.1+1.2", 4.0), ("0.1+2.3", 20.0), ("1.2+2.3", 20.0)]
    drawn = drawn_zones([(0, "a", square(0, 0, 4)), (0, "b", square(3, 3, 4)), (0, "c", square(6, 6, 4)), (0, "d", square(50, 0, 4)), (0, "e", square(54, 0, 4))], spark)
    assert {r.zone_id: r.zone_group for r in merge_zones(drawn).collect()} == {"a": "a", "b": "a", "c": "a", "d": "d", "e": "e"}
    tri = spark.createDataFrame([([{"x": 0.0, "y": 0.0}, {"x": 3.0, "y": 0.0}, {"x": 0.0, "y": 4.0}],)], "ring array<struct<x:double,y:double>>")
    r = tri.select(ring_area(F.col("ring")).alias("a"), ring_perimeter(F.col("ring")).alias("p"), ring_centroid(F.col("ring")).alias("c")).first()
    assert np.allclose((r.a, r.p, r.c.x, r.c.y), (6, 12, 1, 4 / 3))
    geo = zones_to_geo(drawn, ViewPort(0.0, 180.0, 1.0)).orderBy("zone_id").select("zone_id", "geo_ring")
    parts = split_antimeridian(geo).where("zone_id = 'a'").select("west", "east").collect()
    assert sorted((p.west, p.east) for p in parts) == [(-180.0, -176.0), (180.0, 180.0)] or sorted((p.west, p.east) for p in parts) == [(-180.0, -176.0)]
    assert np.allclose(clip(np.array(square(0, 0, 2), float), np.array(square(1, 1, 2), float)).max(axis=0), 2) and as_ring(np.zeros((0, 2))) == []


def test_matching_far_outside_and_without_place(spark):
    """Points and zones beyond any screen, and points without a place; all strategies agree with a plain test."""
    rng = np.random.default_rng(2)
    spots = [(float(x), float(y)) for x, y in rng.normal(0, 900, (400, 2))] + [(None, 1.0), (2.0, None), (float("nan"), 3.0)]
    corners = [(float(x), float(y), float(s)) for x, y, s in zip(rng.normal(0, 1500, 30), rng.normal(0, 1500, 30), rng.choice([3, 80, 900], 30), strict=True)] + [(-9000.0, -9000.0, 18000.0)]
    zones = drawn_zones([(k % 3, f"z{k}", square(x, y, s)) for k, (x, y, s) in enumerate(corners)], spark).cache()
    want = {(k % 3, f"z{k}", i) for k, (x, y, s) in enumerate(corners) for i, (px, py) in enumerate(spots) if px is not None and py is not None and x < px < x + s and y < py < y + s}
    points = spark.createDataFrame([(i, *p) for i, p in enumerate(spots)], "point_id long, x double, y double").cache()
    for how in ({"strategy": "exhaustive"}, {"strategy": "bbox"}, {"strategy": "auto"}, {}, {"bounds": (-512.0, -512.0, 512.0, 512.0)}, {"accept_full_cells": True, "capacity": 4}, {"capacity": 8, "max_depth": 2, "hot": 9}):
        got = match_points(points, zones, **how)
        assert {tuple(r) for r in got.collect()} == want, how
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "CartesianProduct" not in plan
    status = {r.point_id: r.status for r in match_audit(points, zones.where("zone_id <> 'z30'")).collect()}
    assert len(status) == len(spots) and status[400] == "untested"
    assert {i for i, s in status.items() if s == "inside"} == {i for _, z, i in want if z != "z30"}


def test_lists_of_vectors_reach_recall(spark):
    for sf in ("sf0.001", "sf0.01"):
        points = T.points_embeddings(spark, f"/root/testdata/{sf}")
        asked = points.where("point_id % 20 = 0")
        rows = points.select("point_id", "embedding").toPandas()
        e = np.array(rows["embedding"].tolist(), float)
        ids = rows["point_id"].to_numpy()
        want = []
        for i in np.flatnonzero(ids % 20 == 0):
            d = ((e - e[i]) ** 2).sum(axis=1)
            d[i] = np.inf
            want += [(int(ids[i]), int(j)) for j in ids[np.lexsort((ids, d))[:5]]]
        truth = spark.createDataFrame(want, "owner long, point_id long")
        got = highlights.approximate_lists(points, "embedding", asked, depth=5)
        assert measures.list_recall(got, truth).agg(F.avg("recall")).first()[0] >= 0.9


def test_every_session_is_answered(spark):
    """A session without a zone starts from its smallest unseen id; matched points are passed over."""
    points = spark.createDataFrame([(i, 48.0 + i / 100, 2.0, "ab"[i % 2]) for i in range(9)], "point_id long, lat double, lon double, kind string")
    spec = [feedback.Facet("kind", "kind")]
    found = spark.createDataFrame([(1, 0), (1, 2), (1, 6), (2, 0), (2, 1)], "session_id long, point_id long")
    vector = feedback.update_feedback(None, found.where("session_id = 1"), feedback.facetize(points, spec))
    sessions = spark.createDataFrame([(1,), (2,), (3,)], "session_id long")
    got = {r.session_id: (r.anchor, r.sim_f) for r in highlights.anchors(points, vector, spec, found, sessions).collect()}
    assert got == {1: (4, 1.0), 2: (2, 0.0), 3: (0, 0.0)}
    starts = highlights.anchors(points, vector, spec, found, sessions).cache()
    whole = highlights.search_highlights(points, spec, starts, found, 3, None).collect()
    short = highlights.search_highlights(points, spec, starts, found, 3, None, depth=4).collect()
    key = lambda rows: sorted((r.session_id, r.slot, r.point_id, r.scans) for r in rows)
    assert key(whole) == key(short) and {r.session_id for r in whole} == {1, 2, 3}


def test_iterations(spark):
    """The local iteration is run_iteration; since="last" finds zones in a third iteration; drift of the vectors."""
    sf = "/root/testdata/sf0.01"
    points = T.first_n(T.points_part(spark, sf), 1000).cache()
    trace = T.trace_view(spark, sf).where("session_id < 2").cache()
    params = Params(every_ms=T.TICK, time_limit_ms=None, max_scans=60)
    rows, _ = run_iteration(State(), T.T_C, trace, points, T.PART_SPEC, params)
    got = {}
    for r in rows.collect():
        got.setdefault(r.session_id, set()).add(r.point_id)
    held = LocalPoints(points.select("point_id", "x", "y", "lat", "lon", feedback.signature(T.PART_SPEC).alias("facets")).orderBy("point_id").toPandas())
    samples = trace.toPandas()
    for s in (0, 1):
        shown, _ = iterate(held, samples[samples["session_id"] == s], T.T_C, 3, 20, 5, 5, 60, T.TICK)
        assert set(shown.tolist()) == got[s]
    from dataclasses import replace

    chosen, log = explore(T.trace_view(spark, sf, pooled=4), points, [T.T_C // 3, 2 * T.T_C // 3, T.T_C], T.PART_SPEC, replace(params, since="last", min_pts=4))
    assert {r.iter for r in chosen.collect()} == {0, 1, 2}
    assert log.where("iter = 2").count() >= log.where("iter = 1").count() > 0
    raw = T.trace_view(spark, sf, pooled=4)
    third = lambda rows, **how: discover_zones(rows, T.T_C, 3, 25, 4, None, **how).count()
    assert third(raw, t_0=2 * T.T_C // 3) > 0 and third(raw.where(F.col("t_ms") > 2 * T.T_C // 3)) == 0
    drift = feedback.preference_drift(log.withColumn("at", F.expr("make_timestamp(2024, 1 + iter, 1, 0, 0, 0)")))
    assert drift.where("change is not null").count() > 0


def test_two_hulls_agree(spark):
    zones, points = workloads.running_example(spark)
    assert zones.count() == 4 and match_points(points, zones).count() == 10
    assert measures.agreement(match_points(points, zones).select("point_id"), match_points(points, zones, "bbox").select("point_id")).first().recall == 1.0
