"""Jobs that were refused, or whose work grew faster than the tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from attention_engine.operators import feedback, highlights
from attention_engine.plans.queries import QUERIES
from attention_engine.sources import tables as T


def test_visitors_are_counted_exactly(spark, tmp_path):
    """a sketch of 2**18 is no longer exact at 400,000 users."""
    ids = spark.range(400_000).select(F.when(F.col("id") % 4 == 0, "view").otherwise("click").alias("event_type"), (F.col("id") * 7).alias("user_id"))
    none = spark.createDataFrame([("error", None), ("click", None)], "event_type string, user_id long")
    ids.unionByName(ids.limit(1000)).unionByName(none).write.parquet(f"{tmp_path}/events.parquet")
    got = {r.event_type: r.visitors for r in QUERIES["approx_visitors"](spark, str(tmp_path)).collect()}
    assert got == {"view": 100_000, "click": 300_000, "error": 0}


def test_full_lists_of_many_points(spark, monkeypatch):
    """more than MAX_FULL points were refused though the lists have a depth."""
    points = T.points_supplier(spark, "/root/testdata/sf0.1")
    want = sorted(map(tuple, highlights.build_neighbours(points.where("point_id < 90"), T.SUPPLIER_SPEC, "full", 20).collect()))
    monkeypatch.setattr(highlights, "MAX_FULL", 60)
    assert sorted(map(tuple, highlights.build_neighbours(points.where("point_id < 90"), T.SUPPLIER_SPEC, "full", 20).collect())) == want
    with pytest.raises(ValueError):
        highlights.build_neighbours(points, T.SUPPLIER_SPEC, "full")


@pytest.mark.parametrize("reach", [None, 120.0])
def test_nearest_points(spark, reach):
    """Crowds, equal places and points, and all of the reach (110 was missed with a reach of 120)."""
    points = [(i, float(i * 37 % 100) / 10, float(i * i % 97) / 10) for i in range(300)] + [(900, 500.0, 500.0), (901, 500.0, 500.0), (902, -300.0, 20.0)]
    places = [(k % 2, k, float(k * 13 % 50) / 5, float(k * 7 % 60) / 6) for k in range(80)] + [(0, 100, 610.0, 500.0), (1, 101, 610.0, 500.0), (0, 102, -900.0, 20.0), (0, 103, None, 1.0)]
    want = set()
    for s, k, x, y in places[:-1]:
        d, i = min(((x - px) ** 2 + (y - py) ** 2, i) for i, px, py in points)
        if reach is None or d <= reach * reach:
            want.add((s, k, i))
    got = feedback.nearest_points(spark.createDataFrame(places, "session_id long, sample_id long, x double, y double"), spark.createDataFrame(points, "point_id long, x double, y double"), reach=reach)
    assert sorted(map(tuple, got.collect())) == sorted(want)


def test_facets_are_not_broadcast(spark):
    """Four rows a point look like one to the planner; at 1.2 million points they filled the driver."""
    points = T.points_part(spark, "/root/testdata/sf0.01")
    facets = feedback.facetize(points, T.PART_SPEC)
    found = spark.range(50).select(F.lit(0).cast("long").alias("session_id"), F.col("id").alias("point_id"))
    vector = spark.createDataFrame([(0, "beds", "1", 1.0)], "session_id long, attr string, val string, weight double")
    for df in (feedback.increments(found, facets), highlights.explain_highlights(found, facets, vector)):
        assert "SortMergeJoin" in df._jdf.queryExecution().executedPlan().toString()
        assert df.count() > 0


@pytest.mark.parametrize("how", ["", "_softmax"])
def test_toy_vectors_read_a_table(spark, how):
    """the homes were made up in the code."""
    rows = QUERIES[f"toy_vector{how}"](spark, "/root/testdata/sf0.01")
    assert any(f.endswith("part.parquet") for f in rows.inputFiles())
    sums = rows.groupBy("session_id").agg(F.sum("weight").alias("w"), F.count("*").alias("n")).collect()
    assert len(sums) == 500 and all(abs(r.w - 1) < 1e-4 for r in sums)
    assert {r.n for r in sums} == {14} if how else max(r.n for r in sums) <= 12


def test_small_slices_share_a_call(spark):
    """a Python call per slice; and a slice over several batches stays whole."""
    from attention_engine.operators.density import density_clusters

    rows = [(s, s * 100 + i, float(i % 4), float(i // 4), i, "m", g) for s in range(5) for g in range(2) for i in range(3 + 9 * s * (g + 1) % 40)]
    trace = spark.createDataFrame(rows, T.TRACE + ", seg int")
    assert "FlatMapGroupsInPandas" not in density_clusters(trace, 1.5, 4)._jdf.queryExecution().executedPlan().toString()
    cols = ["session_id", "seg", "sample_id", "cluster_id", "role"]
    whole = sorted(map(str, density_clusters(trace, 1.5, 4).select(cols).collect()))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        assert sorted(map(str, density_clusters(trace, 1.5, 4).select(cols).collect())) == whole
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    grid = sorted(map(str, density_clusters(trace, 1.5, 4, strategy="grid").select(cols).collect()))
    assert grid == whole and len(whole) == len(rows)


def test_lists_of_vectors_by_tiles(spark, monkeypatch):
    """F8: every pair was joined once for each bucket it shares; tiles measure it once and give the lists of plain comparison."""
    rng = np.random.default_rng(3)
    e = rng.normal(size=(160, 8))
    e /= np.linalg.norm(e, axis=1)[:, None]
    e[100:130] = e[0]  # copies
    e[-1] = 40.0  # shares no bucket
    e = e.astype(np.float32).astype(float)
    points = spark.createDataFrame([(i, v) for i, v in enumerate(e.tolist())] + [(999, None)], "point_id long, e array<double>")
    monkeypatch.setattr(highlights, "TILE_ROWS", 50)
    monkeypatch.setattr(highlights, "TILE_OWNERS", 9)
    monkeypatch.setattr(highlights, "TILE_CELLS", 300)
    lists = highlights.approximate_lists(points, "e", points.where("point_id % 3 = 0"), tables=20, depth=5)
    got = {}
    for r in lists.orderBy("owner", "rank").collect():
        got.setdefault(r.owner, []).append((r.point_id, round(r.sim, 9)))
    want = {}
    for i in range(0, 160, 3):
        d = np.sqrt(((e - e[i]) ** 2).sum(axis=1))
        d[i] = np.inf
        want[i] = [(int(j), round(-float(d[j]), 9)) for j in np.lexsort((np.arange(160), np.round(d, 12)))[:5]]
    assert got == want
    assert "FlatMapCoGroupsInArrow" in lists._jdf.queryExecution().toString()
    assert highlights.approximate_lists(points.limit(0), "e").count() == 0
    ragged = spark.createDataFrame([(0, [1.0, 0.0]), (1, [1.0]), (2, [0.0, 1.0, 0.0])], "point_id long, e array<double>")
    with pytest.raises(Exception, match="different lengths"):
        highlights.approximate_lists(ragged, "e", depth=1).collect()


def test_all_points_have_lists_of_vectors(spark):
    """only points whose id is divisible by 20 had a list; and rows screened by rounded products are the nearest ones."""
    from __spark_entry__ import queries

    lists = queries()["neighbour_list_approximate"](spark, "/root/testdata/sf0.001").collect()
    rows = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").orderBy("vec_id").toPandas()
    assert sorted((r.owner, r["rank"]) for r in lists) == [(i, k) for i in rows.vec_id for k in range(1, 6)]
    e = np.array(rows.embedding.tolist(), float)
    far = np.sqrt(((e[:, None] - e) ** 2).sum(axis=2))
    np.fill_diagonal(far, np.inf)
    want = {(int(i), int(j)) for i, d in zip(rows.vec_id, far, strict=True) for j in rows.vec_id.to_numpy()[np.lexsort((rows.vec_id, np.round(d, 12)))[:5]]}
    assert len({(r.owner, r.point_id) for r in lists} & want) >= 0.9 * len(want)
    rng = np.random.default_rng(2)
    for n, width, bucket in ((3000, 8, 1.2), (3000, 8, 0.1), (3000, 8, 0.001), (1500, 3, 1e9)):
        b = rng.normal(size=(n, width)) * (1e9 if bucket > 2 else 1.0)
        b[200:900], b[5], ids = b[199], np.nan, rng.permutation(n)  # many copies, one vector that isn't finite
        ids[n - 40 :] = ids[n - 40]  # rows of one id
        at, directions = rng.integers(0, n, 120), rng.normal(size=(width, 6))
        got = list(zip(*(x.tolist() for x in highlights.nearest_in_tile(ids[at], b[at], ids, b, directions, bucket, 4)), strict=True))
        plain, cell = [], np.floor(b @ directions / bucket)
        for k in at[at != 5]:
            d = np.round(np.sqrt(((b - b[k]) ** 2).sum(axis=1)), 12)
            met = (cell == cell[k]).any(axis=1)
            pool = [j for j in np.lexsort((ids, d)) if ids[j] != ids[k] and np.isfinite(d[j])]
            near = [j for j in pool if met[j]]
            plain += [(int(ids[k]), int(ids[j]), bool(met[j])) for j in (near[:4] if len(near) >= 4 else [j for r, j in enumerate(pool) if r < 4 or met[j]])]
        assert sorted((o, p, m) for o, p, _, m in got) == sorted(plain), (n, width, bucket)


def test_softmax_of_counts_beyond_the_range_of_exp(spark):
    """exp of a count over 709 has no double, so weights are taken from differences to the largest count."""
    raw = [768.0, 767.0, 719.0, 1.0]
    rows = spark.createDataFrame([(1, "a", str(k), x) for k, x in enumerate(raw)], "session_id long, attr string, val string, raw double")
    want = np.exp(np.array(raw) - 768) / np.exp(np.array(raw) - 768).sum()
    for how in ("softmax", "softmax_touched"):
        got = [r.weight for r in feedback.normalise(rows, how).orderBy("val").collect()]
        assert np.allclose(got, want, atol=1e-15)
