"""Sources, sinks, streams and SQL names."""

import json

import numpy as np
from pyspark.sql import functions as F

from attention_engine.functions import sqlnames
from attention_engine.operators import highlights
from attention_engine.operators.zones import drawn_zones
from attention_engine.plans import workloads
from attention_engine.sources import tables as T
from attention_engine.streaming import live

SF = "/root/testdata/sf0.001"


def test_logs_and_sinks(spark, tmp_path):
    log = tmp_path / "log.json"
    log.write_text('{"session_id": 1, "sample_id": 2, "x": 1.5, "y": 2, "t_ms": 7, "modality": "m"}\n{"session_id": 1, "sample_id": 3, "x": null, "y": 2, "t_ms": 8}\nnot json\n')
    good, bad = T.read_trace(spark, str(log))
    assert [(r.sample_id, r.x) for r in good.collect()] == [(2, 1.5)] and bad.count() == 2
    zones = drawn_zones([(0, "a", [(0, 0), (2, 0), (2, 1)])], spark)
    assert T.to_wkt(zones).first().wkt.upper().startswith("POLYGON")
    shape = json.loads(T.to_geojson(zones).first().geojson)
    assert shape["type"] == "Polygon" and len(shape["coordinates"][0]) == 4
    points = T.points_part(spark, SF)
    T.write_points(points.select("point_id", "x", "y"), str(tmp_path / "points"), (-512.0, -512.0, 512.0, 512.0), 6, 3)
    stored = spark.read.parquet(str(tmp_path / "points"))
    assert stored.count() == points.count()
    spans = stored.groupBy(F.input_file_name()).agg(F.min("morton").alias("a"), F.max("morton").alias("b")).orderBy("a").collect()
    assert all(p.b <= q.a for p, q in zip(spans, spans[1:]))
    vector = spark.createDataFrame([(0, "kind", "a", 1.0, 1.0)], "session_id long, attr string, val string, raw double, weight double")
    for _ in range(2):  # a repeated batch changes nothing
        T.save_state(vector, str(tmp_path / "state"), 3)
    assert T.load_state(spark, str(tmp_path / "state"), 3).collect() == vector.collect()
    lists = highlights.build_neighbours(T.points_supplier(spark, SF), T.SUPPLIER_SPEC, "signature", 3).orderBy("owner", "rank")
    cursor, rows = highlights.ListCursor(lists.where("owner = 0")), lists.where("owner = 0").collect()
    assert [cursor.next().point_id for _ in rows] == [r.point_id for r in rows] and cursor.next() is None


def events(spark, tmp_path, days):
    """Samples of two sessions, one file a day, in the given order of days."""
    rows = [(s, d * 10 + k, float(k), float(d), d * 86_400_000 + k * 3_600_000, "m") for d in days for s in ((0, 1) if d < 20 else (0,)) for k in range(4)]
    path = str(tmp_path / "stream")
    for n, d in enumerate(days):
        part = spark.createDataFrame([r for r in rows if r[4] // 86_400_000 == d], T.TRACE).withColumn("at", F.timestamp_millis("t_ms"))
        part.coalesce(1).write.parquet(f"{path}/day={n}")
    schema = T.TRACE + ", at timestamp, day int"
    return rows, lambda lateness: live.live_samples(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(path).drop("day"), lateness)


def run(df, tmp_path, name, mode="append"):
    out = {}

    def write(batch, number):
        out[number] = batch.collect()

    query = df.writeStream.outputMode(mode).option("checkpointLocation", str(tmp_path / name)).foreachBatch(write).trigger(availableNow=True).start()
    query.awaitTermination()
    return [r for rows in out.values() for r in rows], query


def test_windows(spark, tmp_path):
    rows, stream = events(spark, tmp_path, [0, 1, 2, 9])
    got, query = run(live.fixed_segments(stream("1 day"), "1 day"), tmp_path, "a", "update")
    assert sum({(r.session_id, r.start): r.n for r in got}.values()) == len(rows) and live.late_rows(query) == 0
    got, _ = run(live.visits(stream("1 day"), "6 hours"), tmp_path, "b", "append")
    assert {(r.session_id, r.n) for r in got} == {(0, 4), (1, 4)} and len(got) == 6  # the last day's are still open
    got, _ = run(live.sliding_attention(stream("1 day"), 50.0, "2 days", "1 day"), tmp_path, "c", "update")
    assert sum(r.n for r in {(r.session_id, r.start, r.tx, r.ty): r for r in got}.values()) == 2 * len(rows)


def test_late_rows_are_counted(spark, tmp_path):
    _, stream = events(spark, tmp_path, [5, 9, 1])
    _, query = run(live.fixed_segments(stream("1 hour"), "1 day"), tmp_path, "late", "update")
    assert live.late_rows(query) > 0
    try:
        live.finished(query)
    except RuntimeError as e:
        assert "later" in str(e)
    else:
        raise AssertionError("late rows of a stored table must be an error")


def test_state_expires_and_updates_repeat(spark, tmp_path):
    _, stream = events(spark, tmp_path, [0, 1, 40, 41, 42])
    df = live.elastic_zones(stream("1 hour"), 1000, eps=2, min_pts=2, expire_ms=86_400_000)
    _, query = run(df, tmp_path, "state", "update")
    assert sum(int(op["numRowsRemoved"]) for p in query.recentProgress for op in p["stateOperators"]) > 0
    step = live.update_on_batch(lambda batch: batch.groupBy("session_id").count(), str(tmp_path / "out"))
    batch = spark.createDataFrame([(0,), (0,), (1,)], "session_id long")
    for _ in range(2):
        step(batch, 7)
    assert {(r.session_id, r["count"]) for r in spark.read.parquet(str(tmp_path / "out")).collect()} == {(0, 2), (1, 1)}


def test_replay(spark, tmp_path):
    trace = workloads.lattice_trace(spark)
    out = []
    query = live.replay(trace, 5000).writeStream.option("checkpointLocation", str(tmp_path / "replay")).foreachBatch(lambda b, n: out.append((n, b.collect()))).start()
    while not query.lastProgress or query.lastProgress["batchId"] < 9:
        query.awaitTermination(1)
    query.stop()
    for n, rows in out:
        assert all(r.t_ms // 5000 == n for r in rows)
    assert sum(len(rows) for n, rows in out if n < 9) == trace.where("t_ms < 45000").count()


def test_sql_names(spark):
    assert "ae_contains" in sqlnames.register(spark)
    ring = "array(named_struct('x', 0D, 'y', 0D), named_struct('x', 4D, 'y', 0D), named_struct('x', 4D, 'y', 4D), named_struct('x', 0D, 'y', 4D))"
    r = spark.sql(f"SELECT ae_ring_area({ring}) AS a, ae_contains({ring}, 1D, 1D) AS i, ae_contains({ring}, 4D, 1D) AS o, ae_morton(5L, 3L, 3) AS m, ae_distance(0D, 0D, 0D, 90D) AS d, ae_diversity(array(named_struct('lat', 0D, 'lon', 0D), named_struct('lat', 0D, 'lon', 90D))) AS v").first()
    assert (r.a, r.i, r.o, r.m) == (16.0, True, False, 0b1_011011) and np.isclose(r.d, 6371 * np.pi / 2) and np.isclose(r.v, r.d)
    assert spark.sql("SELECT count(*) AS n, count(DISTINCT cell) AS c FROM ae_quadtree_cover(2L, 3L, 4L, 4L, 4)").first() == (6, 6)
    rows = spark.sql("SELECT * FROM ae_resample(0D, 0D, 0L, 10D, 20D, 100L, 25L)").collect()
    assert [(x.t_ms, x.x, x.y) for x in rows] == [(0, 0, 0), (25, 2.5, 5), (50, 5, 10), (75, 7.5, 15)]
    points = spark.createDataFrame([(k % 2, float(k % 7), float(k * k % 11)) for k in range(60)], "g int, x double, y double").repartition(5)
    many, one = ({r.g: sorted((p.x, p.y) for p in r.ring) for r in sqlnames.hulls(df, ["g"]).collect()} for df in (points, points.coalesce(1)))
    assert many == one and len(many[0]) >= 4
