"""Streams against their batch forms."""

import time

from pyspark.sql import functions as F

from aggnear.operators.layout import build_plane
from aggnear.plans import plane
from aggnear.sources import adapters as A
from aggnear.streaming import stream

D = "/root/testdata/sf0.001"


def _files(spark, tmp_path):
    e = A.table(spark, D, "events").select(F.col("event_id").alias("point_id"), F.col("ts").cast("timestamp").alias("ts"), F.unix_seconds(F.col("ts").cast("timestamp")).alias("x"), A.cents("value").alias("y"))
    e.orderBy("ts").repartitionByRange(4, "ts").write.parquet(str(tmp_path / "in"))
    return e


def test_windowed_stream_equals_batch(spark, tmp_path):
    e = _files(spark, tmp_path)
    q = A.benchmark_query(spark, D)
    want = {(r.start, r.query_id, r.rank): r.point_id for r in stream.windowed_topk(e, q, 3).collect()}
    s = stream.point_stream(spark, str(tmp_path / "in"), e.schema, "point_id", "ts", "x", "y", 4)
    run = stream.windowed_topk(s, q, 3).writeStream.format("memory").queryName("win").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination(120)
    got = {(r.start, r.query_id, r.rank): r.point_id for r in spark.table("win").collect()}
    assert got and all(want[k] == v for k, v in got.items())
    assert stream.windowed_topk(e, q, 3, slide="12 hours").count() > len(want)


def test_running_topk_with_tombstones(spark, tmp_path):
    q = spark.createDataFrame([(1, 0, 0, 1)], "query_id long, qx long, qy long, w long")
    for n, rows in enumerate([[(1, 5, 0, False), (2, 3, 0, False)], [(2, 3, 0, True), (3, 1, 1, False)], [(2, 3, 0, False)]]):
        spark.createDataFrame(rows, "point_id long, x long, y long, gone boolean").coalesce(1).write.parquet(str(tmp_path / "pts" / f"b{n}"))
        time.sleep(1.1)
    s = spark.readStream.schema("point_id long, x long, y long, gone boolean").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "pts"))
    run = stream.running_topk(s, q, 2, slack=2).writeStream.format("memory").queryName("heap").outputMode("update").trigger(availableNow=True).start()
    run.awaitTermination(120)
    rows = [(r.rank, r.point_id, r.agg_dist) for r in spark.table("heap").collect()]
    assert rows[:2] == [(1, 2, 3), (2, 1, 5)] and rows[2:4] == [(1, 3, 2), (2, 1, 5)] and rows[4:] == [(1, 3, 2), (2, 2, 3)]


def test_groups_that_arrive(spark, tmp_path):
    layout = build_plane(A.embeddings_plane(spark, D), slabs=2, bands=2)
    q = A.embeddings_query(spark, D)
    q.coalesce(1).write.parquet(str(tmp_path / "q"))
    s = spark.readStream.schema(q.schema).parquet(str(tmp_path / "q"))
    stream.answer_arriving(s, layout, 3, str(tmp_path / "out")).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start().awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out")).select("query_id", "rank", "point_id").collect()
    assert sorted(got) == sorted(plane.topk(A.embeddings_plane(spark, D), q, 3).select("query_id", "rank", "point_id").collect())


def test_repeats(spark, tmp_path):
    e = _files(spark, tmp_path)
    e.limit(50).write.mode("append").parquet(str(tmp_path / "in"))
    s = spark.readStream.schema(e.schema).parquet(str(tmp_path / "in"))
    run = stream.without_repeats(s, "400 days").writeStream.format("memory").queryName("once").trigger(availableNow=True).start()
    run.awaitTermination(120)
    assert spark.table("once").count() == e.count()


def _at(day: float) -> float:
    return 86_400 * day


def test_late_rows_are_dropped_and_windows_close(spark, tmp_path):
    q = spark.createDataFrame([(1, 0, 0, 1)], "query_id long, qx long, qy long, w long")
    days = [[(1, 1.1, 9), (2, 1.2, 4), (3, 1.3, 7)], [(4, 3.5, 1)], [(5, 1.4, 2), (6, 3.6, 8)], [(7, 9.0, 5)]]  # 5 comes too late
    for n, rows in enumerate(days):
        d = spark.createDataFrame([(i, _at(t), x, 0) for i, t, x in rows], "point_id long, s double, x long, y long")
        d.select("point_id", F.timestamp_seconds("s").alias("ts"), "x", "y").coalesce(1).write.parquet(str(tmp_path / "in" / f"b{n}"))
        time.sleep(1.1)
    s = spark.readStream.schema("point_id long, ts timestamp, x long, y long").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    run = stream.windowed_topk(s, q, 2).writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination(120)
    got = sorted((r.start.day, r.rank, r.point_id, r.agg_dist) for r in spark.table("late").collect())
    assert got == [(2, 1, 2, 4), (2, 2, 3, 7), (4, 1, 4, 1), (4, 2, 6, 8)]


def test_sessions_of_a_stream(spark, tmp_path):
    q = spark.createDataFrame([(1, 0, 0, 1)], "query_id long, qx long, qy long, w long")
    rows = [(1, "a", 0, 5), (2, "a", 600, 3), (3, "a", 9_000, 4), (4, "b", 100, 2), (5, "b", 1_500, 6), (6, "z", 500_000, 1)]
    d = spark.createDataFrame(rows, "point_id long, user string, s long, x long").select("point_id", "user", F.timestamp_seconds("s").alias("ts"), "x", F.lit(0).cast("long").alias("y"))
    want = sorted((r.user, r.start, r.rank, r.point_id) for r in stream.session_topk(d, q, 1, "user").collect())
    assert [(u, p) for u, _, _, p in want] == [("a", 2), ("a", 3), ("b", 4), ("z", 6)]
    for n, part in enumerate((d.filter("point_id < 6"), d.filter("point_id = 6"))):
        part.coalesce(1).write.parquet(str(tmp_path / "in" / f"b{n}"))
        time.sleep(1.1)
    s = spark.readStream.schema(d.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    run = stream.session_topk(s, q, 1, "user").writeStream.format("memory").queryName("sess").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination(120)
    assert sorted((r.user, r.start, r.rank, r.point_id) for r in spark.table("sess").collect()) == want[:3]
