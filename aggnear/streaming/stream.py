"""Streams: points that arrive, points that go, and groups that arrive.

Event time must be a TIMESTAMP: TIMESTAMP_NTZ columns are cast first, under a UTC session zone.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.profile import load_groups
from ..model import checked_query, sign_of
from ..plans import plane


def point_stream(spark: SparkSession, path: str, schema, point_id: str, ts: str, x: str, y: str, per_trigger: int = 1) -> DataFrame:
    """Parquet files as a stream of (point_id, ts, x, y)."""
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)
    cols = [F.expr(point_id).cast("long").alias("point_id"), F.expr(ts).cast("timestamp").alias("ts")]
    return s.select(*cols, F.expr(x).cast("long").alias("x"), F.expr(y).cast("long").alias("y"))


def without_repeats(points: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each point_id once within the watermark."""
    return points.withWatermark("ts", late).dropDuplicatesWithinWatermark(["point_id"])


def _scored(points: DataFrame, groups, *more: str) -> DataFrame:
    """A row per point and group with agg_dist; groups are few and static, ``more`` columns go along."""

    def run(batches):
        for batch in batches:
            px, py = batch.column(2).to_numpy(), batch.column(3).to_numpy()
            for g in groups:
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(px), g.query_id)), *batch.columns, pa.array(g(px, py))], names=["query_id", *batch.schema.names, "agg_dist"])

    x = points.select("point_id", "ts", "x", "y", *more)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in x.schema)
    return x.mapInArrow(run, f"query_id long, {kinds}, agg_dist long")


_BEST = "fs array<long>, ids array<long>, xs array<long>, ys array<long>"


def _keep_best(k: int):
    """Per (window, group): the k best rows so far; they come out once the watermark has passed the window."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        start, end, query_id = key
        if state.hasTimedOut:
            rows = list(zip(*state.get))
            state.remove()
            yield pd.DataFrame([(start, end, query_id, n + 1, i, x, y, f) for n, (f, i, x, y) in enumerate(rows)], columns=["start", "end", "query_id", "rank", "point_id", "x", "y", "key"])
            return
        end_ms = int(pd.Timestamp(end).timestamp() * 1000)
        if end_ms <= state.getCurrentWatermarkMs():
            return  # too late: this window has been given out
        rows = list(zip(*state.get)) if state.exists else []
        for pdf in batches:
            rows = sorted([*rows, *pdf[["key", "point_id", "x", "y"]].itertuples(index=False, name=None)])[:k]
        state.update(tuple([int(v) for v in c] for c in zip(*rows)))
        state.setTimeoutTimestamp(end_ms)

    return step


def windowed_topk(points: DataFrame, query: DataFrame, k: int, direction: str = "nearest", length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """The k best points of every event-time window per group, once the watermark has passed it.

    A stream's state is k rows for each open window and group; rows whose window the watermark has
    passed are dropped. A table is answered by one ranked window.
    """
    groups = load_groups(checked_query(query))
    s = sign_of(direction)
    x = _scored(points, groups).withWatermark("ts", late).withColumn("key", F.col("agg_dist") * s)
    x = x.withColumn("w", F.window("ts", length, slide) if slide else F.window("ts", length)).withColumn("start", F.col("w.start")).withColumn("end", F.col("w.end")).drop("w")
    if points.isStreaming:
        kinds = "start timestamp, end timestamp, query_id long, rank long, point_id long, x long, y long, key long"
        x = x.groupBy("start", "end", "query_id").applyInPandasWithState(_keep_best(k), kinds, _BEST, "append", GroupStateTimeout.EventTimeTimeout)
    else:
        order = Window.partitionBy("start", "end", "query_id").orderBy("key", "point_id", "x", "y")
        x = x.withColumn("rank", F.row_number().over(order).cast("long")).filter(F.col("rank") <= k)
    return x.select("start", "end", "query_id", "rank", "point_id", "x", "y", (F.col("key") * s).alias("agg_dist"))


def session_topk(points: DataFrame, query: DataFrame, k: int, user: str, direction: str = "nearest", gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """The same per session of a user, for tables and streams; points carry the user column.

    Sessions grow together when a row falls between them, so an open session's state holds its rows.
    """
    s = sign_of(direction)
    x = _scored(points, load_groups(checked_query(query)), user).withWatermark("ts", late)
    entry = F.struct((F.col("agg_dist") * s).alias("k"), "point_id", "x", "y")
    x = x.groupBy(F.session_window("ts", gap).alias("w"), user, "query_id").agg(F.slice(F.array_sort(F.collect_list(entry)), 1, k).alias("best"))
    x = x.select("w.start", "w.end", user, "query_id", F.posexplode("best").alias("rank", "b"))
    return x.select("start", "end", user, "query_id", (F.col("rank") + 1).cast("long").alias("rank"), "b.point_id", "b.x", "b.y", (F.col("b.k") * s).alias("agg_dist"))


RUNNING = "query_id long, rank long, point_id long, x long, y long, agg_dist long"


def running_topk(points: DataFrame, query: DataFrame, k: int, direction: str = "nearest", slack: int = 0) -> DataFrame:
    """The k best so far per group, given anew whenever a batch changes them.

    Points may carry ``gone`` (boolean): a tombstone takes its point off, and a later row of the same
    id puts it back. State holds k + slack rows a group and no more; deletions beyond the slack leave
    fewer than k, and a tombstone that comes before its point has no effect.
    """
    groups = load_groups(checked_query(query))
    s, keep = sign_of(direction), k + slack
    flag = F.coalesce(F.col("gone"), F.lit(False)) if "gone" in points.columns else F.lit(False)
    known = {g.query_id: g for g in groups}
    x = points.select("point_id", "x", "y", flag.alias("gone"), F.explode(F.array(*[F.lit(q) for q in known])).alias("query_id"))

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = {i: (f, i, a, b) for f, i, a, b in zip(*state.get)} if state.exists else {}
        before = sorted(rows.values())[:k]
        g = known[key[0]]
        for pdf in batches:
            f = g(pdf["x"].to_numpy(), pdf["y"].to_numpy()) * s
            for i, a, b, off, v in zip(pdf["point_id"], pdf["x"], pdf["y"], pdf["gone"], f):
                if off:
                    rows.pop(i, None)
                else:
                    rows[int(i)] = (int(v), int(i), int(a), int(b))
        best = sorted(rows.values())[:keep]
        state.update(tuple([r[c] for r in best] for c in range(4)))
        now = best[:k]
        if now != before:
            yield pd.DataFrame([(key[0], n + 1, r[1], r[2], r[3], r[0] * s) for n, r in enumerate(now)], columns=["query_id", "rank", "point_id", "x", "y", "agg_dist"])

    return x.groupBy("query_id").applyInPandasWithState(step, RUNNING, _BEST, "update", GroupStateTimeout.NoTimeout)


def answer_arriving(queries: DataFrame, layout, k: int, out: str, direction: str = "nearest"):
    """Groups that arrive in micro-batches, each answered against the static layout; returns the writer to start."""

    def batch(df: DataFrame, epoch: int) -> None:
        if not df.isEmpty():
            plane.topk(layout, df, k, direction).withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{out}/epoch={epoch}")

    return queries.writeStream.foreachBatch(batch)
