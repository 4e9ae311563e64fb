"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.profile import Group
from ..model import sign_of
from ..staging import stage
from . import frontier, tiles
from .layout import PlaneLayout


def exactness(answer: DataFrame, truth: DataFrame) -> DataFrame:
    """Per group: rows, rows equal in rank and point, points in both, largest distance gap by rank."""
    a, t = answer.alias("a"), truth.select(*[F.col(c).alias(f"t_{c}") for c in truth.columns]).alias("t")
    by_rank = a.join(t, (F.col("a.query_id") == F.col("t_query_id")) & (F.col("a.rank") == F.col("t_rank")), "full")
    q = F.coalesce("query_id", "t_query_id").alias("query_id")
    ranks = by_rank.groupBy(q).agg(
        F.count("*").alias("rows"),
        F.sum(F.when(F.col("point_id") == F.col("t_point_id"), 1).otherwise(0)).alias("same_rank"),
        F.max(F.coalesce(F.abs(F.col("agg_dist") - F.col("t_agg_dist")), F.lit(-1))).alias("gap"),
    )
    both = answer.select("query_id", "point_id").intersect(truth.select("query_id", "point_id")).groupBy("query_id").agg(F.count("*").alias("in_both"))
    return ranks.join(both, "query_id", "left").na.fill(0)


def out_of_order(answer: DataFrame, direction: str = "nearest") -> DataFrame:
    """Rows of an answer that are worse than the one after them: none."""
    w = Window.partitionBy("query_id").orderBy("rank")
    return answer.withColumn("next", F.lead("agg_dist").over(w)).filter((F.col("next") - F.col("agg_dist")) * sign_of(direction) < 0)


def frontier_size(points: DataFrame, query: DataFrame, direction: str = "nearest") -> DataFrame:
    """Vertices of every frontier: query_id, quad, vertices."""
    return frontier.minimal(frontier.quadrants(points, query, direction)).groupBy("query_id", "quad").agg(F.count("*").alias("vertices"))


def tiles_read(layout: PlaneLayout, groups: list[Group], k: int, direction: str = "nearest") -> DataFrame:
    """Per group: tiles and rows that pruning leaves, of all."""
    all_ = layout.tiles.agg(F.count("*").alias("tiles_all"), F.sum("n").alias("rows_all"))
    kept = tiles.candidate_tiles(layout, groups, k, direction).groupBy("query_id").agg(F.count("*").alias("tiles"), F.sum("n").alias("rows"))
    return kept.crossJoin(F.broadcast(all_))  # one row


def work_of(df: DataFrame) -> dict[str, int]:
    """Runs a plan without output; rows that its scans read and that it shuffles, and shuffle bytes, as Spark counts them."""
    spark = df.sparkSession
    df.write.format("noop").mode("overwrite").save()
    # the write has a query execution of its own: count over an execution of the same plan that is kept
    plan = df._jdf.queryExecution().executedPlan()
    df._jdf.queryExecution().toRdd().count()
    out = {"rows_read": 0, "rows_shuffled": 0, "bytes_shuffled": 0}

    def visit(node):
        name, metrics = node.nodeName(), node.metrics()
        value = lambda m: int(metrics.apply(m).value()) if metrics.contains(m) else 0
        if name.startswith("Scan"):
            out["rows_read"] += value("numOutputRows")
        if name == "Exchange":
            out["rows_shuffled"] += value("shuffleRecordsWritten")
            out["bytes_shuffled"] += value("shuffleBytesWritten")
        if name.startswith("AdaptiveSparkPlan"):
            return visit(node.executedPlan())
        if "QueryStage" in name:
            return visit(node.plan())
        children = node.children()
        for i in range(children.size()):
            visit(children.apply(i))

    visit(plan)
    return out


def evaluated(found: DataFrame, query: DataFrame, evaluator: str) -> DataFrame:
    """Counted work of evaluating found(query_id, point_id, ...): candidates that meet in the last step, and terms or look-ups.

    direct: one term for each query point of each candidate. prefix: two looks-up for each axis of a
    candidate, each lg m steps, after one entry for each distinct coordinate. merge: one step for each
    row of candidates and distinct coordinates.
    """
    m = query.groupBy("query_id").agg(F.count("*").alias("m"), F.countDistinct("qx").alias("d"))
    c = found.groupBy("query_id").agg(F.count("*").alias("candidates"))
    steps = {"direct": F.col("candidates") * F.col("m"), "prefix": F.col("candidates") * F.length(F.bin("d")) + F.col("d"), "merge": F.col("candidates") + F.col("d")}[evaluator]
    return c.join(m, "query_id").select("query_id", "m", "candidates", F.lit(evaluator).alias("evaluator"), steps.cast("long").alias("steps"))


def layout_size(layout: PlaneLayout) -> DataFrame:
    """Hulls and vertices by level and run level: the size side of the build/query trade-off."""
    return layout.hulls.groupBy("level", "run_level").agg(F.count("*").alias("hulls"), F.sum(F.size("vertices")).alias("vertices"))


def rollup(counters: DataFrame) -> DataFrame:
    """Sums of a counters table by query, quadrant and measure, with totals."""
    return counters.rollup("measure", "query_id", "quad").agg(F.sum("value").alias("total"), F.max("value").alias("largest"))


def layout_bytes(layout: PlaneLayout) -> int:
    """Bytes of a layout's files."""
    spark = layout.points.sparkSession
    at = spark._jvm.org.apache.hadoop.fs.Path(layout.folder)
    return int(at.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(at).getLength())


def timed(df: DataFrame) -> float:
    """Seconds of a plan without output."""
    t = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - t


def query_steps(points: DataFrame, query: DataFrame, groups: list[Group], k: int, direction: str = "nearest") -> dict[str, float]:
    """Seconds of a search step by step: anchors, quadrants, first cells, peel, merge."""
    from ..functions import weights
    from ..plans.plane import merge_quadrants
    from . import peel

    found = stage(peel.quadrant_topk(points, query, groups, k, direction), "step-found")
    return {
        "anchors": timed(weights.anchor(query)),
        "quadrants": timed(frontier.quadrants(points, query, direction)),
        "first cells": timed(peel.first_cells(points, query, groups, direction)),
        "peel": timed(peel.quadrant_topk(points, query, groups, k, direction)),
        "merge": timed(merge_quadrants(found.drop("quad"), k, direction)),
    }


def exponent(sizes: list[float], values: list[float]) -> float:
    """Slope of log value over log size: the growth of a measure."""
    x, y = [math.log(s) for s in sizes], [math.log(max(v, 1e-9)) for v in values]
    mx, my = sum(x) / len(x), sum(y) / len(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y)) / sum((a - mx) ** 2 for a in x)


def growth(totals: DataFrame) -> DataFrame:
    """totals(measure, parameter, total) -> measure, points, exponent: the slope of log total over log parameter."""
    x = totals.filter("total > 0").select("measure", F.log("parameter").alias("lx"), F.log("total").alias("ly"))
    return x.groupBy("measure").agg(F.count("*").alias("points"), F.round(F.regr_slope("ly", "lx"), 3).alias("exponent"))
