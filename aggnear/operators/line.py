"""Top-k group neighbours on a line.

The answer stands next to the interval of minimisers (nearest) or at the ends of the point set
(farthest): k points left of the interval, k right of it, and k by id inside, where all distances are
equal. With global ranks these are rank intervals, so a batch of groups costs k rows each and one
equi-join with the sorted points, not a scan per group.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import weights
from ..functions.profile import agg_dist, upto
from ..model import canonical, check_k, checked_points, checked_query, sign_of
from ..staging import stage
from .layout import LineLayout, build_line
from .least import least_ids


def _buckets(points: DataFrame) -> list[int]:
    """Cuts of x between about equal numbers of points, four for each shuffle partition (at most 4096)."""
    parts = min(4096, 4 * int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    got = points.select(F.percentile_approx("x", [i / parts for i in range(1, parts)], 100 * parts)).first()[0] or []
    return sorted({int(v) for v in got})


def _bucket(cuts: list[int], x) -> F.Column:
    return upto(F.array(*[F.lit(v) for v in cuts]).cast("array<bigint>"), x) if cuts else F.lit(0)


def locate(layout: LineLayout, anchors: DataFrame) -> DataFrame:
    """anchors(query_id, ax, ax_hi) plus below (points with x < ax) and upto (points with x <= ax_hi).

    An as-of join: anchors and the distinct coordinates' ranks in one order, the last rank carried
    forward; dealt by ranges of x of equal numbers of points, so that no single task sees everything.
    """
    p = layout.points
    cuts = _buckets(p)
    asks = anchors.select("query_id", F.explode(F.array(F.struct(F.lit("below").alias("what"), (F.col("ax") - 1).alias("x")), F.struct(F.lit("upto").alias("what"), F.col("ax_hi").alias("x")))).alias("s"))
    asks = asks.select("query_id", "s.what", "s.x", F.lit(None).cast("long").alias("pos"))
    asks = asks.withColumn("b", _bucket(cuts, F.col("x")))
    own = p.groupBy("x").agg((F.max("pos") + 1).alias("pos")).withColumn("b", _bucket(cuts, F.col("x")))
    ends = own.groupBy("b").agg(F.max("pos").alias("pos"))  # a row per bucket
    before = F.coalesce(F.max("pos").over(Window.orderBy("nb").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    all_b = p.sparkSession.range(len(cuts) + 1).select(F.col("id").cast("int").alias("nb"))
    base = all_b.join(ends, F.col("nb") == F.col("b"), "left").select("nb", before.alias("base"))
    both = own.select(F.lit(None).cast("long").alias("query_id"), F.lit(None).cast("string").alias("what"), "x", "pos", "b").unionByName(asks)
    run = Window.partitionBy("b").orderBy("x").rangeBetween(Window.unboundedPreceding, 0)
    got = both.withColumn("c", F.max("pos").over(run)).filter("what is not null")
    got = got.join(F.broadcast(base), F.col("b") == F.col("nb")).withColumn("c", F.coalesce("c", "base"))  # at most 4097 rows
    counts = got.groupBy("query_id").agg(F.max(F.when(F.col("what") == "below", F.col("c"))).alias("below"), F.max(F.when(F.col("what") == "upto", F.col("c"))).alias("upto"))
    return anchors.join(counts, "query_id")


def sides(layout: LineLayout, located: DataFrame, k: int, direction: str) -> DataFrame:
    """At most 3k candidates per group: (query_id, point_id, x)."""
    p, n = layout.points, F.lit(layout.n)
    near = sign_of(direction) > 0
    first_left = n - F.col("below") if near else F.lit(0).cast("long")
    first_right = F.col("upto") if near else F.lit(0).cast("long")
    left = F.struct(F.lit("sop" if near else "pos").alias("by"), first_left.alias("lo"), F.least(first_left + k, first_left + F.col("below")).alias("hi"))
    right = F.struct(F.lit("pos" if near else "sop").alias("by"), first_right.alias("lo"), F.least(first_right + k, first_right + n - F.col("upto")).alias("hi"))
    spans = located.select("query_id", F.explode(F.array(left, right)).alias("s")).filter("s.hi > s.lo")
    at = spans.select("query_id", "s.by", F.explode(F.sequence(F.col("s.lo"), F.col("s.hi") - 1)).alias("at"))
    out = None
    for by in ("pos", "sop"):
        own = at.filter(F.col("by") == by).join(p.select("point_id", "x", F.col(by).alias("at")), "at").select("query_id", "point_id", "x")
        out = own if out is None else out.unionByName(own)
    # inside: at one coordinate positions go by id, so the first k do; across several, the least ids of the range
    last = F.when(F.col("ax") == F.col("ax_hi"), F.least(F.col("upto"), F.col("below") + k)).otherwise(F.col("upto"))
    flat = located.filter("upto > below").select("query_id", F.col("below").alias("lo"), last.alias("hi"))
    inside = least_ids(p, layout.n, flat, k)
    by_id = Window.partitionBy("query_id").orderBy("point_id", "x")
    inside = inside.withColumn("r", F.row_number().over(by_id)).filter(F.col("r") <= k).select("query_id", "point_id", "x")
    return out.unionByName(inside)


def _rank(x: DataFrame, k: int, direction: str) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(*canonical(direction, "x"))
    x = x.withColumn("rank", F.row_number().over(order).cast("long")).filter(F.col("rank") <= k)
    return x.select("query_id", "rank", "point_id", "x", "agg_dist")


def topk(points: DataFrame | LineLayout, query: DataFrame, k: int, direction: str = "nearest", evaluator: str = "auto") -> DataFrame:
    """query_id, rank, point_id, x, agg_dist; min(k, points) rows per group.

    query: rows (query_id, qx, w), or groups that are sorted already, (query_id, q: array of (v, w)), whose
    medians and profiles cost one pass over the array (an array out of order raises). ``auto``
    evaluates directly while k is below the logarithm of the group sizes, else by prefix sums.
    """
    k = check_k(k)
    layout = points if isinstance(points, LineLayout) else build_line(checked_points(points))
    if "q" in query.columns:
        if evaluator not in ("auto", "prefix"):
            raise ValueError("sorted groups are evaluated by prefix sums")
        found = sides(layout, locate(layout, weights.anchor_of_sorted(query)), k, direction)
        return _rank(agg_dist(found, query, "prefix"), k, direction)
    query = checked_query(query)
    if evaluator == "auto":
        m = query.groupBy("query_id").count().agg(F.max("count")).first()[0] or 1
        evaluator = "direct" if k < max(1, m).bit_length() - 1 else "prefix"
    found = sides(layout, locate(layout, weights.anchor(query.select("query_id", "qx", "w"))), k, direction)
    return _rank(agg_dist(found, query.select("query_id", "qx", "w"), evaluator), k, direction)


def nearest(points: DataFrame, query: DataFrame) -> DataFrame:
    """k = 1: the neighbours of the interval of minimisers, or the least id inside it.

    No ranks, no sort of the points: one row per distinct coordinate meets the intervals in ranges of
    x, and a row per range tells what stands in the ranges before, after and between.
    """
    query, p = checked_query(query).select("query_id", "qx", "w"), checked_points(points)
    cuts = _buckets(p)
    one = stage(p.groupBy("x").agg(F.min("point_id").alias("id")).withColumn("b", _bucket(cuts, F.col("x"))), "line-coordinates")
    here = F.struct("x", "id")
    ends = one.groupBy("b").agg(F.min(here).alias("lo"), F.max(here).alias("hi"), F.min(F.struct("id", "x")).alias("least"))
    spots = one.sparkSession.range(len(cuts) + 1).select(F.col("id").cast("int").alias("nb")).join(ends, F.col("nb") == F.col("b"), "left")
    order = Window.orderBy("nb")  # one row per bucket
    spots = spots.select(
        "nb", "least",
        F.last("hi", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1)).alias("before"),
        F.first("lo", ignorenulls=True).over(order.rowsBetween(1, Window.unboundedFollowing)).alias("after"),
    )
    spots = stage(spots, "line-buckets")
    a = stage(weights.anchor(query), "line-anchors").select("query_id", "ax", "ax_hi")
    asks = a.select("query_id", F.explode(F.array(F.struct(F.lit("left").alias("what"), (F.col("ax") - 1).alias("x")), F.struct(F.lit("right").alias("what"), (F.col("ax_hi") + 1).alias("x")))).alias("s")).select("query_id", "s.what", "s.x")
    both = one.select(F.lit(None).cast("long").alias("query_id"), F.lit(None).cast("string").alias("what"), "x", "b", here.alias("here"))
    both = both.unionByName(asks.withColumn("b", _bucket(cuts, F.col("x"))), allowMissingColumns=True)
    run = Window.partitionBy("b").orderBy("x")
    both = both.withColumn("lo", F.last("here", ignorenulls=True).over(run.rangeBetween(Window.unboundedPreceding, 0)))
    both = both.withColumn("hi", F.first("here", ignorenulls=True).over(run.rangeBetween(0, Window.unboundedFollowing))).filter("what is not null")
    both = both.join(F.broadcast(spots), F.col("b") == F.col("nb"))  # at most 4097 rows
    hit = F.when(F.col("what") == "left", F.coalesce("lo", "before")).otherwise(F.coalesce("hi", "after"))
    out = both.select("query_id", hit.alias("h")).filter("h is not null").select("query_id", F.col("h.id").alias("point_id"), "h.x")
    # inside the interval: its first and last range by their coordinates, those between by their least id
    flat = a.withColumn("b0", _bucket(cuts, F.col("ax"))).withColumn("b1", _bucket(cuts, F.col("ax_hi")))
    edge = flat.withColumn("b", F.explode(F.array_distinct(F.array("b0", "b1")))).join(one, "b").filter("x between ax and ax_hi")
    inner = flat.filter("b1 - b0 > 1").withColumn("b", F.explode(F.sequence(F.col("b0") + 1, F.col("b1") - 1)))
    inner = inner.join(F.broadcast(spots.filter("least is not null").select("nb", "least")), F.col("b") == F.col("nb"))
    inside = edge.select("query_id", F.struct("id", "x").alias("i")).unionByName(inner.select("query_id", F.col("least").alias("i")))
    inside = inside.groupBy("query_id").agg(F.min("i").alias("i")).select("query_id", F.col("i.id").alias("point_id"), "i.x")
    return _rank(agg_dist(out.unionByName(inside), query, "prefix"), 1, "nearest")


def farthest_ends(points: DataFrame, query: DataFrame) -> DataFrame:
    """k = 1, farthest: only the two ends of the point set can be the answer."""
    query, p = checked_query(query), checked_points(points)
    e = p.agg(F.min(F.struct("x", "point_id")).alias("lo"), F.max(F.struct("x", (-F.col("point_id")).alias("i"))).alias("hi"))
    e = e.select(F.explode(F.array(F.struct(F.col("lo.point_id").alias("point_id"), F.col("lo.x").alias("x")), F.struct((-F.col("hi.i")).alias("point_id"), F.col("hi.x").alias("x")))).alias("e")).select("e.*").distinct()
    x = query.select("query_id").distinct().crossJoin(F.broadcast(e))  # two rows
    return _rank(agg_dist(x, query.select("query_id", "qx", "w"), "direct"), 1, "farthest")
