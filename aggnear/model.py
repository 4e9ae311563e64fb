"""Schemas, canonical order and input checks.

Points are (point_id, x[, y]) and query groups (query_id, qx[, qy], w), all whole numbers ("ticks"),
so that every engine gives the same sums. A point may carry ``own``: the query it takes no part in.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NEAREST, FARTHEST = "nearest", "farthest"
LINE_POINTS = "point_id long, x long"
PLANE_POINTS = "point_id long, x long, y long"
QUERY = "query_id long, qx long, qy long, w long"
ANSWER = "query_id long, rank long, point_id long, x long, y long, agg_dist long"
LINE_ANSWER = "query_id long, rank long, point_id long, x long, agg_dist long"
COUNTERS = "query_id long, quad int, round int, measure string, value long"
#: Sums beyond this are refused: total weight times coordinate span must stay below it.
LIMIT = 1 << 62


def sign_of(direction: str) -> int:
    if direction not in (NEAREST, FARTHEST):
        raise ValueError(f"direction must be {NEAREST} or {FARTHEST}, not {direction!r}")
    return 1 if direction == NEAREST else -1


def canonical(direction: str, *more: str) -> list[Column]:
    """Best first: by distance, then by point_id and coordinates upwards."""
    first = F.col("agg_dist").asc() if sign_of(direction) > 0 else F.col("agg_dist").desc()
    return [first, *(F.col(c).asc() for c in ("point_id", *more))]


def check_k(k: int) -> int:
    if k < 1:
        raise ValueError("k must be 1 or more")
    return int(k)


def _never_null(df: DataFrame, names: list[str], what: str) -> DataFrame:
    bad = F.lit(False)
    for c in names:
        bad = bad | F.col(c).isNull()
    one = names[0]
    return df.withColumn(one, F.when(bad, F.raise_error(F.lit(f"{what}: null in {', '.join(names)}"))).otherwise(F.col(one)))


def checked_points(points: DataFrame) -> DataFrame:
    """Points as longs; a null id or coordinate raises when it is read."""
    axes = [c for c in ("x", "y") if c in points.columns]
    more = ["own"] if "own" in points.columns else []
    return _never_null(points.select(*[F.col(c).cast("long").alias(c) for c in ("point_id", *axes, *more)]), ["point_id", *axes], "points")


def checked_query(query: DataFrame) -> DataFrame:
    """Query rows as longs; nulls and weights below 1 raise when they are read."""
    axes = [c for c in ("qx", "qy") if c in query.columns]
    q = _never_null(query.select(*[F.col(c).cast("long").alias(c) for c in ("query_id", *axes, "w")]), ["query_id", *axes, "w"], "query")
    return q.withColumn("w", F.when(F.col("w") <= 0, F.raise_error(F.lit("query: weights must be positive"))).otherwise(F.col("w")))
