"""What the search rests on, as queries that must come back empty."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import weights
from ..functions.profile import agg_dist
from . import frontier


def monotone_line(points: DataFrame, query: DataFrame) -> DataFrame:
    """Pairs of neighbouring points on one side of the anchor where the farther one has the smaller distance."""
    a = weights.anchor(query.select("query_id", "qx", "w")).select("query_id", "ax")
    x = agg_dist(frontier.with_groups(points.select("point_id", "x"), a), query.select("query_id", "qx", "w"))
    side = F.col("x") <= F.col("ax")
    w = Window.partitionBy("query_id", side).orderBy(F.abs(F.col("x") - F.col("ax")), "point_id")
    return x.withColumn("before", F.lag("agg_dist").over(w)).filter(F.col("before") > F.col("agg_dist"))


def monotone_plane(points: DataFrame, query: DataFrame) -> DataFrame:
    """Steps away from the anchor along one axis that make the distance smaller, at the points' coordinates: query_id, axis, at.

    The distance is a sum over the axes, so it grows along every monotone path exactly if it grows
    along each axis: neighbours on an axis are compared, not pairs of points.
    """
    a = weights.anchor(query).select("query_id", "ax", "ay")
    out = None
    for c in "xy":
        spots = frontier.with_groups(points.select(F.col(c).alias("at")).distinct(), a)
        on = {"x": F.col("at") if c == "x" else F.col("ax"), "y": F.col("at") if c == "y" else F.col("ay")}
        x = agg_dist(spots.select("query_id", F.lit(0).cast("long").alias("point_id"), on["x"].alias("x"), on["y"].alias("y"), "at", F.col(f"a{c}").alias("a")), query)
        w = Window.partitionBy("query_id", F.col("at") <= F.col("a")).orderBy(F.abs(F.col("at") - F.col("a")))
        x = x.withColumn("before", F.lag("agg_dist").over(w)).filter(F.col("before") > F.col("agg_dist")).select("query_id", F.lit(c).alias("axis"), "at")
        out = x if out is None else out.unionByName(x)
    return out
