"""Minimal and maximal points of the quadrants, as plans.

Input rows are (query_id, quad, u, v, point_id, x, y): points in a quadrant's own coordinates.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import plane_geometry as G
from ..functions import weights
from ..functions.profile import Group
from ..staging import stage

_IN = ["query_id", "quad"]
_SLABS = 64


#: Groups whose anchors are handed to every task; more are dealt out in blocks of points.
FEW_GROUPS = 20_000


def with_groups(points: DataFrame, groups: DataFrame) -> DataFrame:
    """Every point with every row of groups (one a group): each pair is part of the result.

    The groups travel to the tasks while they are few; more meet the points in blocks, by shuffle.
    """
    groups = stage(groups, "anchors")
    many = groups.count()
    if many <= FEW_GROUPS:
        return points.crossJoin(F.broadcast(groups))  # at most FEW_GROUPS rows
    blocks = -(-many // FEW_GROUPS)
    dealt = groups.withColumn("block", F.pmod(F.xxhash64("query_id"), F.lit(blocks)).cast("int"))
    copies = points.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("deal", F.pmod(F.monotonically_increasing_id(), F.lit(64)).cast("int"))
    dealt = dealt.withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(63))))
    return copies.join(dealt, ["block", "deal"]).drop("block", "deal")


def quadrants(points: DataFrame, query: DataFrame, direction: str = "nearest", narrow: bool = False) -> DataFrame:
    """Every point once per group (none for its own group): quad, u, v as distances from the anchor, both >= 0.

    For the farthest direction u and v are counted from the quadrant's far corner. narrow: distances
    from the interval of all minimisers; a point that another one dominates is then truly worse.
    """
    a = weights.anchor(query).select("query_id", "ax", "ay", "ax_hi", "ay_hi")
    x = with_groups(points, a)
    if "own" in points.columns:
        x = x.filter(F.col("own").isNull() | (F.col("own") != F.col("query_id")))
    right, up = F.col("x") > F.col("ax"), F.col("y") > F.col("ay")
    quad = F.when(up, F.when(right, 1).otherwise(2)).otherwise(F.when(right, 4).otherwise(3))

    def away(c, above):
        hi = F.col(f"a{c}_hi") if narrow else F.col(f"a{c}")
        return F.when(above, F.greatest(F.col(c) - hi, F.lit(0))).otherwise(F.col(f"a{c}") - F.col(c))

    x = x.select("query_id", quad.alias("quad"), away("x", right).alias("u"), away("y", up).alias("v"), "point_id", "x", "y")
    if direction == "nearest":
        return x
    far = x.groupBy(*_IN).agg(F.max("u").alias("mu"), F.max("v").alias("mv"))
    return x.join(far, _IN).select("query_id", "quad", (F.col("mu") - F.col("u")).alias("u"), (F.col("mv") - F.col("v")).alias("v"), "point_id", "x", "y")


def dominates(a: str, b: str) -> Column:
    """Whether row a's (u, v) is at most row b's on both axes and below it on one; coincident points do not dominate each other."""
    (au, av), (bu, bv) = ((F.col(f"{r}.u"), F.col(f"{r}.v")) for r in (a, b))
    return (au <= bu) & (av <= bv) & ((au < bu) | (av < bv))


def minimal(quads: DataFrame, by: list[str] = _IN) -> DataFrame:
    """Rows that no row of the same group dominates; coincident ones stay together.

    Two phases: the least v of every u-slab of a group, then within a slab only rows below the
    minimum of the slabs before it meet in a window.
    """
    span = quads.groupBy(*by).agg(F.min("u").alias("u0"), F.max("u").alias("u1"))
    x = quads.join(span, by)
    x = x.withColumn("slab", F.expr(f"(u - u0) * {_SLABS} div (u1 - u0 + 1)")).drop("u0", "u1")
    low = x.groupBy(*by, "slab").agg(F.min("v").alias("low"))
    before = Window.partitionBy(*by).orderBy("slab").rowsBetween(Window.unboundedPreceding, -1)
    low = low.withColumn("low", F.min("low").over(before))  # at most 64 rows a group
    x = x.join(low, [*by, "slab"]).filter(F.col("low").isNull() | (F.col("v") < F.col("low")))
    spots = x.groupBy(*by, "slab", "u").agg(F.min("v").alias("v"))
    above = Window.partitionBy(*by, "slab").orderBy("u").rowsBetween(Window.unboundedPreceding, -1)
    spots = spots.withColumn("m", F.min("v").over(above)).filter(F.col("m").isNull() | (F.col("v") < F.col("m")))
    return x.join(spots.drop("m"), [*by, "slab", "u", "v"]).select(*quads.columns)


def first(points: DataFrame, query: DataFrame, groups: list[Group], direction: str = "nearest") -> DataFrame:
    """k = 1: the best point of each quadrant is on its frontier; evaluate that alone and take the best."""
    from .local import FOUND, scan

    f = minimal(quadrants(points, query, direction)).select("point_id", "x", "y", "query_id")
    found = f.mapInArrow(scan(groups, 1, 1 if direction == "nearest" else -1, False, by_group=True), FOUND)
    from ..model import canonical

    order = Window.partitionBy("query_id").orderBy(*canonical(direction, "x", "y"))
    x = found.withColumn("rank", F.row_number().over(order).cast("long")).filter("rank = 1")
    return x.select("query_id", "rank", "point_id", "x", "y", "agg_dist")


def exposed(quads: DataFrame, gone: DataFrame) -> DataFrame:
    """The frontier rows that appear when ``gone`` (rows of the frontier) is taken off: one box per run of taken points.

    Only what taken points alone dominated can surface: rows right of and above one of them, left of
    the next spot that stays and below the one before. Only rows of these boxes are looked at.
    """
    keys = [*_IN, "point_id", "x", "y"]
    front = stage(minimal(quads), "frontier")
    stays = front.join(gone.select(*keys), keys, "left_anti").select(*_IN, "u", "v").distinct().withColumn("stays", F.lit(True))
    left = front.join(gone.select(*keys), keys, "left_semi").select(*_IN, "u", "v").distinct()
    spots = left.join(stays, [*_IN, "u", "v"], "left_anti").withColumn("stays", F.lit(False)).unionByName(stays)  # a twin that stays keeps the spot
    order = Window.partitionBy(*_IN).orderBy("u")
    on = F.when(F.col("stays"), F.struct("u", "v"))
    nxt = F.first(on, ignorenulls=True).over(order.rowsBetween(1, Window.unboundedFollowing))
    prv = F.last(on, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1))
    box = spots.withColumn("u1", nxt["u"]).withColumn("v1", prv["v"]).filter("not stays")
    box = box.groupBy(*_IN, "u1", "v1").agg(F.min("u").alias("box_u"), F.min("v").alias("box_v"))  # taken neighbours share a box
    rows = quads.join(gone.select(*keys), keys, "left_anti").join(box, _IN).filter("u >= box_u and v >= box_v and (u1 is null or u < u1) and (v1 is null or v < v1)")
    return minimal(rows.drop("u1", "v1"), [*_IN, "box_u", "box_v"]).select(*quads.columns)


def band(quads: DataFrame, k: int) -> DataFrame:
    """Rows that fewer than k rows of the same group dominate; a task's own band first, then the groups'."""

    def local(batches):
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            q, d, u, v = (batch.column(i).to_numpy() for i in range(4))
            key = q * 8 + d
            for one in np.unique(key):
                at = np.flatnonzero(key == one)
                keep[at] = G.band(u[at], v[at], k)
            yield batch.filter(pa.array(keep))

    schema = quads.schema

    def whole(pdf: pd.DataFrame) -> pd.DataFrame:
        return pdf[G.band(pdf["u"].to_numpy(), pdf["v"].to_numpy(), k)]

    some = quads.mapInArrow(local, schema)
    # in two steps, so that no worker gets more than the bands of a 32nd of a quadrant, then the bands of those
    dealt = some.groupBy(*_IN, F.pmod(F.xxhash64("point_id", "x", "y"), F.lit(32))).applyInPandas(whole, schema)
    return dealt.groupBy(*_IN).applyInPandas(whole, schema)
