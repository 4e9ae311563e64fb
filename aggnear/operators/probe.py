"""Segment dragging: the first point that a moving segment meets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..staging import stage
from .layout import PlaneLayout

#: Segments that go to every task; more are a plain join, and should come with a layout.
FEW = 20_000
SEGMENT = "seg_id long, axis string, dir int, lo long, hi long, start long"


def drag(points: DataFrame | PlaneLayout, segs: DataFrame, removed: DataFrame | None = None) -> DataFrame:
    """segs(seg_id, axis, dir, lo, hi, start) -> seg_id, point_id, x, y of the first point met.

    ``v`` segments are vertical, span lo <= y < hi (null: open) and move along x from ``start``
    (the start itself included) upwards (dir 1) or downwards (-1); ``h`` segments likewise with the
    axes exchanged. Of points met together the least on the other axis, then by id, wins. Points in
    ``removed`` (point_id) are passed over: nothing is deleted, dropping the table restores them.
    With a layout only tiles that a segment can meet are read.
    """
    if segs.limit(FEW + 1).count() <= FEW:
        segs = F.broadcast(segs)  # at most FEW rows
    tall = F.col("axis") == "v"
    if isinstance(points, PlaneLayout):
        move_lo, move_hi = F.when(tall, F.col("xlo")).otherwise(F.col("ylo")), F.when(tall, F.col("xhi")).otherwise(F.col("yhi"))
        span_lo, span_hi = F.when(tall, F.col("ylo")).otherwise(F.col("xlo")), F.when(tall, F.col("yhi")).otherwise(F.col("xhi"))
        meets = F.when(F.col("dir") > 0, move_hi >= F.col("start")).otherwise(move_lo <= F.col("start"))
        meets = meets & (F.col("lo").isNull() | (span_hi >= F.col("lo"))) & (F.col("hi").isNull() | (span_lo < F.col("hi")))
        live = stage(points.tiles.join(segs, meets).select("slab", "band", "seg_id", "axis", "dir", "lo", "hi", "start"), "live-tiles")
        x = points.of_tiles(live)
    else:
        x = points.crossJoin(segs)
    if removed is not None:
        x = x.join(removed.select("point_id"), "point_id", "left_anti")
    move, span = F.when(tall, F.col("x")).otherwise(F.col("y")), F.when(tall, F.col("y")).otherwise(F.col("x"))
    ahead = (move - F.col("start")) * F.col("dir")
    x = x.filter((ahead >= 0) & (F.col("lo").isNull() | (span >= F.col("lo"))) & (F.col("hi").isNull() | (span < F.col("hi"))))
    hit = F.min_by(F.struct("point_id", "x", "y"), F.struct(ahead.alias("a"), span.alias("s"), "point_id"))
    return x.groupBy("seg_id").agg(hit.alias("p")).select("seg_id", "p.point_id", "p.x", "p.y")
