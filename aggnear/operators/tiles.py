"""Tile pruning: bounds of a group's distance over a tile, and the tiles that can hold an answer."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.profile import Group, each_group
from ..model import sign_of
from ..staging import stage
from .layout import PlaneLayout
from .local import CHUNK, FOUND, meet_cuts

_BOUND = pa.schema([("query_id", pa.int64()), ("slab", pa.int32()), ("band", pa.int32()), ("n", pa.int64()), ("low", pa.int64()), ("high", pa.int64())])


_TILE = ["slab", "band", "xlo", "xhi", "ylo", "yhi", "n"]


def _bounds_of(g: Group, tiles) -> pa.RecordBatch:
    """Each axis function is convex: least at the point nearest the anchor, greatest at an end."""
    slab, band, xlo, xhi, ylo, yhi, n = tiles
    ax, ay = g.anchor
    low = g.fx(np.clip(ax, xlo, xhi)) + g.fy(np.clip(ay, ylo, yhi))
    high = np.maximum(g.fx(xlo), g.fx(xhi)) + np.maximum(g.fy(ylo), g.fy(yhi))
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(n), g.query_id)), pa.array(slab), pa.array(band), pa.array(n), pa.array(low), pa.array(high)], schema=_BOUND)


def _bounds(groups: list[Group]):
    def run(batches):
        for batch in batches:
            tiles = [c.to_numpy() for c in batch.columns]
            for g in groups:
                yield _bounds_of(g, tiles)

    return run


def _bounds_dealt(tiles):
    def run(batches):
        for g in each_group(batches):
            yield _bounds_of(g, tiles)

    return run


def _dealt(query: DataFrame) -> DataFrame:
    """The rows of a group one after the other, groups dealt out."""
    n = int(query.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return query.select("query_id", "qx", "qy", "w").repartition(n, "query_id").sortWithinPartitions("query_id")


def _all_bounds(layout: PlaneLayout, groups: list[Group] | DataFrame) -> DataFrame:
    """query_id, slab, band, n, low, high; groups that are too many for the plan come as their table and meet the list of tiles."""
    kinds, tiles = "query_id long, slab int, band int, n long, low long, high long", layout.tiles.select(*_TILE)
    if not isinstance(groups, DataFrame):
        return tiles.mapInArrow(_bounds(groups), kinds)
    got = tiles.toPandas()  # a row per tile of PER_TILE points
    return _dealt(groups).mapInArrow(_bounds_dealt([got[c].to_numpy(np.int32 if c in ("slab", "band") else np.int64) for c in _TILE]), kinds)


def candidate_tiles(layout: PlaneLayout, groups: list[Group] | DataFrame, k: int, direction: str) -> DataFrame:
    """(query_id, slab, band) of the tiles that may hold one of the k best (all ties included).

    Tiles sorted by their worst value until they hold k points give a value that k points reach;
    a tile whose best value does not reach it is out. Points that a group leaves out do not count.
    """
    near = sign_of(direction) > 0
    b = _all_bounds(layout, groups)
    if "own" in layout.points.columns:
        away = layout.points.groupBy("own", "slab", "band").agg(F.count("*").alias("away")).withColumnRenamed("own", "query_id")
        b = b.join(away, ["query_id", "slab", "band"], "left").withColumn("n", F.col("n") - F.coalesce("away", F.lit(0))).drop("away")
    worst, good = (F.col("high"), F.col("low")) if near else (-F.col("low"), -F.col("high"))
    b = b.withColumn("worst", worst).withColumn("good", good).filter("n > 0")
    run = Window.partitionBy("query_id").orderBy("worst").rangeBetween(Window.unboundedPreceding, 0)
    b = b.withColumn("upto", F.sum("n").over(run))
    tau = F.min(F.when(F.col("upto") >= k, F.col("worst"))).over(Window.partitionBy("query_id"))
    b = b.withColumn("tau", tau)
    return b.filter(F.col("tau").isNull() | (F.col("good") <= F.col("tau"))).select("query_id", "slab", "band", "n")


def tiles_within(layout: PlaneLayout, groups: list[Group], tau: DataFrame, direction: str) -> DataFrame:
    """(query_id, slab, band) of the tiles that can hold a point as good as tau(query_id, tau)."""
    near = sign_of(direction) > 0
    b = _all_bounds(layout, groups)
    b = b.join(tau, "query_id").filter(F.col("low") <= F.col("tau") if near else F.col("high") >= F.col("tau"))
    return b.select("query_id", "slab", "band")


def _cuts_of(query, live):
    """A group's rows and its live tiles -> rows (tile, parts, query_id, v, axis, w, rest) of its distance within each tile."""
    live = live if query.num_rows else live.slice(0, 0)
    g = None if not live.num_rows else Group.of(query["query_id"][0].as_py(), *(query[c].to_numpy() for c in ("qx", "qy", "w")))
    out = []
    for tile, parts, *ends in zip(*(live[c].to_pylist() for c in ("tile", "parts", "xlo", "xhi", "ylo", "yhi"))):
        for axis, f, lo, hi in ((0, g.fx, *ends[:2]), (1, g.fy, *ends[2:])):
            v, w, rest = f.cut(lo, hi)
            m = len(v)
            out.append((np.full(m, tile), np.full(m, parts), np.full(m, g.query_id), v, np.full(m, axis), w, np.r_[rest, np.zeros(m - 1, np.int64)]))
    cols = [np.concatenate(c) for c in zip(*out)] or [np.zeros(0, np.int64)] * 7
    return pa.table([pa.array(c) for c in cols], names=["tile", "parts", "query_id", "v", "axis", "w", "rest"])


def found_dealt(layout: PlaneLayout, query: DataFrame, k: int, direction: str) -> DataFrame:
    """The k best of each group per piece of its live tiles, for batches too large for the plan: a group goes to a tile as its distance within it."""
    n, none = int(query.sparkSession.conf.get("spark.sql.shuffle.partitions")), F.lit(None).cast("long")
    live = stage(candidate_tiles(layout, query, k, direction).drop("n"), "live-tiles")
    tiles = layout.tiles.join(live.select("slab", "band").distinct(), ["slab", "band"])
    tiles = tiles.withColumn("tile", F.col("slab").cast("long") * F.lit(1 << 20) + F.col("band"))
    tiles = stage(tiles.withColumn("parts", F.least(F.ceil(F.col("n") / CHUNK), F.lit(1024)).cast("long")).drop("n"), "chunk-tiles")
    p = layout.of_tiles(tiles.select("slab", "band", "tile", "parts"))
    chunk = F.col("tile") * 1024 + F.pmod(F.xxhash64("point_id", "x", "y"), F.col("parts"))
    own = F.col("own") if "own" in p.columns else none
    p = p.select(chunk.alias("chunk"), F.lit(0).alias("kind"), none.alias("query_id"), "point_id", "x", "y", own.cast("long").alias("own"), none.alias("w"))
    live = live.join(tiles, ["slab", "band"]).select("query_id", "tile", "parts", "xlo", "xhi", "ylo", "yhi")
    q = query.select("query_id", "qx", "qy", "w").groupBy("query_id").cogroup(live.groupBy("query_id"))
    q = q.applyInArrow(_cuts_of, "tile long, parts long, query_id long, v long, axis long, w long, rest long")
    chunk = F.explode(F.sequence(F.col("tile") * 1024, F.col("tile") * 1024 + F.col("parts") - 1))
    q = q.select(chunk.alias("chunk"), F.lit(1).alias("kind"), "query_id", none.alias("point_id"), F.col("v").alias("x"), F.col("axis").alias("y"), F.col("rest").alias("own"), "w")
    return p.unionByName(q).repartition(n, "chunk").sortWithinPartitions("chunk", "kind", "query_id").mapInArrow(meet_cuts(k, sign_of(direction)), FOUND)


def candidates(layout: PlaneLayout, groups: list[Group] | DataFrame, k: int, direction: str) -> DataFrame:
    """The points of the candidate tiles, a row per group that may need them."""
    tiles = stage(candidate_tiles(layout, groups, k, direction).drop("n"), "live-tiles")
    return layout.of_tiles(tiles).drop("slab", "band")
