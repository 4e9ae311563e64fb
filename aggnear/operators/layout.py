"""Physical layouts of the point set.

Line: points with their ranks from either end, and the bounds of each part of the order. Plane:
tiles (slabs of x, bands of y) with bounds, and convex hulls of dyadic node x run blocks of tiles.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.profile import part_of
from ..functions.subhulls import kept_levels
from ..staging import new_folder, stage


def _number(batches):
    part, row = TaskContext.get().partitionId(), 0
    for batch in batches:
        n = batch.num_rows
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(n, part)), pa.array(np.arange(row, row + n))], names=[*batch.schema.names, "part", "row"])
        row += n


def _ranked(points: DataFrame, order: list, name: str) -> DataFrame:
    """points with their global position in the order: range partitions, numbered inside, plus what stands before."""
    n = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    x = points.repartitionByRange(n, *order).sortWithinPartitions(*order)
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in points.schema)
    x = stage(x.mapInArrow(_number, f"{kinds}, part long, row long"), f"line-{name}")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row per part
    base = x.groupBy("part").agg(F.count("*").alias("n")).withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    return x.join(F.broadcast(base.drop("n")), "part").select(*points.columns, (F.col("base") + F.col("row")).alias(name))


@dataclass
class LineLayout:
    points: DataFrame  # point_id, x, pos: rank by (x, id); sop: rank by (x downwards, id)
    n: int


def build_line(points: DataFrame) -> LineLayout:
    """Sort once; both ranks are needed as ties on a coordinate go by ascending id from either side."""
    p = points.select("point_id", "x")
    up = _ranked(p, [F.col("x"), F.col("point_id")], "pos")
    # the rank from the other end: all points of larger coordinate, then smaller ids at the same one
    up = stage(up, "line-up")
    same = stage(up.groupBy("x").agg(F.min("pos").alias("first"), F.count("*").alias("many")), "line-ties")  # plain sides: a join on a hot x can be split
    n = up.count()
    x = up.join(same, "x").select("point_id", "x", "pos", (F.lit(n) - F.col("first") - F.col("many") + F.col("pos") - F.col("first")).alias("sop"))
    return LineLayout(stage(x, "line-layout"), n)


def hull(x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Indices of the vertices of the convex hull, around it from the least x (and y) on, lower chain first.

    Of coincident points the least id stands; points inside an edge are left out.
    """
    order = np.lexsort((ids, y, x))
    keep = np.r_[True, (np.diff(x[order]) != 0) | (np.diff(y[order]) != 0)]
    order = order[keep]
    if len(order) < 3:
        return order
    px, py = x[order].tolist(), y[order].tolist()

    def half(seq):
        out: list[int] = []
        for i in seq:
            while len(out) > 1 and (px[out[-1]] - px[out[-2]]) * (py[i] - py[out[-2]]) <= (py[out[-1]] - py[out[-2]]) * (px[i] - px[out[-2]]):
                out.pop()
            out.append(i)
        return out

    lower, upper = half(range(len(order))), half(range(len(order) - 1, -1, -1))
    return order[lower[:-1] + upper[:-1]]


_HULL = "level int, node int, run_level int, run int, n long, vertices array<struct<point_id:long,x:long,y:long>>"


#: Tiles that get a folder each; of more, every slab gets one.
FOLDERS = 4096
#: Points of a tile that a layout aims at when it is not told how many tiles to make.
PER_TILE = 1_000_000


@dataclass
class PlaneLayout:
    folder: str
    mode: str
    points: DataFrame  # point_id, x, y[, own], band, slab: a folder per tile or slab
    tiles: DataFrame  # slab, band, xlo, xhi, ylo, yhi, n
    hulls: DataFrame | None
    x_cuts: list[int]
    y_cuts: list[int]
    seconds: dict  # per step of the build

    @property
    def run_levels(self) -> int:
        return _levels(self.y_cuts)

    def of_tiles(self, tiles: DataFrame) -> DataFrame:
        """Points of tiles(slab, band, ...), which is staged: only the folders of tiles (of slabs, if tiles are very many) that are asked for are read."""
        slabs, bands = ([r[0] for r in tiles.select(c).distinct().collect()] for c in ("slab", "band"))  # at most a row per slab, per band
        return self.points.filter(F.col("slab").isin(slabs) & F.col("band").isin(bands)).join(tiles, ["slab", "band"])


def _levels(cuts: list[int]) -> int:
    return int(np.ceil(np.log2(len(cuts) + 1))) + 1


def _cuts(points: DataFrame, c: str, parts: int) -> list[int]:
    """Upper-exclusive cut values between parts of about equal numbers of points."""
    got = points.select(F.percentile_approx(c, [i / parts for i in range(1, parts)], 10_000)).first()[0] or []
    return sorted({int(v) for v in got})


def _hull_of(key_names: list[str]):
    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        if "vertices" in pdf:
            rows = [v for vs in pdf["vertices"] for v in vs]
            ids, x, y = (np.array([r[c] for r in rows], np.int64) for c in ("point_id", "x", "y"))
            n = int(pdf["n"].sum())
        else:
            ids, x, y = (pdf[c].to_numpy(np.int64) for c in ("point_id", "x", "y"))
            n = len(pdf)
        at = hull(x, y, ids)
        return pd.DataFrame([(*key, n, [{"point_id": int(ids[i]), "x": int(x[i]), "y": int(y[i])} for i in at])], columns=[*key_names, "n", "vertices"])

    return run


def _local_hulls(batches):
    """Points of each tile in a batch -> hull vertices: what a task sends on is no tile's points but their hull's."""
    for batch in batches:
        cols = [c.to_numpy() for c in batch.columns]
        order = np.lexsort((cols[4], cols[3]))
        key = cols[3][order].astype(np.int64) * (1 << 32) + cols[4][order]
        keep = [part[hull(cols[1][part], cols[2][part], cols[0][part])] for part in np.split(order, np.flatnonzero(np.diff(key)) + 1) if len(part)]
        many = [len(part) for part in np.split(order, np.flatnonzero(np.diff(key)) + 1) if len(part)]
        if keep:
            first = np.concatenate([[n, *[0] * (len(k) - 1)] for n, k in zip(many, keep)])  # a tile's points are counted at its first vertex
            at = np.concatenate(keep)
            yield pa.RecordBatch.from_arrays([*(c.take(pa.array(at)) for c in batch.columns), pa.array(first)], names=[*batch.schema.names, "n"])


def build_plane(points: DataFrame, mode: str | None = None, slabs: int | None = None, bands: int | None = None, path: str | None = None) -> PlaneLayout:
    """Cut the points into slabs x bands; with a mode also store hulls of dyadic blocks of tiles.

    Without numbers the tiles hold about ``PER_TILE`` points, and there are 8 x 16 at least. Every dyadic
    node of slabs keeps hulls of runs of bands, at the run levels of its mode (``subhulls.kept_levels``):
    all (``dyadic_full``, the earlier structure), lglg many (``fast``), every fourth (``middle``) or single
    bands (``small``). Tasks send on the hulls of what they read, and a block's hull is the hull of its
    children's vertices, so neither a tile nor a block is ever gathered.
    """
    spark, began, seconds = points.sparkSession, time.time(), {}

    def done(step):
        nonlocal began
        seconds[step] = round(time.time() - began, 3)
        began = time.time()

    path = path or new_folder(spark, "plane-layout")
    if slabs is None or bands is None:
        tiles = max(1, points.count() // PER_TILE)
        slabs = slabs or min(1024, max(8, 1 << (math.isqrt(tiles) - 1).bit_length()))
        bands = bands or min(4096, max(16, 1 << (-(-tiles // slabs) - 1).bit_length()))
    x_cuts, y_cuts = _cuts(points, "x", slabs), _cuts(points, "y", bands)
    done("cuts")

    p = points.withColumn("band", part_of(y_cuts, F.col("y"))).withColumn("slab", part_of(x_cuts, F.col("x")))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    by = ["slab", "band"] if (len(x_cuts) + 1) * (len(y_cuts) + 1) <= FOLDERS else ["slab"]
    p.repartitionByRange(n, "slab", "band", "y").sortWithinPartitions("slab", "band", "y").write.partitionBy(*by).parquet(f"{path}/points")
    p = spark.read.schema(p.schema).parquet(f"{path}/points")
    tiles = p.groupBy("slab", "band").agg(F.min("x").alias("xlo"), F.max("x").alias("xhi"), F.min("y").alias("ylo"), F.max("y").alias("yhi"), F.count("*").alias("n"))
    tiles = stage(tiles, "tiles", f"{path}/tiles")
    done("tiles")
    if mode is None:
        return PlaneLayout(path, "none", p, tiles, None, x_cuts, y_cuts, seconds)
    x_levels, y_levels = _levels(x_cuts), _levels(y_cuts)
    kept = kept_levels(mode, y_levels - 1)
    keys = ["slab", "band"]
    some = p.select("point_id", "x", "y", *keys).mapInArrow(_local_hulls, "point_id long, x long, y long, slab int, band int, n long")
    one = F.struct("point_id", "x", "y")
    leaf = some.groupBy(*keys, F.pmod(F.xxhash64("point_id"), F.lit(16)).alias("deal")).agg(F.sum("n").alias("n"), F.collect_list(one).alias("vertices")).drop("deal")
    vertices = "n long, vertices array<struct<point_id:long,x:long,y:long>>"
    leaf = leaf.groupBy(*keys).applyInPandas(_hull_of(keys), f"slab int, band int, {vertices}")
    base = stage(leaf.select(F.lit(0).alias("level"), F.col("slab").alias("node"), F.lit(0).alias("run_level"), F.col("band").alias("run"), "n", "vertices"), "hulls", f"{path}/hulls-0")
    done("leaf hulls")
    names = ["level", "node", "run_level", "run"]
    every, nodes = base, base
    for level in range(x_levels):
        if level:
            up = nodes.select(F.lit(level).alias("level"), F.shiftright("node", 1).alias("node"), "run_level", "run", "n", "vertices")
            nodes = stage(up.groupBy(*names).applyInPandas(_hull_of(names), _HULL), "hulls", f"{path}/hulls-{level}")
            every = every.unionByName(nodes)
        runs, at = nodes, 0
        for r in kept[1:]:
            up = runs.select("level", "node", F.lit(r).alias("run_level"), F.shiftright("run", r - at).alias("run"), "n", "vertices")
            runs, at = up.groupBy(*names).applyInPandas(_hull_of(names), _HULL), r
            every = every.unionByName(runs)
    hulls = stage(every, "hulls", f"{path}/hulls")
    done("blocks")
    return PlaneLayout(path, mode, p, tiles, hulls, x_cuts, y_cuts, seconds)
