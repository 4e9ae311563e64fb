"""Cells of the grid through a group's points: location, linear form, frontier cells, best point in a rectangle."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import plane_geometry as G
from ..functions import weights
from ..functions.profile import Group
from ..functions.subhulls import kept_levels
from ..model import sign_of
from . import frontier
from .layout import PlaneLayout


#: Pieces of the x axis that meet all of the y axis in one place.
STRIP = 512


def grid(query: DataFrame) -> DataFrame:
    """All (m + 1)^2 cells of each group's grid: query_id, ci, cj, their bounds, and ca, cb, cc of the distance inside.

    ci and cj count the grid lines at or below. A join of the two axes' pieces by group and strip of ``STRIP`` pieces of x:
    a group's grid is made strip by strip in many tasks, for one copy of its y axis a strip.
    """
    x, y = (weights.intervals(query, c) for c in ("x", "y"))
    x = x.select("query_id", F.expr(f"i div {STRIP}").alias("strip"), F.col("i").alias("ci"), F.col("lo").alias("xlo"), F.col("hi").alias("xhi"), F.col("slope").alias("ca"), F.col("rest").alias("rx"))
    y = y.select("query_id", F.col("i").alias("cj"), F.col("lo").alias("ylo"), F.col("hi").alias("yhi"), F.col("slope").alias("cb"), F.col("rest").alias("ry"))
    strips = query.groupBy("query_id").agg(F.expr(f"count(distinct qx) div {STRIP}").alias("last"))
    y = y.join(strips, "query_id").withColumn("strip", F.explode(F.sequence(F.lit(0).cast("long"), "last"))).drop("last")
    return x.join(y, ["query_id", "strip"]).withColumn("cc", F.col("rx") + F.col("ry")).drop("strip", "rx", "ry")


def coefficients(query: DataFrame) -> DataFrame:
    """(query_id, ci, cj, ca, cb, cc) of every cell: distance = ca * x + cb * y + cc inside it."""
    return grid(query).select("query_id", "ci", "cj", "ca", "cb", "cc")


_CELL = "query_id long, quad int, u long, v long, point_id long, x long, y long, ci long, cj long, agg_dist long"


def _located(groups: list[Group], direction: str, far: dict | None):
    """Quadrant rows -> their cell (lines in the quadrant's own coordinates) and distance by the cell's linear form."""
    known = {g.query_id: g for g in groups}

    def run(batches):
        for batch in batches:
            q, d, u, v, ids, x, y = (c.to_numpy() for c in batch.columns)
            ci, cj, f = (np.zeros(len(q), np.int64) for _ in range(3))
            for key in np.unique(q * 8 + d).tolist():
                at = np.flatnonzero(q * 8 + d == key)
                g = known[key // 8]
                frame = G.Frame.of(g, key % 8, direction, (far or {}).get((key // 8, key % 8), (0, 0)))
                fu, fv = frame.axes(g)
                ci[at], cj[at] = np.searchsorted(fu.v, u[at], "right"), np.searchsorted(fv.v, v[at], "right")
                (a, c), (b, e) = fu.slope_at(u[at]), fv.slope_at(v[at])
                f[at] = a * u[at] + b * v[at] + c + e
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(ci), pa.array(cj), pa.array(f)], names=[*batch.schema.names, "ci", "cj", "agg_dist"])

    return run


def far_corners(quads_near: DataFrame) -> dict:
    """(query_id, quad) -> the coordinates of the quadrant's far corner: four rows a group."""
    x = quads_near.groupBy("query_id", "quad").agg(
        F.max("x").alias("x1"), F.min("x").alias("x0"), F.max("y").alias("y1"), F.min("y").alias("y0")
    )
    out = {}
    for r in x.collect():
        sx, sy = G.QUADS[r.quad]
        out[r.query_id, r.quad] = (r.x1 if sx > 0 else r.x0, r.y1 if sy > 0 else r.y0)
    return out


def cell_of(points: DataFrame, query: DataFrame, groups: list[Group], direction: str = "nearest") -> DataFrame:
    """Every point once per group with quad, u, v, cell (ci, cj) and agg_dist."""
    quads = frontier.quadrants(points, query, direction)
    far = far_corners(quads) if direction == "farthest" else None
    return quads.mapInArrow(_located(groups, direction, far), _CELL)


def frontier_cells(points: DataFrame, query: DataFrame, groups: list[Group], direction: str = "nearest") -> DataFrame:
    """query_id, quad, ci, cj, entry_id (leftmost vertex), floor_id (lowest vertex) of the cells that hold frontier vertices."""
    located = cell_of(points, query, groups, direction)
    f = frontier.minimal(located)
    out = f.groupBy("query_id", "quad", "ci", "cj").agg(
        F.min_by("point_id", F.struct("u", "v", "point_id", "x", "y")).alias("entry_id"),
        F.min_by("point_id", F.struct("v", "u", "point_id", "x", "y")).alias("floor_id"),
    )
    return out.withColumn("quad", F.col("quad").cast("long"))


def cell_topk(points: DataFrame, query: DataFrame, groups: list[Group], k: int, direction: str) -> DataFrame:
    """The k best of every occupied cell: (query_id, point_id, x, y, agg_dist)."""
    located = cell_of(points, query, groups, direction)
    sign = sign_of(direction)
    order = Window.partitionBy("query_id", "quad", "ci", "cj").orderBy(F.col("agg_dist") * sign, "point_id", "x", "y")
    return located.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= k).select("query_id", "point_id", "x", "y", "agg_dist")


# Rectangles --------------------------------------------------------------------------------------

RECT = "query_id long, rect_id long, xlo long, xhi long, ylo long, yhi long, ca long, cb long, cc long"


def _dyadic(a: int, b: int) -> list[tuple[int, int]]:
    """[a, b) as (level, block) of aligned powers of two."""
    out = []
    while a < b:
        level = min((a & -a).bit_length() - 1 if a else 62, (b - a).bit_length() - 1)
        out.append((level, a >> level))
        a += 1 << level
    return out


def _inside(lo, hi, cuts: list[int]) -> tuple[int, int, list[int]]:
    """Parts fully inside [lo, hi) as a range, and parts partly inside."""
    edges = [None, *cuts, None]
    full, part = [], []
    for i in range(len(cuts) + 1):
        a, b = edges[i], edges[i + 1]
        if (hi is not None and a is not None and a >= hi) or (lo is not None and b is not None and b <= lo):
            continue
        whole = (lo is None or (a is not None and a >= lo)) and (hi is None or (b is not None and b <= hi))
        (full if whole else part).append(i)
    return (full[0], full[-1] + 1, part) if full else (0, 0, part)


def _cover(layout: PlaneLayout):
    kept = kept_levels(layout.mode, layout.run_levels - 1)
    x_cuts, y_cuts = layout.x_cuts, layout.y_cuts

    def run(batches):
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                x0, x1, xp = _inside(r["xlo"], r["xhi"], x_cuts)
                y0, y1, yp = _inside(r["ylo"], r["yhi"], y_cuts)
                own = tuple(r.values())
                for level, node in _dyadic(x0, x1):
                    for rl, run_ in _dyadic(y0, y1):
                        keep = max(x for x in kept if x <= rl)  # the largest stored level not above
                        rows += [(*own, level, node, keep, (run_ << (rl - keep)) + i) for i in range(1 << (rl - keep))]
                for s in range(len(x_cuts) + 1):
                    for b in range(len(y_cuts) + 1):
                        if (s in xp and (b in yp or y0 <= b < y1)) or (b in yp and x0 <= s < x1):
                            rows.append((*own, -1, s, -1, b))
            cols = list(zip(*rows)) if rows else [[] for _ in range(13)]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=[*batch.schema.names, "level", "node", "run_level", "run"])

    return run


def optimum(layout: PlaneLayout, rects: DataFrame, direction: str = "nearest") -> tuple[DataFrame, DataFrame]:
    """Best point of each rectangle [xlo, xhi) x [ylo, yhi) (null: open) under its linear form.

    A rectangle is covered by dyadic blocks of whole tiles, on whose hulls the extreme vertex is found
    by binary search, and by border tiles, whose points are read. Returns (query_id, rect_id, point_id,
    x, y, agg_dist) and counters (query_id, rect_id, runs, vertices: those looked at, border_points). Of equal
    values the least id of those seen wins: hulls leave out points inside an edge, so ties are
    complete only up to distance.
    """
    sign = sign_of(direction)
    cover = rects.mapInArrow(_cover(layout), f"{RECT}, level long, node long, run_level long, run long")
    value = F.col("ca") * F.col("x") + F.col("cb") * F.col("y") + F.col("cc")
    blocks = cover.filter("level >= 0").join(layout.hulls, ["level", "node", "run_level", "run"])
    blocks = blocks.select("query_id", "rect_id", extreme("vertices", F.col("ca") * sign, F.col("cb") * sign).alias("e"), "ca", "cb", "cc")
    blocks = blocks.select("query_id", "rect_id", "e.point_id", "e.x", "e.y", "e.looked", "ca", "cb", "cc").withColumn("agg_dist", value)
    edge = cover.filter("level < 0").select("query_id", "rect_id", "xlo", "xhi", "ylo", "yhi", "ca", "cb", "cc", F.col("node").cast("int").alias("slab"), F.col("run").cast("int").alias("band"))
    edge = edge.join(layout.points.select("point_id", "x", "y", "slab", "band"), ["slab", "band"])
    edge = edge.filter("(xlo is null or x >= xlo) and (xhi is null or x < xhi) and (ylo is null or y >= ylo) and (yhi is null or y < yhi)")
    edge = edge.select("query_id", "rect_id", "point_id", "x", "y", value.alias("agg_dist"))
    every = blocks.select("query_id", "rect_id", "point_id", "x", "y", "agg_dist").unionByName(edge)
    best = every.groupBy("query_id", "rect_id").agg(F.min(F.struct((F.col("agg_dist") * sign).alias("k"), "point_id", "x", "y", "agg_dist")).alias("b"))
    runs = cover.groupBy("query_id", "rect_id").agg(F.sum(F.when(F.col("level") >= 0, 1).otherwise(0)).alias("runs"))
    seen = blocks.groupBy("query_id", "rect_id").agg(F.sum("looked").alias("vertices"))
    border = edge.groupBy("query_id", "rect_id").agg(F.count("*").alias("border_points"))
    counters = runs.join(seen, ["query_id", "rect_id"], "left").join(border, ["query_id", "rect_id"], "left").na.fill(0)
    return best.select("query_id", "rect_id", "b.point_id", "b.x", "b.y", "b.agg_dist"), counters


def _axis_pieces(axis, cuts: list[int]) -> np.ndarray:
    """The piece of a group's axis that holds each part between cuts wholly, else -1: the parts of ``_inside`` the other way round."""
    at = np.array(cuts, np.int64)
    first = np.r_[0, np.searchsorted(axis.v, at, "right")]
    last = np.r_[np.searchsorted(axis.v, at, "left"), len(axis.v)]
    return np.where(first == last, first, -1)


def _block_cells(groups: list[Group], x_cuts: list[int], y_cuts: list[int]):
    """Numbers of groups -> the rectangles of their cells that hold a whole tile: at most as many as there are tiles."""

    def run(batches):
        for batch in batches:
            rows = []
            for i in batch.column(0).to_pylist():
                g = groups[i]
                sides = []
                for axis, cuts in ((g.fx, x_cuts), (g.fy, y_cuts)):
                    v, cw, cwv = axis.v.tolist(), axis.cw.tolist(), axis.cwv.tolist()
                    held = [int(c) for c in np.unique(_axis_pieces(axis, cuts)) if c >= 0]
                    sides.append([(c, v[c - 1] if c else None, v[c] if c < len(v) else None, 2 * cw[c] - cw[-1], cwv[-1] - 2 * cwv[c]) for c in held])
                rows += [(g.query_id, ci * (len(g.fy.v) + 1) + cj, xlo, xhi, ylo, yhi, ca, cb, rx + ry) for ci, xlo, xhi, ca, rx in sides[0] for cj, ylo, yhi, cb, ry in sides[1]]
            cols = list(zip(*rows)) if rows else [[] for _ in range(9)]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=[c.split()[0] for c in RECT.split(", ")])

    return run


_BORDER = "query_id long, rect_id long, point_id long, x long, y long, agg_dist long, n long"


def _border_cells(groups: list[Group], x_cuts: list[int], y_cuts: list[int], sign: int):
    """Points of tiles -> per batch, group and cell the best of those whose tile is not wholly inside the cell, and their number."""

    def run(batches):
        pieces = [(_axis_pieces(g.fx, x_cuts), _axis_pieces(g.fy, y_cuts)) for g in groups]
        for batch in batches:
            ids, x, y, slab, band = (c.to_numpy() for c in batch.columns)
            for g, (px, py) in zip(groups, pieces):
                at = np.flatnonzero((px[slab] < 0) | (py[band] < 0))
                rect = np.searchsorted(g.fx.v, x[at], "right") * (len(g.fy.v) + 1) + np.searchsorted(g.fy.v, y[at], "right")
                f = g(x[at], y[at])
                order = np.lexsort((y[at], x[at], ids[at], f * sign, rect))
                rect, start = np.unique(rect[order], return_index=True)
                n, best = np.diff(np.r_[start, len(order)]), at[order[start]]
                cols = [np.full(len(rect), g.query_id), rect, ids[best], x[best], y[best], f[order[start]], n]
                yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in cols], names=[c.split()[0] for c in _BORDER.split(", ")])

    return run


def cell_optimum(layout: PlaneLayout, groups: list[Group], direction: str = "nearest") -> tuple[DataFrame, DataFrame]:
    """``optimum`` of ``cell_rectangles`` for the cells that hold a point, without making the (m + 1)^2 others.

    Cells are disjoint, so those that hold whole tiles are at most as many as the tiles: they alone are covered by
    blocks and searched by hulls. Every other point finds its cell by binary search on the two axes.
    """
    sign, spark = sign_of(direction), layout.points.sparkSession
    rects = spark.range(len(groups)).mapInArrow(_block_cells(groups, layout.x_cuts, layout.y_cuts), RECT)
    cover = rects.mapInArrow(_cover(layout), f"{RECT}, level long, node long, run_level long, run long").filter("level >= 0")
    blocks = cover.join(layout.hulls, ["level", "node", "run_level", "run"])
    blocks = blocks.select("query_id", "rect_id", extreme("vertices", F.col("ca") * sign, F.col("cb") * sign).alias("e"), "ca", "cb", "cc")
    blocks = blocks.select("query_id", "rect_id", "e.point_id", "e.x", "e.y", (F.col("ca") * F.col("e.x") + F.col("cb") * F.col("e.y") + F.col("cc")).alias("agg_dist"), "e.looked")
    edge = layout.points.select("point_id", "x", "y", "slab", "band").mapInArrow(_border_cells(groups, layout.x_cuts, layout.y_cuts, sign), _BORDER)
    none = F.lit(0).cast("long")
    every = blocks.select(*blocks.columns[:6], F.lit(1).cast("long").alias("run"), "looked", none.alias("n")).unionByName(edge.select(*blocks.columns[:6], none.alias("run"), none.alias("looked"), "n"))
    best = every.groupBy("query_id", "rect_id").agg(F.min(F.struct((F.col("agg_dist") * sign).alias("k"), "point_id", "x", "y", "agg_dist")).alias("b"))
    counters = every.groupBy("query_id", "rect_id").agg(F.sum("run").alias("runs"), F.sum("looked").alias("vertices"), F.sum("n").alias("border_points"))
    return best.select("query_id", "rect_id", "b.point_id", "b.x", "b.y", "b.agg_dist"), counters


def cell_rectangles(query: DataFrame) -> DataFrame:
    """All grid cells of the groups as rectangles with their linear forms; rect_id is ci times the group's rows plus cj."""
    g = grid(query)
    rows = g.groupBy("query_id").agg((F.max("cj") + 1).alias("ny"))
    g = g.join(rows, "query_id").withColumn("rect_id", F.col("ci") * F.col("ny") + F.col("cj"))
    return g.select("query_id", "rect_id", "xlo", "xhi", "ylo", "yhi", "ca", "cb", "cc")


EXTREME = "point_id long, x long, y long, looked long"


def extreme(vertices: str, ca, cb):
    """The vertex with the least ca * x + cb * y, and the vertices looked at.

    Vertices stand around the hull from the least x on (``layout.hull``): the lower chain up to the largest
    x, then the upper chain back. Along the chain that faces the direction the values fall, then
    rise, so each is searched by halving: lg h looks, not h.
    """

    @F.pandas_udf(EXTREME)
    def search(rings: pd.Series, a: pd.Series, b: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([_extreme(r, int(p), int(q)) for r, p, q in zip(rings, a, b)], columns=["point_id", "x", "y", "looked"])

    return search(F.col(vertices), ca, cb)


def _extreme(ring, a: int, b: int) -> tuple:
    n, looked, best = len(ring), 0, None

    def key(i):
        p = ring[i % n]
        return a * p["x"] + b * p["y"], p["point_id"], i % n

    turn, hi = 0, n - 1
    while turn < hi:  # the largest x: it rises, then falls
        mid = (turn + hi) // 2
        looked += 1
        turn, hi = (mid + 1, hi) if ring[mid]["x"] < ring[mid + 1]["x"] else (turn, mid)
    for lo, hi in ((0, turn), (turn, n)):
        end = hi
        while lo < hi:
            mid = (lo + hi) // 2
            looked += 1
            lo, hi = (lo, mid) if key(mid)[0] <= key(mid + 1)[0] else (mid + 1, hi)
        for i in (lo, min(lo + 1, end)):  # both ends of an edge of equal values
            best = key(i) if best is None else min(best, key(i))
    v = ring[best[2]]
    return v["point_id"], v["x"], v["y"], looked
