"""The methods that the search is held against, with what they cost."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import plane_geometry as G
from ..functions import weights
from ..functions.profile import Group
from ..plans.plane import merge_quadrants
from . import cells, frontier, peel
from .layout import PlaneLayout, hull


def all_cells(layout: PlaneLayout, groups: list[Group], direction: str = "nearest") -> tuple[DataFrame, DataFrame]:
    """k = 1: the best point of every grid cell that holds one, by its hulls where it holds whole tiles, then the best of all."""
    best, cost = cells.cell_optimum(layout, groups, direction)
    return merge_quadrants(best.drop("rect_id"), 1, direction), cost


def full_frontier(points: DataFrame, query: DataFrame, groups: list[Group], direction: str = "nearest") -> DataFrame:
    """k = 1: evaluate every frontier vertex."""
    return frontier.first(points, query, groups, direction)


def grid_walk(points: DataFrame, query: DataFrame, groups: list[Group], direction: str = "nearest") -> DataFrame:
    """k = 1: keep the cells of the grid that the frontier walks through, and take the best point of those."""
    located = cells.cell_of(points, query, groups, direction)
    keys = ["query_id", "quad", "ci", "cj"]
    walked = frontier.minimal(located).select(*keys).distinct()
    for c, axis in (("ci", "x"), ("cj", "y")):  # the grid is the product of its axes' pieces: a cell is in it if both of its are
        walked = walked.join(weights.intervals(query, axis).select("query_id", F.col("i").alias(c)), ["query_id", c], "left_semi")
    return merge_quadrants(located.join(walked, keys).select("query_id", "point_id", "x", "y", "agg_dist"), 1, direction)


def _repeel(groups: list[Group], k: int, direction: str, reuse: str | None):
    """One quadrant, one answer a round, the frontier cells afresh each time."""
    known = {g.query_id: g for g in groups}
    sign = 1 if direction == "nearest" else -1

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        g = known[int(key[0])]
        pl = peel.of_group(g, int(key[1]), direction, pdf["point_id"], pdf["x"], pdf["y"])
        q, taken, searched, optima, kept = pl.q, [], 0, 0, set()
        for _ in range(min(k, len(q.ids))):
            live = np.flatnonzero(q.live)
            front = live[G.minimal(q.u[live], q.v[live])]
            now = {q.cell(p) for p in front.tolist()}
            searched += len(now - kept) if reuse == "cells" else len(now)
            optima += len(now)
            kept |= now
            code = q.ci * (len(q.lines_v) + 1) + q.cj
            inside = live[np.isin(code[live], [a * (len(q.lines_v) + 1) + b for a, b in now])]
            z = inside[np.lexsort((pl.y[inside], pl.x[inside], q.ids[inside], pl.f[inside]))[0]]
            taken.append(int(z))
            q.live[z] = False
        at = np.array(taken, np.int64)
        return pd.DataFrame({"query_id": g.query_id, "quad": int(key[1]), "point_id": q.ids[at], "x": pl.x[at], "y": pl.y[at], "agg_dist": pl.f[at] * sign, "cells_searched": searched, "optima": optima})

    return run


_REPEEL = "query_id long, quad int, point_id long, x long, y long, agg_dist long, cells_searched long, optima long"


def repeel(points: DataFrame, query: DataFrame, groups: list[Group], k: int, direction: str = "nearest", reuse: str | None = None) -> tuple[DataFrame, DataFrame]:
    """Answers and costs when every round finds all frontier cells again (reuse None) or keeps the cells but searches each again ("cells")."""
    x = peel.quads_of(points, query).groupBy("query_id", "quad").applyInPandas(_repeel(groups, k, direction, reuse), _REPEEL)
    cost = x.groupBy("query_id", "quad").agg(F.max("cells_searched").alias("cells_searched"), F.max("optima").alias("optima"))
    return merge_quadrants(x.select("query_id", "point_id", "x", "y", "agg_dist"), k, direction), cost


def rebuild_hulls(layout: PlaneLayout, gone: DataFrame) -> DataFrame:
    """True deletion: the hulls of the single tiles that hold a point of gone(point_id), built again without it.

    Returns slab, band, n_rebuilt (points read again): the price that cutting cells into shards saves.
    """
    touched = layout.points.join(gone.select("point_id"), "point_id", "left_semi").select("slab", "band").distinct()
    left = layout.points.join(touched, ["slab", "band"], "left_semi").join(gone.select("point_id"), "point_id", "left_anti")

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x, y, ids = (pdf[c].to_numpy(np.int64) for c in ("x", "y", "point_id"))
        at = hull(x, y, ids)
        v = [{"point_id": int(ids[i]), "x": int(x[i]), "y": int(y[i])} for i in at]
        return pd.DataFrame([(*key, len(pdf), v)], columns=["slab", "band", "n_rebuilt", "vertices"])

    return left.groupBy("slab", "band").applyInPandas(run, "slab int, band int, n_rebuilt long, vertices array<struct<point_id:long,x:long,y:long>>")
