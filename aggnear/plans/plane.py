"""Planner and entry point of plane searches."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.profile import Group, agg_dist, few_groups, groups_or_table, load_groups, merged
from ..model import canonical, check_k, checked_points, checked_query, sign_of
from ..operators import cells, frontier, peel, tiles
from ..operators.layout import PlaneLayout, build_plane
from ..operators.local import FOUND, scan, scan_dealt
from ..staging import stage

STRATEGIES = ("scan", "scan_dealt", "scan_joins", "tiles", "skyband", "cells", "peel_grouped", "peel_driver", "hull", "auto")


@dataclass(frozen=True)
class GroupQueryPlan:
    """What a search will do; ``build`` turns it into one lazy DataFrame."""

    direction: str
    k: int
    strategy: str
    layout: str
    evaluator: str = "prefix"
    counters: bool = False


#: Points that the grouped peel may find in all, unpruned; beyond that the cells strategy answers.
PEEL_ROWS = 20_000_000


def plan(points, k: int, direction: str, strategy: str = "auto", evaluator: str = "auto", counters: bool = False, query: DataFrame | None = None) -> GroupQueryPlan:
    """``auto``: counters ask for the peel; a batch too large to travel with the plan is dealt out; a layout is pruned by tiles; anything else is one scan."""
    sign_of(direction)
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy must be one of {STRATEGIES}")
    has = isinstance(points, PlaneLayout)
    if strategy == "auto":
        few = query is None or few_groups(query)
        strategy = "peel_grouped" if counters else "scan_dealt" if not few else "tiles" if has else "scan"
    if strategy == "hull" and (direction != "farthest" or k != 1 or not has or points.hulls is None):
        raise ValueError("the hull shortcut answers farthest, k = 1, on a layout with hulls")
    if strategy == "peel_grouped" and not has and not counters and points.count() > PEEL_ROWS:
        strategy = "cells"
    return GroupQueryPlan(direction, check_k(k), strategy, points.mode if has else "none", "prefix" if evaluator == "auto" else evaluator, counters)


def merge_quadrants(found: DataFrame, k: int, direction: str) -> DataFrame:
    """The k best of what parts of the plane have found, in canonical order."""
    order = Window.partitionBy("query_id").orderBy(*canonical(direction, "x", "y"))
    x = found.withColumn("rank", F.row_number().over(order).cast("long")).filter(F.col("rank") <= k)
    return x.select("query_id", "rank", "point_id", "x", "y", "agg_dist")


def _scan(points: DataFrame, groups: list[Group], k: int, direction: str, by_group: bool = False) -> DataFrame:
    own = "own" in points.columns
    cols = ["point_id", "x", "y", *(["own"] if own else []), *(["query_id"] if by_group else [])]
    return points.select(*cols).mapInArrow(scan(groups, k, sign_of(direction), own, by_group), FOUND)


def complete_ties(layout: PlaneLayout, groups: list[Group], tau: DataFrame, k: int, direction: str) -> DataFrame:
    """The canonical k best among all points as good as the k-th value tau(query_id, tau): only tiles that can hold such points are read."""
    live = stage(tiles.tiles_within(layout, groups, tau, direction), "tie-tiles")
    points = layout.of_tiles(live).drop("slab", "band")
    found = _scan(points, groups, k, direction, by_group=True).join(tau, "query_id")
    ok = (F.col("agg_dist") - F.col("tau")) * sign_of(direction) <= 0
    return merge_quadrants(found.filter(ok).drop("tau"), k, direction)


def _peel_driver(points: DataFrame, query: DataFrame, groups: list[Group], k: int, direction: str) -> DataFrame:
    """The peel as plans, two jobs a round: for small k and for study. Each round's best point of a quadrant is an answer."""
    quads = stage(frontier.quadrants(points, query, direction, narrow=True), "peel-points")
    keys = ["query_id", "quad", "point_id", "x", "y"]
    front = stage(frontier.minimal(quads), "peel-front")
    out = None
    for _ in range(k):
        scored = _evaluate(front, groups, direction)
        order = Window.partitionBy("query_id", "quad").orderBy(*canonical(direction, "x", "y"))
        best = stage(scored.withColumn("r", F.row_number().over(order)).filter("r = 1").drop("r"), "peel-best")
        out = best if out is None else out.unionByName(best)
        quads = stage(quads.join(best.select(*keys), keys, "left_anti"), "peel-points")
        around = Window.partitionBy("query_id", "quad").orderBy("u")
        spots = front.select("query_id", "quad", "u", "v").distinct().withColumn("u_next", F.lead("u").over(around)).withColumn("v_prev", F.lag("v").over(around))
        box = best.join(spots, ["query_id", "quad", "u", "v"]).select("query_id", "quad", F.col("u").alias("u0"), F.col("v").alias("v0"), "u_next", "v_prev")
        inside = quads.join(box, ["query_id", "quad"]).filter("u >= u0 and v >= v0 and (u_next is null or u < u_next) and (v_prev is null or v < v_prev)")
        stay = front.join(best.select(*keys), keys, "left_anti")
        new = frontier.minimal(inside.select(*quads.columns).unionByName(stay.join(box, ["query_id", "quad"], "left_semi")))
        front = stage(new.unionByName(stay.join(box, ["query_id", "quad"], "left_anti")), "peel-front")
    return merge_quadrants(out.select("query_id", "point_id", "x", "y", "agg_dist"), k, direction)


def _evaluate(quad_rows: DataFrame, groups: list[Group], direction: str) -> DataFrame:
    """Quadrant rows plus agg_dist."""
    import numpy as np
    import pyarrow as pa

    known = {g.query_id: g for g in groups}
    names = quad_rows.columns

    def run(batches):
        for batch in batches:
            q, x, y = (batch.column(names.index(c)).to_numpy() for c in ("query_id", "x", "y"))
            f = np.zeros(len(q), np.int64)
            for one in np.unique(q).tolist():
                at = q == one
                f[at] = known[one](x[at], y[at])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(f)], names=[*names, "agg_dist"])

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in quad_rows.schema)
    return quad_rows.mapInArrow(run, f"{kinds}, agg_dist long")


def _one(p: GroupQueryPlan, points: DataFrame | PlaneLayout, query: DataFrame, groups: list[Group] | DataFrame) -> DataFrame:
    k, d = p.k, p.direction
    layout = points if isinstance(points, PlaneLayout) else None
    flat = layout.points.drop("slab", "band") if layout else points
    if p.strategy == "scan":
        return merge_quadrants(_scan(flat, groups, k, d), k, d)
    if p.strategy == "scan_dealt":
        return merge_quadrants(scan_dealt(flat, query, k, d), k, d)
    if p.strategy == "scan_joins":
        x = frontier.with_groups(flat, query.select("query_id").distinct())
        if "own" in flat.columns:
            x = x.filter(F.col("own").isNull() | (F.col("own") != F.col("query_id"))).drop("own")
        return merge_quadrants(agg_dist(x, query, p.evaluator), k, d)
    if p.strategy == "tiles" and isinstance(groups, DataFrame):
        return merge_quadrants(tiles.found_dealt(layout, groups, k, d), k, d)
    if p.strategy == "tiles":
        return merge_quadrants(_scan(tiles.candidates(layout, groups, k, d), groups, k, d, by_group=True), k, d)
    if p.strategy == "skyband":
        # beyond the flat stretches a dominated point is truly worse, so the band holds the canonical answer
        band = frontier.band(frontier.quadrants(flat, query, d, narrow=True), k)
        return merge_quadrants(_scan(band, groups, k, d, by_group=True), k, d)
    if p.strategy == "cells":
        return merge_quadrants(cells.cell_topk(flat, query, groups, k, d), k, d)
    if p.strategy == "peel_grouped":
        own = tiles.candidates(layout, groups, k, d) if layout else flat
        return merge_quadrants(peel.quadrant_topk(own, query, groups, k, d).drop("quad"), k, d)
    if p.strategy == "peel_driver":
        return _peel_driver(flat, query, groups, k, d)
    # hull: a convex function is greatest at a vertex of the hull of all points; points equally far are looked up in their tiles
    root = layout.hulls.groupBy().agg(F.max("level").alias("l"))
    top = layout.hulls.crossJoin(root).filter("level = l and run_level = 0").select(F.inline("vertices"))  # root is one row
    best = merge_quadrants(_scan(top.select("point_id", "x", "y"), groups, 1, d), 1, d)
    return complete_ties(layout, groups, best.select("query_id", F.col("agg_dist").alias("tau")), 1, d)


def build(p: GroupQueryPlan, points: DataFrame | PlaneLayout, query: DataFrame) -> DataFrame:
    """query: checked and staged."""
    points = points if isinstance(points, PlaneLayout) else checked_points(points)
    load = groups_or_table if p.strategy in ("tiles", "peel_grouped") or p.counters else load_groups
    groups = [] if p.strategy in ("scan_dealt", "scan_joins") and not p.counters else load(query)
    if p.counters:
        own = tiles.candidates(points, groups, p.k, p.direction) if isinstance(points, PlaneLayout) else points
        return peel.quadrant_topk(own, query, groups, p.k, p.direction, counters=True)
    return _one(p, points, query, groups)


def _planned(points, query: DataFrame, k: int, direction: str, strategy: str, layout: str | None, evaluator: str, counters: bool):
    query = stage(merged(checked_query(query)), "query")
    if layout and not isinstance(points, PlaneLayout):
        points = build_plane(checked_points(points), None if layout == "tiles" else layout)
    p = plan(points, k, direction, strategy, evaluator, counters, query)
    if p.strategy == "tiles" and not isinstance(points, PlaneLayout):
        points = build_plane(checked_points(points))
        p = replace(p, layout="none")
    return p, points, query


def topk(points: DataFrame | PlaneLayout, query: DataFrame, k: int, direction: str = "nearest", strategy: str = "auto", layout: str | None = None, evaluator: str = "auto", counters: bool = False) -> DataFrame:
    """query_id, rank, point_id, x, y, agg_dist: the k best points of each group, min(k, points) rows.

    layout: build one first (``fast``, ``middle``, ``small``, ``dyadic_full``, or ``tiles`` for bounds
    alone). With counters the search's cost rows come back in place of the answer.
    """
    return build(*_planned(points, query, k, direction, strategy, layout, evaluator, counters))


def explain(points: DataFrame | PlaneLayout, query: DataFrame, k: int, direction: str = "nearest", strategy: str = "auto", layout: str | None = None, evaluator: str = "auto", counters: bool = False) -> str:
    """The chosen plan and Spark's plan for it."""
    p, points, query = _planned(points, query, k, direction, strategy, layout, evaluator, counters)
    df = build(p, points, query)
    return f"{p}\n{df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString('formatted'))}"
