"""Registry of the group-proximity workloads: Spark query and DuckDB text under one name."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import weights
from .functions.profile import groups_or_table, load_groups, merged
from .model import checked_points, checked_query
from .operators import baselines, cells, frontier, invariants, line, metrics, peel, probe
from .operators.layout import build_plane
from .plans import plane, sqlsurface
from .sources import adapters as A
from .sources import oracle as O
from .staging import stage
from .streaming import stream

QUERIES: dict = {}
ORACLES: dict = {}


def register(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


@register("line_nn_customer", O.topk("customer", "supplier", 10, plane=False))
def line_nn_customer(spark, d):
    return line.topk(A.customer_line(spark, d), A.supplier_by_nation(spark, d), 10)


@register("line_fn_customer", O.topk("customer", "supplier", 10, "farthest", plane=False))
def line_fn_customer(spark, d):
    return line.topk(A.customer_line(spark, d), A.supplier_by_nation(spark, d), 10, "farthest")


@register("line_nn_k1", O.topk("customer", "supplier", 1, plane=False))
def line_nn_k1(spark, d):
    return line.nearest(A.customer_line(spark, d), A.supplier_by_nation(spark, d))


@register("line_nn_sorted", O.topk("customer", "supplier", 10, plane=False))
def line_nn_sorted(spark, d):
    """Groups that come as sorted arrays: no sort, no shuffle of the groups."""
    return line.topk(A.customer_line(spark, d), weights.sorted_groups(A.supplier_by_nation(spark, d)), 10)


@register("line_fn_k1", O.topk("customer", "supplier", 1, "farthest", plane=False))
def line_fn_k1(spark, d):
    return line.farthest_ends(A.customer_line(spark, d), A.supplier_by_nation(spark, d))


@register("line_nn_unweighted", O.topk("orders_price", "orders_price", 5, plane=False))
def line_nn_unweighted(spark, d):
    p = A.points(A.table(spark, d, "orders"), "o_orderkey", A.cents("o_totalprice"))
    q = A.query(A.table(spark, d, "orders"), "o_custkey", A.cents("o_totalprice"), w=A.priority())
    return line.topk(p, weights.unweighted(q), 5)


@register("line_nn_dates", O.topk("orders_day", "orders_day", 10, plane=False))
def line_nn_dates(spark, d):
    p = A.points(A.table(spark, d, "orders"), "o_orderkey", A.days("o_orderdate"))
    return line.topk(p, A.query(A.table(spark, d, "orders"), "o_custkey", A.days("o_orderdate"), w=A.priority()), 10)


@register("line_nn_bigk", O.topk("supplier", "segment", 1000, plane=False))
def line_nn_bigk(spark, d):
    p = A.points(A.table(spark, d, "supplier"), "s_suppkey", A.cents("s_acctbal"))
    return line.topk(p, A.query(A.table(spark, d, "customer"), F.ascii("c_mktsegment"), A.cents("c_acctbal")), 1000)


def _evaluator(name: str):
    def run(spark, d):
        return line.topk(A.customer_line(spark, d), A.supplier_by_nation(spark, d), 3, evaluator=name)

    return run


for _e in ("direct", "prefix", "merge"):
    register(f"line_evaluator_{_e}", O.topk("customer", "supplier", 3, plane=False))(_evaluator(_e))

_ANCHOR = f"WITH {O.anchors('supplier')} SELECT query_id, min(v) FILTER (2 * cw >= wt) AS ax, min(v) FILTER (2 * cw > wt) AS ax_hi, max(wt)::BIGINT AS w_total FROM c GROUP BY query_id"


@register("anchor_by_nation", _ANCHOR)
def anchor_by_nation(spark, d):
    return weights.anchor(A.supplier_by_nation(spark, d))


@register("anchor_by_selection", _ANCHOR)
def anchor_by_selection(spark, d):
    return weights.anchor(A.supplier_by_nation(spark, d), how="select")


@register(
    "profile_by_nation",
    f"""WITH {O.anchors('supplier')} SELECT query_id, v, cw::BIGINT AS cw, (sum(w * v) OVER (PARTITION BY query_id ORDER BY v))::BIGINT AS cwv,
(wt - cw + w)::BIGINT AS sw, (sum(w * v) OVER (PARTITION BY query_id ORDER BY v DESC))::BIGINT AS swv FROM c""",
)
def profile_by_nation(spark, d):
    return weights.profile_rows(A.supplier_by_nation(spark, d))


# Plane -------------------------------------------------------------------------------------------

_PLANE = {
    "embeddings": (A.embeddings_plane, A.embeddings_query, 10),
    "part": (A.part_plane, A.part_query, 10),
    "part_sales": (A.part_plane, A.part_sales_query, 10),
    "lineitem": (A.lineitem_plane, A.dearest_order_query, 10),
    "lineitem_brands": (A.lineitem_plane, A.part_by_brand, 10),
    "orders": (A.orders_plane, A.orders_query, 5),
    "events": (A.events_plane, A.events_query, 10),
    "documents": (A.documents_plane, A.documents_query, 10),
    "pages": (A.pages_plane, A.pages_query, 5),
    "conversations": (A.conversations_plane, A.conversations_query, 5),
    "benchmark": (A.documents_plane, A.benchmark_query, 10),
}
_POINTS_OF = {"part_sales": "part", "benchmark": "documents", "lineitem_brands": "lineitem"}
_QUERY_OF = {"lineitem_brands": "brands"}


def _plane(name: str, direction: str, **options):
    points, query, k = _PLANE[name]

    def run(spark, d):
        return plane.topk(points(spark, d), query(spark, d), k, direction, **options)

    return run


for _n, (_p, _q, _k) in _PLANE.items():
    _sql = O.topk(_POINTS_OF.get(_n, _n), _QUERY_OF.get(_n, _n), _k)
    register(f"plane_nn_{_n}", _sql)(_plane(_n, "nearest"))
    if _n in ("embeddings", "part", "lineitem"):
        register(f"plane_fn_{_n}", O.topk(_POINTS_OF.get(_n, _n), _n, _k, "farthest"))(_plane(_n, "farthest"))

for _s in ("scan_dealt", "scan_joins", "tiles", "skyband", "cells", "peel_grouped"):
    register(f"strategy_{_s}_nn", O.topk("part", "part", 10))(_plane("part", "nearest", strategy=_s))
    register(f"strategy_{_s}_fn", O.topk("part", "part", 10, "farthest"))(_plane("part", "farthest", strategy=_s))
register("strategy_tiles_lineitem", O.topk("lineitem", "brands", 10))(_plane("lineitem_brands", "nearest", strategy="tiles"))
register("strategy_peel_tiles_lineitem", O.topk("lineitem", "brands", 10))(_plane("lineitem_brands", "nearest", strategy="peel_grouped", layout="tiles"))


@register("strategy_peel_driver", O.topk("embeddings", "embeddings", 4))
def strategy_peel_driver(spark, d):
    return plane.topk(A.embeddings_plane(spark, d), A.embeddings_query(spark, d), 4, strategy="peel_driver")


@register("strategy_hull_fn", O.topk("embeddings_all", "embeddings", 1, "farthest"))
def strategy_hull_fn(spark, d):
    return plane.topk(A.embeddings_plane(spark, d).drop("own"), A.embeddings_query(spark, d), 1, "farthest", strategy="hull", layout="small")


def _groups(query):
    return load_groups(checked_query(query))


def _embeddings(spark, d):
    q = checked_query(A.embeddings_query(spark, d))
    return A.embeddings_plane(spark, d), q, _groups(q)


@register("quadrant_nn_embeddings", f"{O.quads('embeddings', 'embeddings')}, r AS (SELECT *, row_number() OVER (PARTITION BY query_id, quad ORDER BY agg_dist, point_id, x, y) AS n FROM z) SELECT query_id, quad, point_id, x, y, agg_dist FROM r WHERE n <= 10")
def quadrant_nn_embeddings(spark, d):
    p, q, g = _embeddings(spark, d)
    return peel.quadrant_topk(p, q, g, 10).withColumn("quad", F.col("quad").cast("long"))


def _frontier(points, query, direction):
    def run(spark, d):
        f = frontier.minimal(frontier.quadrants(points(spark, d), query(spark, d), direction))
        return f.select("query_id", F.col("quad").cast("long").alias("quad"), "point_id", "x", "y")

    return run


register("frontier_embeddings", O.frontier("embeddings", "embeddings"))(_frontier(A.embeddings_plane, A.embeddings_query, "nearest"))
register("frontier_part", O.frontier("part", "part"))(_frontier(A.part_plane, A.part_query, "nearest"))
register("frontier_max_embeddings", O.frontier("embeddings", "embeddings", "farthest"))(_frontier(A.embeddings_plane, A.embeddings_query, "farthest"))
register("frontier_max_part", O.frontier("part", "part", "farthest"))(_frontier(A.part_plane, A.part_query, "farthest"))


@register("frontier_exposed_embeddings", O.exposed("embeddings", "embeddings"))
def frontier_exposed_embeddings(spark, d):
    quads = frontier.quadrants(A.embeddings_plane(spark, d), A.embeddings_query(spark, d))
    gone = frontier.minimal(quads).filter("point_id % 2 = 0")
    return frontier.exposed(quads, gone).select("query_id", F.col("quad").cast("long").alias("quad"), "point_id", "x", "y")


@register("frontier_cells_embeddings", O.frontier_cells("embeddings", "embeddings"))
def frontier_cells_embeddings(spark, d):
    return cells.frontier_cells(*_embeddings(spark, d))


@register("first_cells_by_probes", O.frontier_cells("embeddings", "embeddings"))
def first_cells_by_probes(spark, d):
    """The same cells from the column machine of probes instead of the frontier."""
    p, q, g = _embeddings(spark, d)
    return peel.first_cells(p, q, g)


@register("cell_coefficients", O.coefficients("embeddings"))
def cell_coefficients(spark, d):
    return cells.coefficients(checked_query(A.embeddings_query(spark, d)))


def _optimum(direction, mode):
    def run(spark, d):
        p, q, g = _embeddings(spark, d)
        layout = build_plane(checked_points(p.drop("own")), mode)
        ny = q.groupBy("query_id").agg((F.countDistinct("qy") + 1).alias("ny"))
        best, _ = cells.cell_optimum(layout, g, direction)
        best = best.join(ny, "query_id")
        return best.select("query_id", F.expr("rect_id div ny").alias("ci"), (F.col("rect_id") % F.col("ny")).alias("cj"), "point_id", "agg_dist")

    return run


for _m in ("fast", "middle", "small", "dyadic_full"):
    register(f"cell_optimum_nn_{_m}", O.cell_optimum("embeddings_all", "embeddings"))(_optimum("nearest", _m))
register("cell_optimum_fn_fast", O.cell_optimum("embeddings_all", "embeddings", "farthest"))(_optimum("farthest", "fast"))

_SEGS = [(1, "v", 1, 85000, 140000, 1000), (2, "v", -1, None, 120000, 3000), (3, "h", 1, 1000, 2500, 95000), (4, "h", -1, 2000, None, 150000), (5, "v", 1, 500000, 600000, 0)]


def _drag(removed: bool, tiled: bool = False):
    def run(spark, d):
        p = A.part_plane(spark, d).drop("own")
        gone = p.filter("point_id % 3 = 0").select("point_id") if removed else None
        return probe.drag(build_plane(checked_points(p)) if tiled else p, spark.createDataFrame(_SEGS, probe.SEGMENT), gone)

    return run


register("drag_four_ways", O.drag("part", _SEGS))(_drag(False))
register("drag_with_removed", O.drag("part", _SEGS, "point_id % 3 <> 0"))(_drag(True))
register("drag_tiled", O.drag("part", _SEGS))(_drag(False, True))


@register("baseline_all_cells", O.topk("embeddings_all", "embeddings", 1))
def baseline_all_cells(spark, d):
    p, _, g = _embeddings(spark, d)
    return baselines.all_cells(build_plane(checked_points(p.drop("own")), "dyadic_full"), g)[0]


@register("baseline_full_frontier", O.topk("embeddings", "embeddings", 1))
def baseline_full_frontier(spark, d):
    return baselines.full_frontier(*_embeddings(spark, d))


@register("baseline_full_frontier_fn", O.topk("embeddings", "embeddings", 1, "farthest"))
def baseline_full_frontier_fn(spark, d):
    return baselines.full_frontier(*_embeddings(spark, d), "farthest")


@register("baseline_grid_walk", O.topk("embeddings", "embeddings", 1))
def baseline_grid_walk(spark, d):
    return baselines.grid_walk(*_embeddings(spark, d))


@register("baseline_repeel", O.topk("embeddings", "embeddings", 5))
def baseline_repeel(spark, d):
    return baselines.repeel(*_embeddings(spark, d), 5)[0]


@register("baseline_repeel_cells", O.topk("embeddings", "embeddings", 5, "farthest"))
def baseline_repeel_cells(spark, d):
    return baselines.repeel(*_embeddings(spark, d), 5, "farthest", "cells")[0]


@register("baseline_rebuild_hulls")
def baseline_rebuild_hulls(spark, d):
    layout = build_plane(checked_points(A.part_plane(spark, d)), "small")
    return baselines.rebuild_hulls(layout, layout.points.filter("point_id < 20").select("point_id")).select("slab", "band", "n_rebuilt", F.size("vertices").alias("n_vertices"))


_NONE = "SELECT 1::BIGINT AS query_id WHERE false"


@register("invariant_monotone_line", _NONE)
def invariant_monotone_line(spark, d):
    return invariants.monotone_line(A.customer_line(spark, d), A.supplier_by_nation(spark, d)).select("query_id")


@register("invariant_monotone_plane", _NONE)
def invariant_monotone_plane(spark, d):
    return invariants.monotone_plane(A.embeddings_plane(spark, d), checked_query(A.embeddings_query(spark, d))).select("query_id")


@register("counters_peel")
def counters_peel(spark, d):
    p, q, g = _embeddings(spark, d)
    out = None
    for k in (1, 2, 4, 8, 16, 32, 64):
        x = peel.quadrant_topk(p, q, g, k, counters=True).withColumn("k", F.lit(k))
        out = x if out is None else out.unionByName(x)
    return out


@register("counters_rollup")
def counters_rollup(spark, d):
    p, q, g = _embeddings(spark, d)
    return metrics.rollup(peel.quadrant_topk(p, q, g, 10, counters=True))


@register("layout_tradeoff")
def layout_tradeoff(spark, d):
    """What each layout stores and takes to build against what the optima of all cells of an order's grid look at."""
    p, q = checked_points(A.lineitem_plane(spark, d)), checked_query(A.dearest_order_query(spark, d))
    out = []
    for mode in ("dyadic_full", "fast", "middle", "small"):
        layout = build_plane(p, mode)
        _, cost = cells.optimum(layout, cells.cell_rectangles(q))
        c = cost.agg(F.sum("runs").alias("runs"), F.sum("vertices").alias("looked"), F.sum("border_points").alias("border")).first()
        stored = metrics.layout_size(layout).agg(F.sum("hulls").alias("hulls"), F.sum("vertices").alias("vertices")).first()
        out.append((mode, stored.hulls, stored.vertices, metrics.layout_bytes(layout), float(sum(layout.seconds.values())), c.runs or 0, c.looked or 0, c.border or 0))
    return spark.createDataFrame(out, "mode string, hulls long, stored long, bytes long, build_seconds double, runs long, looked long, border_points long")


@register("build_and_query_steps")
def build_and_query_steps(spark, d):
    """Seconds of each step of the builds and of a search."""
    p, q, g = _embeddings(spark, d)
    out = [(f"build {mode}", step, float(t)) for mode in ("dyadic_full", "fast", "middle", "small") for step, t in build_plane(checked_points(p.drop("own")), mode).seconds.items()]
    out += [("query", step, float(t)) for step, t in metrics.query_steps(p, q, g, 10).items()]
    return spark.createDataFrame(out, "what string, step string, seconds double")


@register("frontier_sizes", f"WITH a AS ({O.frontier('embeddings', 'embeddings')}) SELECT query_id, quad, count(*) AS vertices FROM a GROUP BY ALL")
def frontier_sizes(spark, d):
    return metrics.frontier_size(A.embeddings_plane(spark, d), A.embeddings_query(spark, d)).withColumn("quad", F.col("quad").cast("long"))


@register("evaluations_line")
def evaluations_line(spark, d):
    """Candidates that the line search merges (at most 2k beside the flat stretch) and what each evaluator does for them."""
    q = checked_query(A.supplier_by_nation(spark, d))
    layout = line.build_line(checked_points(A.customer_line(spark, d)))
    found = stage(line.sides(layout, line.locate(layout, weights.anchor(q)), 10, "nearest"), "candidates")
    out = None
    for e in ("direct", "prefix", "merge"):
        x = metrics.evaluated(found, q, e)
        out = x if out is None else out.unionByName(x)
    return out


@register("tiles_read")
def tiles_read(spark, d):
    q = groups_or_table(stage(merged(checked_query(A.part_by_brand(spark, d))), "query"))
    return metrics.tiles_read(build_plane(checked_points(A.lineitem_plane(spark, d)), slabs=16, bands=16), q, 10)


@register("work_of_strategies")
def work_of_strategies(spark, d):
    """Rows read and shuffled by a scan and by tile pruning, as Spark counts them."""
    p, q = checked_points(A.lineitem_plane(spark, d)), A.dearest_order_query(spark, d)
    layout = build_plane(p, slabs=16, bands=16)
    out = [(name, m, int(v)) for name, x in (("scan", p), ("tiles", layout)) for m, v in metrics.work_of(plane.topk(x, q, 10, strategy=name)).items()]
    return spark.createDataFrame(out, "strategy string, measure string, value long")


@register("deletion_costs")
def deletion_costs(spark, d):
    """Taking answers off: points that true deletions read and hull again, against the stretches that the peel cuts cells into."""
    p, q, g = _embeddings(spark, d)
    out = None
    for k in (1, 4, 16):
        answers = stage(plane.topk(p, q, k, strategy="peel_grouped"), "answers")
        layout = build_plane(checked_points(p.drop("own")), "small")
        again = baselines.rebuild_hulls(layout, answers.select("point_id").distinct()).agg(F.sum("n_rebuilt").alias("value")).select(F.lit("rebuilt_points").alias("measure"), "value")
        shards = peel.quadrant_topk(p, q, g, k, counters=True).filter("measure in ('shard_optima', 'cell_optima', 'vertices', 'probe_steps')").groupBy("measure").agg(F.sum("value").alias("value"))
        x = again.unionByName(shards).withColumn("k", F.lit(k))
        out = x if out is None else out.unionByName(x)
    return out


@register("repeel_costs")
def repeel_costs(spark, d):
    """Cells searched and optima taken by fresh rounds, by kept cells, and by the peel, for the same answers."""
    p, q, g = _embeddings(spark, d)
    out = None
    for k in (1, 4, 16):
        for name, reuse in (("fresh", None), ("kept cells", "cells")):
            x = baselines.repeel(p, q, g, k, reuse=reuse)[1].agg(F.sum("cells_searched").alias("cells_searched"), F.sum("optima").alias("optima"))
            x = x.select(F.lit(name).alias("method"), F.lit(k).alias("k"), "cells_searched", "optima")
            out = x if out is None else out.unionByName(x)
        c = peel.quadrant_topk(p, q, g, k, counters=True)
        total = lambda *m: F.sum(F.when(F.col("measure").isin(*m), F.col("value")).otherwise(0))
        out = out.unionByName(c.agg(total("lambda").alias("cells_searched"), total("cell_optima", "shard_optima").alias("optima")).select(F.lit("peel").alias("method"), F.lit(k).alias("k"), "cells_searched", "optima"))
    return out


@register("exactness_peel", f"WITH a AS ({O.topk('part', 'part', 10)}) SELECT query_id, count(*) AS rows, count(*)::BIGINT AS same_rank, 0::BIGINT AS gap, count(*) AS in_both FROM a GROUP BY query_id")
def exactness_peel(spark, d):
    p, q = A.part_plane(spark, d), A.part_query(spark, d)
    return metrics.exactness(stage(plane.topk(p, q, 10, strategy="peel_grouped"), "answer"), stage(plane.topk(p, q, 10), "truth"))


#: What a sweep varies: eighths of the groups' rows or of the points (each holds the ones before, the last is all), or k.
SWEEPS = {"m": (1, 2, 4, 8), "k": (1, 4, 16, 64), "n": (1, 2, 4, 8)}


def _sweep(what: str):
    """How the peel's counters move with one parameter: (parameter, measure, total)."""

    def run(spark, d):
        out = None
        e = A.embeddings_plane(spark, d)
        for v in SWEEPS[what]:
            q = checked_query(A.embeddings_query(spark, d, eighths=v if what == "m" else 8))
            p = e.filter(F.pmod(F.xxhash64("point_id"), F.lit(8)) < v) if what == "n" else e
            c = peel.quadrant_topk(p, q, _groups(q), v if what == "k" else 8, counters=True)
            x = c.groupBy("measure").agg(F.sum("value").alias("total")).withColumn("parameter", F.lit(v))
            out = x if out is None else out.unionByName(x)
        return out

    return run


for _w in SWEEPS:
    register(f"sweep_{_w}")(_sweep(_w))


@register("growth_exponents")
def growth_exponents(spark, d):
    """Exponent of every counter in n, m and k over the sweeps."""
    out = None
    for w in SWEEPS:
        x = metrics.growth(stage(_sweep(w)(spark, d), "sweep")).withColumn("parameter", F.lit(w))
        out = x if out is None else out.unionByName(x)
    return out


# SQL and streams ---------------------------------------------------------------------------------


@register("sql_topk", O.topk("embeddings_all", "embeddings", 5))
def sql_topk(spark, d):
    sqlsurface.install(spark, A.embeddings_plane(spark, d).drop("own"), A.embeddings_query(spark, d))
    return sqlsurface.topk_sql(spark, 5)


@register("sql_topk_table_function", O.topk("part", "part", 5))
def sql_topk_table_function(spark, d):
    sqlsurface.install(spark)
    q = A.part_query(spark, d)
    p = frontier.with_groups(A.part_plane(spark, d), q.select("query_id").distinct()).filter("own <> query_id")
    rows = p.select("query_id", F.lit("p").alias("kind"), "point_id", "x", "y", F.lit(0).cast("long").alias("w"))
    rows = rows.unionByName(q.select("query_id", F.lit("q").alias("kind"), F.lit(0).cast("long").alias("point_id"), F.col("qx").alias("x"), F.col("qy").alias("y"), "w"))
    rows.createOrReplaceTempView("topk_rows")
    return spark.sql("SELECT * FROM topk_group(TABLE(topk_rows) PARTITION BY (query_id), 5)")


_WINDOWED = f"""WITH q0 AS ({O.QUERIES['benchmark']}), e AS (SELECT event_id::BIGINT AS point_id, ts, {O._TS} AS x, {O.c('value')} AS y FROM events),
f AS (SELECT q.query_id, e.point_id, e.x, e.y, time_bucket(INTERVAL 1 DAY, e.ts, TIMESTAMP '1970-01-01') AS start, sum(q.w * (abs(e.x - q.qx) + abs(e.y - q.qy)))::BIGINT AS agg_dist FROM e, q0 q GROUP BY ALL),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id, start ORDER BY agg_dist, point_id, x, y) AS rank FROM f)
SELECT epoch(start)::BIGINT AS start, query_id, rank, point_id, x, y, agg_dist FROM r WHERE rank <= 3"""


@register("stream_windowed_topk", _WINDOWED)
def stream_windowed_topk(spark, d):
    """The windowed search on the events table, in its batch form (tests run it as a stream)."""
    e = A.table(spark, d, "events")
    p = e.select(F.col("event_id").alias("point_id"), F.col("ts").cast("timestamp").alias("ts"), F.unix_seconds(F.col("ts").cast("timestamp")).alias("x"), A.cents("value").alias("y"))
    x = stream.windowed_topk(p, A.benchmark_query(spark, d), 3)
    return x.select(F.unix_seconds("start").alias("start"), "query_id", "rank", "point_id", "x", "y", "agg_dist")
