"""Random inputs, with and without ties, against brute force; counters against their bounds."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from aggnear.functions import plane_geometry as G
from aggnear.functions import weights
from aggnear.functions.profile import Axis, Group
from aggnear.functions.subhulls import SubHulls
from aggnear.operators import cells, frontier, line, metrics, peel
from aggnear.operators.layout import build_plane, hull
from aggnear.plans import plane


def case(rng, span, n=None, m=None):
    n, m = n or int(rng.integers(1, 40)), m or int(rng.integers(1, 7))
    g = Group.of(1, rng.integers(0, span, m), rng.integers(0, span, m), rng.integers(1, 6, m))
    return g, rng.permutation(n), rng.integers(0, span, n), rng.integers(0, span, n)


def test_peel_against_definition_and_bounds():
    rng = np.random.default_rng(1)
    seen, again = {}, 0
    for trial in range(500):
        g, ids, x, y = case(rng, [6, 15, 600][trial % 3])
        direction, sign = ("nearest", 1) if trial % 2 else ("farthest", -1)
        quads = G.quad_of(x, y, *g.anchor)
        for quad in np.unique(quads):
            at = quads == quad
            k = int(rng.integers(1, len(ids) + 2))
            got, search = peel.quadrant_answer(g, int(quad), direction, k, ids[at], x[at], y[at])
            f = g(x[at], y[at]) * sign
            assert got.tolist() == np.lexsort((y[at], x[at], ids[at], f))[:k].tolist()  # the search's own answers, in order
            assert search.run is not None and len(search.rounds) >= min(k, len(f))
            again += search.count["reentered"]
            assert search.count["lambda"] <= search.rounds[-1][0] + k - 1 or len(got) < k
            assert all(cells_ <= (search.q.lines_u > 0).sum() + (search.q.lines_v > 0).sum() + 1 for cells_, _, _ in search.rounds)
            assert search.count["shards_peak"] <= k
            for c, n in search.q.cases.items():
                seen[c] = seen.get(c, 0) + n
    assert again > 0
    assert len(seen) == 8, seen  # every kind of update has come up


def test_peel_of_every_layout_and_its_looks():
    rng = np.random.default_rng(7)
    looked = {}
    for trial in range(150):
        g, ids, x, y = case(rng, [15, 600, 10_000][trial % 3], n=int(rng.integers(60, 400)))
        quads = G.quad_of(x, y, *g.anchor)
        for quad in np.unique(quads):
            at = quads == quad
            want = np.lexsort((y[at], x[at], ids[at], g(x[at], y[at])))[:20].tolist()
            for mode in ("dyadic_full", "fast", "middle", "small"):
                got, search = peel.quadrant_answer(g, int(quad), "nearest", 20, ids[at], x[at], y[at], mode)
                assert got.tolist() == want
                looked[mode] = looked.get(mode, 0) + search.count["runs"]
    assert looked["dyadic_full"] <= looked["fast"] < looked["small"] and looked["fast"] <= looked["middle"]


def test_search_tree_against_scan():
    rng = np.random.default_rng(8)
    for n in (1, 2, 7, 64, 333):
        v = rng.integers(0, 50, n)
        t, gone = peel.FirstBelow(v), np.zeros(n, bool)
        for _ in range(200):
            a, b, limit = int(rng.integers(0, n + 1)), int(rng.integers(0, n + 1)), int(rng.integers(0, 55))
            hit = np.flatnonzero((np.arange(n) >= a) & (np.arange(n) < b) & ~gone & (v < limit))
            before = t.steps
            assert t.first(a, b, limit) == (hit[0] if len(hit) else -1)
            assert t.steps - before <= 4 * n.bit_length() + 4  # lg n, with removals as without
            i = int(rng.integers(0, n))
            gone[i] = True
            t.remove(i)


def test_sub_hulls_keep_less_in_smaller_layouts():
    rng = np.random.default_rng(9)
    u, v = rng.integers(0, 10**6, 5000), np.sort(rng.integers(0, 10**6, 5000))
    names = [(int(i),) for i in rng.permutation(5000)]
    size = {m: SubHulls(u, v, 3 * u + 2 * v, names, m).size() for m in ("dyadic_full", "fast", "middle", "small")}
    assert size["dyadic_full"] > size["fast"] > size["middle"] > size["small"]


def test_too_large_a_cutoff_would_be_seen(monkeypatch):
    """Answers are the search's own: a peel that stops short gives fewer rows, nothing fills them up."""
    rng = np.random.default_rng(10)
    g, ids, x, y = case(rng, 600, n=80, m=5)
    quad = int(G.quad_of(x, y, *g.anchor)[0])
    at = G.quad_of(x, y, *g.anchor) == quad
    monkeypatch.setattr(peel.Quadrant, "take", lambda self, z: self.remove(z) or [])  # no cells but those of the first round
    got, search = peel.quadrant_answer(g, quad, "nearest", len(ids), ids[at], x[at], y[at])
    inside = sum(len(search.members[c]) for c in search.seen)
    assert len(got) == inside


def test_cells_machine_against_frontier():
    rng = np.random.default_rng(2)
    for trial in range(300):
        g, ids, x, y = case(rng, [5, 600][trial % 2])
        quads = G.quad_of(x, y, *g.anchor)
        quad = int(quads[0])
        at = quads == quad
        q = peel.of_group(g, quad, "nearest", ids[at], x[at], y[at], narrow=False).q
        q.first_cells()
        while q.live.any():
            live = np.flatnonzero(q.live)
            front = live[G.minimal(q.u[live], q.v[live])]
            want = {}
            for p in front:
                want.setdefault(q.cell(p), []).append(p)
            assert set(want) == set(q.cells)
            for c, ps in want.items():
                assert q.cells[c].entry == min(ps, key=lambda p: (q.u[p], q.v[p], q.ids[p]))
                assert q.cells[c].floor == min(ps, key=lambda p: (q.v[p], q.u[p], q.ids[p]))
            before = sum(q.probes.values())
            new = q.take(int(rng.choice(front)))
            assert sum(q.probes.values()) - before <= 2 * len(new) + 4


def test_band_and_minimal_and_hull():
    rng = np.random.default_rng(3)
    for trial in range(200):
        n, span = int(rng.integers(1, 30)), [4, 50][trial % 2]
        u, v = rng.integers(0, span, n), rng.integers(0, span, n)
        over = ((u[:, None] <= u) & (v[:, None] <= v) & ((u[:, None] < u) | (v[:, None] < v))).sum(axis=0)
        assert (G.minimal(u, v) == (over == 0)).all()
        for k in (1, 2, 5):
            assert (G.band(u, v, k) == (over < k)).all()
        at = hull(u, v, np.arange(n))
        for a, b in rng.integers(-5, 6, (20, 2)):
            assert (a * u[at] + b * v[at]).min() == (a * u + b * v).min()


def test_axis_function():
    rng = np.random.default_rng(4)
    for _ in range(100):
        c, w, x = rng.integers(-20, 20, 6), rng.integers(1, 5, 6), rng.integers(-30, 30, 25)
        assert (Axis.of(c, w)(x) == (w[:, None] * np.abs(c[:, None] - x)).sum(axis=0)).all()


@pytest.fixture(scope="module")
def tied(spark):
    rng = np.random.default_rng(5)
    p = [(int(i), int(rng.integers(0, 7)), int(rng.integers(0, 7)), int(rng.integers(1, 4))) for i in rng.permutation(150)]
    q = [(int(rng.integers(1, 4)), int(rng.integers(0, 7)), int(rng.integers(0, 7)), int(rng.integers(1, 4))) for _ in range(18)]
    return spark.createDataFrame(p, "point_id long, x long, y long, own long"), spark.createDataFrame(q, "query_id long, qx long, qy long, w long"), p, q


def brute(p, q, k, direction):
    out = []
    for g in sorted({r[0] for r in q}):
        mine = [r for r in q if r[0] == g]
        d = sorted(((1 if direction == "nearest" else -1) * sum(w * (abs(x - a) + abs(y - b)) for _, a, b, w in mine), i, x, y) for i, x, y, own in p if own != g)[:k]
        out += [(g, n + 1, i, x, y, abs(f)) for n, (f, i, x, y) in enumerate(d)]
    return out


@pytest.mark.parametrize("direction", ["nearest", "farthest"])
@pytest.mark.parametrize("strategy", ["scan", "scan_dealt", "scan_joins", "tiles", "skyband", "cells", "peel_grouped", "peel_driver"])
def test_strategies_on_ties(tied, direction, strategy):
    p, q, rp, rq = tied
    k = 3 if strategy == "peel_driver" else 9
    points = build_plane(p, slabs=3, bands=3) if strategy == "tiles" else p
    got = [tuple(r) for r in plane.topk(points, q, k, direction, strategy).orderBy("query_id", "rank").collect()]
    assert got == brute(rp, rq, k, direction)


def test_more_than_there_is_and_counters(tied):
    p, q, rp, rq = tied
    assert plane.topk(p, q, 10_000).count() == len(brute(rp, rq, 10_000, "nearest"))
    c = plane.topk(p, q, 5, counters=True)
    assert {"lambda", "pushes", "probe_COL_ENTRY", "cells", "heap_peak"} <= {r.measure for r in c.select("measure").distinct().collect()}
    assert metrics.rollup(c).count() > 0
    t = plane.topk(p, q, 5)
    assert metrics.out_of_order(t).count() == 0
    assert all(r.rows == r.same_rank == r.in_both and r.gap == 0 for r in metrics.exactness(t, t).collect())
    assert "GroupQueryPlan" in plane.explain(p, q, 5)


def test_line_with_ties(spark):
    rng = np.random.default_rng(6)
    for span in (4, 300):
        p = [(int(i), int(rng.integers(0, span))) for i in rng.permutation(60)]
        q = [(int(rng.integers(1, 5)), int(rng.integers(-2, span + 2)), int(rng.integers(1, 4))) for _ in range(14)]
        dp, dq = spark.createDataFrame(p, "point_id long, x long"), spark.createDataFrame(q, "query_id long, qx long, w long")
        layout = line.build_line(dp)
        for direction, s in (("nearest", 1), ("farthest", -1)):
            for k in (1, 7, 80):
                got = [(r.query_id, r.point_id, r.agg_dist) for r in line.topk(layout, dq, k, direction).orderBy("query_id", "rank").collect()]
                want = []
                for g in sorted({r[0] for r in q}):
                    d = sorted((s * sum(w * abs(x - a) for h, a, w in q if h == g), i) for i, x in p)[:k]
                    want += [(g, i, s * f) for f, i in d]
                assert got == want
        a, b = (weights.anchor(dq, how).orderBy("query_id").collect() for how in ("sort", "select"))
        assert a == b


def test_rectangles_and_layout_sizes(spark, tied):
    p, q, _, _ = tied
    sizes, truth = {}, None
    for mode in ("dyadic_full", "fast", "middle", "small"):
        layout = build_plane(p.drop("own"), mode, 4, 4)
        best, cost = cells.optimum(layout, cells.cell_rectangles(q))
        got = {(r.query_id, r.rect_id): r.agg_dist for r in best.collect()}
        truth = truth or got
        assert got == truth and cost.count() >= len(got)
        sizes[mode] = metrics.layout_size(layout).agg({"vertices": "sum"}).first()[0]
    assert sizes["fast"] >= sizes["middle"] >= sizes["small"]


def test_growth_exponent():
    assert abs(metrics.exponent([1, 2, 4, 8], [3, 6, 12, 24]) - 1) < 1e-9


def test_exposed_is_what_a_fresh_frontier_adds(tied):
    p, q, _, _ = tied
    quads = frontier.quadrants(p, q)
    old = frontier.minimal(quads)
    gone = old.filter("point_id % 2 = 0")
    keys = ["query_id", "quad", "point_id", "x", "y"]
    fresh = frontier.minimal(quads.join(gone.select(*keys), keys, "left_anti")).select(*keys)
    assert sorted(map(tuple, frontier.exposed(quads, gone).select(*keys).collect())) == sorted(map(tuple, fresh.exceptAll(old.select(*keys)).collect()))


def test_minimal_by_the_definition_of_dominance(tied):
    p, q, _, _ = tied
    quads = frontier.quadrants(p, q)
    over = quads.alias("a").join(quads.alias("b"), (F.col("a.query_id") == F.col("b.query_id")) & (F.col("a.quad") == F.col("b.quad")) & frontier.dominates("a", "b")).select("b.*").distinct()
    keys = ["query_id", "quad", "point_id", "x", "y"]
    want = quads.select(*keys).exceptAll(over.select(*keys))
    assert sorted(map(tuple, frontier.minimal(quads).select(*keys).collect())) == sorted(map(tuple, want.collect()))


def test_sorted_groups_and_their_order(spark):
    rng = np.random.default_rng(11)
    p = spark.createDataFrame([(int(i), int(rng.integers(0, 50))) for i in range(80)], "point_id long, x long")
    q = spark.createDataFrame([(int(rng.integers(1, 5)), int(rng.integers(0, 50)), int(rng.integers(1, 4))) for _ in range(30)], "query_id long, qx long, w long")
    groups = weights.sorted_groups(q)
    a, b = (sorted(map(tuple, line.topk(p, x, 7).collect())) for x in (q, groups))
    assert a == b
    bad = spark.createDataFrame([(1, [(3, 1), (2, 1)])], "query_id long, q array<struct<v:long,w:long>>")
    with pytest.raises(Exception, match="ascending"):
        line.topk(p, bad, 3).collect()


def test_nearest_of_one_against_ranks(spark):
    rng = np.random.default_rng(12)
    for span in (3, 40, 1000):
        p = spark.createDataFrame([(int(i), int(rng.integers(0, span))) for i in rng.permutation(70)], "point_id long, x long")
        q = spark.createDataFrame([(int(rng.integers(1, 9)), int(rng.integers(-5, span + 5)), 1) for _ in range(24)], "query_id long, qx long, w long")
        assert sorted(map(tuple, line.nearest(p, q).collect())) == sorted(map(tuple, line.topk(p, q, 1).collect()))


def test_extreme_vertices_by_halving():
    rng = np.random.default_rng(13)
    for n in (1, 2, 3, 5, 40, 400):
        x, y = rng.integers(0, 1000, n), rng.integers(0, 1000, n)
        at = hull(x, y, np.arange(n))
        ring = [{"point_id": int(i), "x": int(x[i]), "y": int(y[i])} for i in at]
        for a, b in [*rng.integers(-9, 10, (60, 2)).tolist(), (0, 1), (1, 0), (0, -1), (-1, 0), (0, 0)]:
            _, px, py, looked = cells._extreme(ring, a, b)
            assert a * px + b * py == (a * x + b * y).min()
            assert looked <= 4 * len(ring).bit_length() + 4


def test_growth_of_sweeps_and_costs(spark):
    """The counters of the peel grow as the bounds say, and its rivals cost more."""
    from aggnear import workloads as W

    d = "/root/testdata/sf0.001"
    g = {(r.parameter, r.measure): r.exponent for r in W.QUERIES["growth_exponents"](spark, d).collect()}
    assert g["k", "lambda"] < 1 and g["k", "pushes"] < 1.2 and g["n", "lambda"] < 0.6 and g["m", "lambda"] < 1.2
    c = {(r.method, r.k): r for r in W.QUERIES["repeel_costs"](spark, d).collect()}
    for k in (4, 16):
        assert c["peel", k].cells_searched < c["fresh", k].cells_searched and c["peel", k].cells_searched <= c["kept cells", k].cells_searched
        assert c["peel", k].optima < c["kept cells", k].optima
    e = {(r.query_id, r.evaluator): r for r in W.QUERIES["evaluations_line"](spark, d).collect()}
    assert all(r.candidates <= 30 for r in e.values())
    x = {(r.measure, r.k): r.value for r in W.QUERIES["deletion_costs"](spark, d).collect()}
    assert x["rebuilt_points", 16] >= x["rebuilt_points", 1] > 0


def test_layouts_store_less_for_more_looks(spark):
    from aggnear import workloads as W

    r = {x["mode"]: x for x in W.QUERIES["layout_tradeoff"](spark, "/root/testdata/sf0.01").collect()}
    modes = ("dyadic_full", "fast", "middle", "small")
    stored = [r[m].stored for m in modes]
    assert stored == sorted(stored, reverse=True) and len(set(stored)) == 4
    assert len({r[m].bytes for m in modes}) == 4 and r["small"].runs > r["dyadic_full"].runs
    assert r["dyadic_full"].runs <= r["fast"].runs <= r["middle"].runs <= r["small"].runs


def test_tiles_read_less_than_the_scan(spark):
    from aggnear import workloads as W

    r = {(x.strategy, x.measure): x.value for x in W.QUERIES["work_of_strategies"](spark, "/root/testdata/sf0.01").collect()}
    assert r["tiles", "rows_read"] < r["scan", "rows_read"]


def test_least_ids_of_ranges(spark, monkeypatch):
    """Ranges of any length look at a few entries, not at the points inside, and find the least ids exactly."""
    from aggnear.operators import least

    monkeypatch.setattr(least, "FAN", 4)
    monkeypatch.setattr(least, "BLOCK", 2)
    r = np.random.default_rng(5)
    for n, k in ((1, 1), (37, 2), (700, 5)):
        ids, x = r.integers(0, 2 * n, n), np.sort(r.integers(0, 50, n))
        points = spark.createDataFrame([(int(i), int(v), p) for p, (i, v) in enumerate(zip(ids, x))], "point_id long, x long, pos long")
        ends = [sorted(map(int, r.integers(0, n + 1, 2))) for _ in range(150)] + [[0, n], [0, 0], [n - 1, n]]
        ranges = spark.createDataFrame([(q, *e) for q, e in enumerate(ends)], "query_id long, lo long, hi long")
        got = {}
        for row in least.least_ids(points, n, ranges, k).collect():
            got.setdefault(row.query_id, []).append((row.point_id, row.x))
        for q, (lo, hi) in enumerate(ends):
            want = sorted((int(ids[p]), int(x[p])) for p in range(lo, hi))[:k]
            assert sorted(got.get(q, []))[:k] == want
            assert len(got.get(q, [])) <= k * 4 * 6


def test_repeated_query_points_count_once_against_the_limit(spark, monkeypatch):
    from aggnear.functions import profile

    monkeypatch.setattr(profile, "BLOCK_ROWS", 20)
    rows = [(g, 10 * i, 7 * i, 1 + g) for g in (1, 2) for i in range(8)]
    q = spark.createDataFrame(rows * 5, "query_id long, qx long, qy long, w long")
    p = spark.createDataFrame([(i, (37 * i) % 101, (53 * i) % 89) for i in range(300)], "point_id long, x long, y long")
    got = [tuple(r) for r in plane.topk(p, q, 3, strategy="tiles").collect()]
    want = []
    for g in (1, 2):
        d = sorted((sum(5 * w * (abs(r.x - x) + abs(r.y - y)) for h, x, y, w in rows if h == g), r.point_id, r.x, r.y) for r in p.collect())[:3]
        want += [(g, n + 1, i, x, y, f) for n, (f, i, x, y) in enumerate(d)]
    assert sorted(got) == want


@pytest.mark.parametrize("direction", ["nearest", "farthest"])
def test_cell_optimum_makes_no_empty_cells(spark, direction):
    """The same rows as over all rectangles of the grid, and costs of occupied cells alone; cells with and without whole tiles."""
    r = np.random.default_rng(8)
    p = spark.createDataFrame([(i, *map(int, r.integers(0, 400, 2))) for i in range(600)], "point_id long, x long, y long")
    rows = [(1, *map(int, r.integers(0, 400, 2)), int(r.integers(1, 4))) for _ in range(12)] + [(2, 390, 395, 1), (3, 200, 200, 2), (3, 380, 10, 1)]
    q = spark.createDataFrame(rows, "query_id long, qx long, qy long, w long")
    groups = [Group.of(i, *zip(*[t[1:] for t in rows if t[0] == i])) for i in (1, 2, 3)]
    layout = build_plane(p, "fast", slabs=8, bands=16)
    want, cost = cells.optimum(layout, cells.cell_rectangles(q), direction)
    got, mine = cells.cell_optimum(layout, groups, direction)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    used = {(c.query_id, c.rect_id): c for c in cost.collect() if c.runs or c.border_points}
    for c in mine.collect():
        assert tuple(c) == tuple(used.pop((c.query_id, c.rect_id)))
    assert all(c.runs and not c.vertices for c in used.values())


@pytest.mark.parametrize("direction", ["nearest", "farthest"])
def test_dealt_scan_asks_few_tiles(spark, monkeypatch, direction):
    """Groups go to the tiles that can hold an answer, not to all points; own points, ties, heavy tiles and large k stay exact."""
    from aggnear.operators import local

    monkeypatch.setattr(local, "TILE", 16)
    monkeypatch.setattr(local, "CHUNK", 50)
    r = np.random.default_rng(9)
    p = [(i, *map(int, r.integers(0, 60, 2)), int(r.integers(1, 6))) for i in range(900)] + [(900 + i, 30, 30, 1) for i in range(150)]
    rows = [(g, *map(int, r.integers(0, 60, 2)), int(r.integers(1, 4))) for g in range(1, 9) for _ in range(3)]
    pts, q = spark.createDataFrame(p, "point_id long, x long, y long, own long"), spark.createDataFrame(rows, "query_id long, qx long, qy long, w long")
    sign = 1 if direction == "nearest" else -1
    for k in (3, 400):
        want = []
        for g in range(1, 9):
            d = sorted((sign * sum(w * (abs(x - qx) + abs(y - qy)) for h, qx, qy, w in rows if h == g), i, x, y) for i, x, y, own in p if own != g)[:k]
            want += [(g, n + 1, i, x, y, sign * f) for n, (f, i, x, y) in enumerate(d)]
        assert sorted(map(tuple, plane.topk(pts, q, k, direction, strategy="scan_dealt").collect())) == want
    _, tiles = local._tiles(pts, len(p))
    asked = list(local._wanted(tiles, 3, sign)([spark.createDataFrame(sorted(rows), "query_id long, qx long, qy long, w long").selectExpr("*", "0L as away").toArrow().combine_chunks().to_batches()[0]]))
    assert sum(b.num_rows for b in asked) < len(rows) * tiles["parts"].sum() / 2


def test_grid_walk_makes_no_grid(spark, monkeypatch):
    from aggnear.operators import baselines

    monkeypatch.setattr(cells, "grid", lambda query: pytest.fail("all cells were made"))
    p = spark.createDataFrame([(i, (37 * i) % 101, (53 * i) % 89) for i in range(200)], "point_id long, x long, y long")
    rows = [(1, 20, 30, 1), (1, 70, 10, 2), (1, 50, 60, 1)]
    g = Group.of(1, *zip(*[t[1:] for t in rows]))
    got = baselines.grid_walk(p, spark.createDataFrame(rows, "query_id long, qx long, qy long, w long"), [g]).collect()
    want = min((sum(w * (abs(r.x - x) + abs(r.y - y)) for _, x, y, w in rows), r.point_id) for r in p.collect())
    assert [(r.agg_dist, r.point_id) for r in got] == [want]
