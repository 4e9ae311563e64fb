"""Layer-by-layer search of one quadrant in a worker's memory, with its cost counters.

Works in the quadrant's own coordinates (small is searched first), so nearest and farthest, and all
four quadrants, are one code. The state of a round is the ordered list of cells that hold frontier
vertices, each with its leftmost vertex (entry), lowest vertex (floor) and the probes that found
them. Taking a point off repairs the list from the probes that had produced it: three routines do
that, ``_probe``, ``_climb`` (upwards in a column to a given cell) and ``_towards`` (rightwards from
a hit to a given cell). Probes and removals go through search trees, a cell's best point through the
hulls of stretches of its points. Cells once found stay with their candidates for the rest of the query, so a
cell that leaves the frontier and comes back is never searched twice; the points answered in a cell
cut it into shards.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np
import pandas as pd

from ..functions import plane_geometry as G
from ..functions.profile import Group
from ..functions.subhulls import SubHulls
from ..model import sign_of

COL_ENTRY, COL_FLOOR, ROW_ENTRY, ROW_FLOOR = "COL_ENTRY", "COL_FLOOR", "ROW_ENTRY", "ROW_FLOOR"
_INF = np.iinfo(np.int64).max


@dataclass
class Cell:
    entry: int = -1
    entry_by: tuple = ()
    floor: int = -1
    floor_by: tuple = ()


class FirstBelow:
    """A minimum tree over values in a fixed order: the first place in a range with a value below a limit, values can go.

    Two of these are the dynamic segment-dragging structure: a query or a removal costs O(lg n).
    """

    def __init__(self, values: np.ndarray):
        self.size = 1 << max(0, (len(values) - 1).bit_length())
        self.low = np.full(2 * self.size, _INF, np.int64)
        self.low[self.size : self.size + len(values)] = values
        at = self.size
        while at > 1:
            self.low[at // 2 : at] = np.minimum(self.low[at : 2 * at : 2], self.low[at + 1 : 2 * at : 2])
            at //= 2
        self.low = self.low.tolist()
        self.steps = 0

    def remove(self, i: int) -> None:
        low, i = self.low, i + self.size
        low[i] = _INF
        while i > 1:
            i //= 2
            low[i] = min(low[2 * i], low[2 * i + 1])

    def first(self, a: int, b: int, limit: int) -> int:
        """Least i in [a, b) with value < limit, -1 for none."""
        low, i, n = self.low, a + self.size, self.size
        if a >= b:
            return -1
        while True:  # to the right end of ever larger blocks until one holds such a value
            self.steps += 1
            if low[i] < limit:
                break
            while i & 1:
                i //= 2
            if i == 0:
                return -1
            i += 1
        while i < n:
            self.steps += 1
            i *= 2
            i += low[i] >= limit
        return i - n if i - n < b else -1


@dataclass
class Quadrant:
    """Points of one quadrant, those taken off gone from its search trees, and the grid lines."""

    u: np.ndarray
    v: np.ndarray
    ids: np.ndarray
    lines_u: np.ndarray
    lines_v: np.ndarray
    live: np.ndarray = None
    cells: dict = field(default_factory=dict)
    probes: dict = field(default_factory=lambda: {COL_ENTRY: 0, COL_FLOOR: 0, ROW_ENTRY: 0, ROW_FLOOR: 0})
    cases: dict = field(default_factory=dict)

    def __post_init__(self):
        self.live = np.ones(len(self.u), bool)
        self.ci = np.searchsorted(self.lines_u, self.u, "right")
        self.cj = np.searchsorted(self.lines_v, self.v, "right")
        u, v, ids, ci, cj = self.u, self.v, self.ids, self.ci, self.cj
        zero = np.zeros(len(u), np.int64)
        # rightwards over all columns (limit on v); upwards in a column (limit on u); rightwards in a cell
        orders = [(np.lexsort((ids, v, u)), v), (np.lexsort((ids, u, v, ci)), u), (np.lexsort((ids, v, u, cj, ci)), zero)]
        self.order_of, self.place, self.trees = [], [], []
        for order, limit in orders:
            place = np.empty(len(order), np.int64)
            place[order] = np.arange(len(order))
            self.order_of.append(order.tolist()), self.place.append(place.tolist()), self.trees.append(FirstBelow(limit[order]))
        self.col_start = np.searchsorted(ci[orders[0][0]], np.arange(len(self.lines_u) + 2)).tolist()
        self.wide = len(self.lines_v) + 2
        self.row_key = (ci * self.wide + cj)[orders[1][0]]  # ascending, as v goes up with the row
        self.cell_key = (ci * self.wide + cj)[orders[2][0]]

    def remove(self, p: int) -> None:
        self.live[p] = False
        for place, tree in zip(self.place, self.trees):
            tree.remove(place[p])

    def cell(self, p: int) -> tuple[int, int]:
        return int(self.ci[p]), int(self.cj[p])

    def order(self) -> list[tuple[int, int]]:
        """Cells from the upper left to the lower right."""
        return sorted(self.cells, key=lambda c: (c[0], -c[1]))

    # Probes -------------------------------------------------------------------------------------

    def _probe(self, by: tuple) -> int:
        """The point a segment meets first, -1 for none. by: (kind, arguments)."""
        kind, n = by[0], len(self.u)
        self.probes[kind] += 1
        span = lambda keys, a, b: np.searchsorted(keys, (a, b)).tolist()
        if kind == COL_ENTRY:  # from the left edge of a column on, below a height
            tree, (a, b), limit = 0, (self.col_start[min(by[1], len(self.col_start) - 1)], n), by[2]
        elif kind == COL_FLOOR:  # upwards in a column
            tree, (a, b), limit = 1, span(self.row_key, by[1] * self.wide, (by[1] + 1) * self.wide), _INF
        elif kind == ROW_ENTRY:  # rightwards in a cell
            key = by[1] * self.wide + by[2]
            tree, (a, b), limit = 2, span(self.cell_key, key, key + 1), 1
        else:  # upwards from the top of a cell, left of its entry
            tree, (a, b), limit = 1, span(self.row_key, by[1] * self.wide + by[2] + 1, (by[1] + 1) * self.wide), by[3]
        hit = self.trees[tree].first(a, b, limit)
        return self.order_of[tree][hit] if hit >= 0 else -1

    # The three routines -------------------------------------------------------------------------

    def _climb(self, cur: tuple, to: tuple, top_entry: int = -1, top_by: tuple = ()) -> None:
        """Find the cells above cur in its column up to the cell ``to``; to gets its floor here, and its entry if given."""
        while cur != to:
            by = (ROW_FLOOR, cur[0], cur[1], int(self.u[self.cells[cur].entry]))
            hit = self._probe(by)
            if hit < 0:
                return
            nxt = self.cell(hit)
            c = self.cells.setdefault(nxt, Cell())
            c.floor, c.floor_by = hit, by
            if nxt != to or top_entry < 0:
                if nxt != to:
                    c.entry_by = (ROW_ENTRY, *nxt)
                    c.entry = self._probe(c.entry_by)
            else:
                c.entry, c.entry_by = top_entry, top_by
            cur = nxt

    def _column(self, hit: int, by: tuple) -> int:
        """All cells of the column that ``hit`` enters; returns the column's floor."""
        col, top = int(self.ci[hit]), self.cell(hit)
        floor_by = (COL_FLOOR, col)
        floor = self._probe(floor_by)
        low = self.cell(floor)
        c = self.cells.setdefault(low, Cell())
        c.floor, c.floor_by = floor, floor_by
        if low == top:
            c.entry, c.entry_by = hit, by
        else:
            c.entry_by = (ROW_ENTRY, *low)
            c.entry = self._probe(c.entry_by)
            self._climb(low, top, hit, by)
        return floor

    def _towards(self, hit: int, by: tuple, to: tuple | None) -> None:
        """From a hit below some floor rightwards until the cell ``to`` (None: to the end)."""
        while hit >= 0:
            here = self.cell(hit)
            if to is not None and here == to:
                self.cells[to].entry, self.cells[to].entry_by = hit, by
                return
            if to is not None and here[0] == to[0]:
                self.cells[to].entry_by = (ROW_ENTRY, *to)
                self.cells[to].entry = self._probe(self.cells[to].entry_by)
                self._climb(to, here, hit, by)
                return
            floor = self._column(hit, by)
            by = (COL_ENTRY, int(self.ci[hit]) + 1, int(self.v[floor]))
            hit = self._probe(by)

    def first_cells(self) -> list[tuple[int, int]]:
        by = (COL_ENTRY, 0, _INF)
        self._towards(self._probe(by), by, None)
        return self.order()

    def take(self, z: int) -> list[tuple[int, int]]:
        """Take the point off and repair the cells; returns the cells that are new in this round."""
        before = set(self.cells)
        order = self.order()
        self.remove(z)
        c = self.cell(z)
        state = self.cells.get(c)
        is_entry, is_floor = state is not None and state.entry == z, state is not None and state.floor == z
        case = "none" if not (is_entry or is_floor) else "-".join([*(["entry"] * is_entry), *(["floor"] * is_floor)])
        if not (is_entry or is_floor):
            self.cases[case] = self.cases.get(case, 0) + 1
            return []
        at = order.index(c)
        prev, nxt = order[at - 1] if at else None, order[at + 1] if at + 1 < len(order) else None
        eb, fb = state.entry_by, state.floor_by
        if is_entry and is_floor:
            del self.cells[c]
            case += "-" + (COL_ENTRY if eb[0] == COL_ENTRY else fb[0])
            if eb[0] == COL_ENTRY:
                self._towards(self._probe(eb), eb, nxt)
            elif fb[0] == COL_FLOOR:
                hit = self._probe(fb)
                low = self.cell(hit)
                s = self.cells.setdefault(low, Cell())
                s.floor, s.floor_by = hit, fb
                if low != prev:
                    s.entry_by = (ROW_ENTRY, *low)
                    s.entry = self._probe(s.entry_by)
                    self._climb(low, prev)
                by = (COL_ENTRY, c[0] + 1, int(self.v[hit]))
                self._towards(self._probe(by), by, nxt)
            else:
                self._climb(nxt, prev)
        elif is_entry:
            case += "-" + eb[0]
            hit = self._probe(eb)
            if eb[0] == ROW_ENTRY:
                state.entry = hit
                self._climb(c, prev)
            elif self.cell(hit) == c:
                state.entry = hit
            else:
                state.entry_by = (ROW_ENTRY, *c)
                state.entry = self._probe(state.entry_by)
                self._climb(c, self.cell(hit), hit, eb)
        else:
            case += "-" + fb[0]
            state.floor = self._probe(fb)
            if fb[0] == COL_FLOOR:
                by = (COL_ENTRY, c[0] + 1, int(self.v[state.floor]))
                self._towards(self._probe(by), by, nxt)
        self.cases[case] = self.cases.get(case, 0) + 1
        return [x for x in self.cells if x not in before]


@dataclass
class Peel:
    """Best points of a quadrant one after another, with counters per round.

    The optimum of a cell, or of a stretch of it between answers, comes from the cell's sub-path hulls.
    """

    q: Quadrant
    f: np.ndarray  # distance times the sign: small is better
    x: np.ndarray
    y: np.ndarray
    mode: str = "fast"
    count: dict = field(default_factory=lambda: {"cell_optima": 0, "shard_optima": 0, "pushes": 0, "pops": 0, "heap_peak": 0, "lambda": 0, "shards_peak": 0, "reentered": 0, "runs": 0, "vertices": 0})
    rounds: list = field(default_factory=list)

    def __post_init__(self):
        order = np.lexsort((self.q.ids, self.q.u, self.q.v, self.q.cj, self.q.ci))  # a cell's points in order of height
        key = (self.q.ci * self.q.wide + self.q.cj)[order]
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, int)
        self.members = {self.q.cell(order[a]): order[a:b] for a, b in zip(start, np.r_[start[1:], len(key)])}
        self.hulls: dict = {}
        self.heap, self.seen, self.shards = [], set(), {}

    def _push(self, cell, lo: int, hi: int, kind: str) -> None:
        """Best point of a cell's shard: members lo to hi in order of height."""
        self.count[kind] += 1
        if hi <= lo:
            return
        if cell not in self.hulls:
            m = self.members[cell]
            self.hulls[cell] = SubHulls(self.q.u[m], self.q.v[m], self.f[m], list(zip(self.q.ids[m].tolist(), self.x[m].tolist(), self.y[m].tolist())), self.mode)
        tree = self.hulls[cell]
        at = tree.best(lo, hi)
        self.count["runs"], self.count["vertices"] = self.count["runs"] + tree.runs, self.count["vertices"] + tree.looked
        p = int(self.members[cell][at])
        heapq.heappush(self.heap, (int(self.f[p]), *tree.names[at], p, cell, lo, hi, at))
        self.count["pushes"] += 1
        self.count["heap_peak"] = max(self.count["heap_peak"], len(self.heap))
        self.shards[cell] = self.shards.get(cell, 0) + 1
        self.count["shards_peak"] = max(self.count["shards_peak"], self.shards[cell])

    def _found(self, cells) -> int:
        new = 0
        for c in cells:
            if c in self.seen:
                self.count["reentered"] += 1
                continue
            self.seen.add(c)
            new += 1
            self._push(c, 0, len(self.members[c]), "cell_optima")
        self.count["lambda"] += new
        return new

    def run(self, k: int) -> list[int]:
        out: list[int] = []
        before = sum(self.q.probes.values())
        new = self._found(self.q.first_cells())
        self.rounds.append((len(self.q.cells), new, sum(self.q.probes.values()) - before))
        while self.heap and len(out) < k:
            *_, p, cell, lo, hi, at = heapq.heappop(self.heap)
            self.count["pops"] += 1
            out.append(p)
            self.shards[cell] -= 1
            if len(out) == k:
                break
            for a, b in ((lo, at), (at + 1, hi)):
                if b > a:
                    self._push(cell, a, b, "shard_optima")
            before = sum(self.q.probes.values())
            fresh = self.q.take(p)
            new = self._found(fresh)
            self.rounds.append((len(self.q.cells), len(fresh), sum(self.q.probes.values()) - before))
        return out


def of_group(group: Group, quad: int, direction: str, ids, x, y, narrow: bool = True, mode: str = "fast") -> Peel:
    """The search of one quadrant's points.

    narrow: take the stretch where an axis' distance is flat out of the coordinates. Then a
    point that another one dominates is truly worse, so the search alone gives the canonical order.
    """
    ids, x, y = (np.asarray(a, np.int64) for a in (ids, x, y))
    sx, sy = G.QUADS[quad]
    far = (int(x.max() if sx > 0 else x.min()), int(y.max() if sy > 0 else y.min())) if len(x) else (0, 0)
    frame = G.Frame.of(group, quad, direction, far)
    u, v = frame(x, y)
    fu, fv = frame.axes(group)
    (a, c), (b, e) = fu.slope_at(u), fv.slope_at(v)
    f = sign_of(direction) * (a * u + b * v + c + e)
    lines_u, lines_v = fu.v, fv.v
    if narrow:
        inside = lambda flat: flat if direction == "farthest" else (max(flat[0], 0), max(flat[1], 0))
        u, lines_u = G.narrowed(u, lines_u, inside(fu.flat))
        v, lines_v = G.narrowed(v, lines_v, inside(fv.flat))
    return Peel(Quadrant(u, v, ids, lines_u, lines_v), f, x, y, mode)


def quadrant_answer(group: Group, quad: int, direction: str, k: int, ids, x, y, mode: str = "fast"):
    """The k best of a quadrant in canonical order, as the peel gives them, and the peel."""
    peel = of_group(group, quad, direction, ids, x, y, mode=mode)
    return np.array(peel.run(k), np.int64), peel


def counter_rows(peel: Peel, query_id: int, quad: int) -> list[tuple]:
    """(query_id, quad, round, measure, value); round -1 holds totals."""
    rows = [(query_id, quad, i, m, int(v)) for i, r in enumerate(peel.rounds) for m, v in zip(("cells", "new_cells", "probes"), r)]
    rows += [(query_id, quad, -1, m, int(v)) for m, v in peel.count.items()]
    rows += [(query_id, quad, -1, f"probe_{m}", int(v)) for m, v in peel.q.probes.items()]
    rows.append((query_id, quad, -1, "probe_steps", sum(t.steps for t in peel.q.trees)))
    return [*rows, (query_id, quad, -1, "line_bound", int((peel.q.lines_u > 0).sum() + (peel.q.lines_v > 0).sum() + 1))]


ANSWERED = "query_id long, quad int, point_id long, x long, y long, agg_dist long"
COUNTED = "query_id long, quad int, round int, measure string, value long"


def _grouped(groups: list[Group] | None, k: int, direction: str, counters: bool):
    """With groups None their rows come beside the points."""
    known = {g.query_id: g for g in groups or []}

    def run(key: tuple, pdf: pd.DataFrame, rows: pd.DataFrame | None = None) -> pd.DataFrame:
        qid, quad = int(key[0]), int(key[1])
        group = known[qid] if rows is None else Group.of(qid, rows["qx"], rows["qy"], rows["w"])
        at, peel = quadrant_answer(group, quad, direction, k, pdf["point_id"], pdf["x"], pdf["y"])
        if counters:
            return pd.DataFrame(counter_rows(peel, qid, quad), columns=["query_id", "quad", "round", "measure", "value"])
        return pd.DataFrame({"query_id": qid, "quad": quad, "point_id": peel.q.ids[at], "x": peel.x[at], "y": peel.y[at], "agg_dist": peel.f[at] * sign_of(direction)})

    return run


def quadrant_topk(candidates, query, groups, k: int, direction: str = "nearest", counters: bool = False):
    """candidates(point_id, x, y[, own][, query_id]) -> answers per (query_id, quad), or the search's counters.

    Candidates should come pruned (tiles): a group's quadrant is held by one worker. groups: a list, or the table of a large batch.
    """
    from pyspark.sql import functions as F

    x, kinds = quads_of(candidates, query), COUNTED if counters else ANSWERED
    if isinstance(groups, list):
        return x.groupBy("query_id", "quad").applyInPandas(_grouped(groups, k, direction, counters), kinds)
    search, names = _grouped(None, k, direction, counters), [f.split()[0] for f in kinds.split(", ")]

    def run(key: tuple, pdf: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        return search(key, pdf, rows) if len(pdf) else pd.DataFrame(columns=names)

    rows = groups.select("query_id", "qx", "qy", "w").withColumn("quad", F.explode(F.array(*map(F.lit, (1, 2, 3, 4)))))
    return x.groupBy("query_id", "quad").cogroup(rows.groupBy("query_id", "quad")).applyInPandas(run, kinds)


def quads_of(candidates, query):
    """Candidates with their quadrant, per group."""
    from pyspark.sql import functions as F

    from ..functions import weights
    from . import frontier

    if "query_id" not in candidates.columns:
        return frontier.quadrants(candidates, query).drop("u", "v")
    x = candidates.join(weights.anchor(query).select("query_id", "ax", "ay"), "query_id")
    if "own" in x.columns:
        x = x.filter(F.col("own").isNull() | (F.col("own") != F.col("query_id")))
    right, up = F.col("x") > F.col("ax"), F.col("y") > F.col("ay")
    quad = F.when(up, F.when(right, 1).otherwise(2)).otherwise(F.when(right, 4).otherwise(3))
    return x.select("query_id", quad.alias("quad"), "point_id", "x", "y")


def first_cells(points, query, groups: list[Group], direction: str = "nearest"):
    """query_id, quad, ci, cj, entry_id, floor_id of round one, found by probes."""
    known = {g.query_id: g for g in groups}

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        q = of_group(known[int(key[0])], int(key[1]), direction, pdf["point_id"], pdf["x"], pdf["y"], narrow=False).q
        rows = [(int(key[0]), int(key[1]), *c, int(q.ids[q.cells[c].entry]), int(q.ids[q.cells[c].floor])) for c in q.first_cells()]
        return pd.DataFrame(rows, columns=["query_id", "quad", "ci", "cj", "entry_id", "floor_id"])

    return quads_of(points, query).groupBy("query_id", "quad").applyInPandas(run, "query_id long, quad long, ci long, cj long, entry_id long, floor_id long")
