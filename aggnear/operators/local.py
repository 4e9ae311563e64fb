"""Worker-side top-k of points for many groups: every task keeps the best rows it has seen per group."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.profile import Axis, Group, part_of
from ..model import LIMIT, sign_of
from ..staging import stage
from .layout import _cuts

SCHEMA = pa.schema([(c, pa.int64()) for c in ("query_id", "point_id", "x", "y", "agg_dist")])
FOUND = "query_id long, point_id long, x long, y long, agg_dist long"


def best(f, ids, x, y, k: int, sign: int) -> np.ndarray:
    """Indices of the k best in canonical order."""
    key = f * sign
    if len(key) > k:
        tau = np.partition(key, k - 1)[k - 1]
        at = np.flatnonzero(key <= tau)
    else:
        at = np.arange(len(key))
    order = np.lexsort((y[at], x[at], ids[at], key[at]))
    return at[order[:k]]


def rows(held: dict) -> pa.RecordBatch:
    """held: query_id, or (part, query_id) -> (point_id, x, y, agg_dist)."""
    parts = [np.vstack([np.full(len(a[0]), q[1] if isinstance(q, tuple) else q), *a]) for q, a in held.items() if len(a[0])]
    all_ = np.hstack(parts) if parts else np.zeros((5, 0), np.int64)
    return pa.RecordBatch.from_arrays([pa.array(c) for c in all_], schema=SCHEMA)


def scan(groups: list[Group], k: int, sign: int, own: bool, by_group: bool = False):
    """Batches (point_id, x, y[, own][, query_id]) -> the task's k best per group; with by_group a row meets its own group only."""
    known = {g.query_id: g for g in groups}

    def run(batches):
        held: dict = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
            ids, x, y = (cols[c].to_numpy() for c in ("point_id", "x", "y"))
            mine = cols["own"].fill_null(-(1 << 62)).to_numpy() if own else None
            asked = cols["query_id"].to_numpy() if by_group else None
            for g in [known[q] for q in np.unique(asked).tolist() if q in known] if by_group else groups:
                use = None
                if by_group:
                    use = asked == g.query_id
                if own:
                    use = (mine != g.query_id) if use is None else use & (mine != g.query_id)
                i, px, py = (ids, x, y) if use is None else (ids[use], x[use], y[use])
                if not len(i):
                    continue
                f = g(px, py)
                at = best(f, i, px, py, k, sign)
                new = np.vstack([i[at], px[at], py[at], f[at]])
                if g.query_id in held:
                    both = np.hstack([held[g.query_id], new])
                    new = both[:, best(both[3], both[0], both[1], both[2], k, sign)]
                held[g.query_id] = new
        yield rows(held)

    return run


#: Points that one task of a dealt scan holds.
CHUNK = 200_000
_MEET = ("chunk", "kind", "query_id", "point_id", "x", "y", "own", "w")


class Cut:
    """A group's distance within a tile, of rows (coordinate, axis, weight, rest)."""

    def __init__(self, query_id, v, axis, w, rest):
        self.query_id, self.rest = int(query_id), int(rest.sum())
        self.fx, self.fy = (Axis.of(v[axis == i], w[axis == i]) for i in (0, 1))

    def __call__(self, x, y) -> np.ndarray:
        return self.fx(x) + self.fy(y) + self.rest


def meet_cuts(k: int, sign: int):
    """Rows of ``_MEET`` sorted by (chunk, kind, query_id): a chunk's points, then the rows of every group's ``Cut`` -> k best of the chunk per group."""

    def run(batches):
        chunk, points, one, found = None, [], [[], None], {}  # one: rows of the group that is being read, its id

        def close():
            nonlocal points
            if one[1] is None:
                return
            if len(found) >= 512:
                yield rows(found)
                found.clear()
            if not isinstance(points, tuple):
                points = tuple(np.concatenate(c) for c in zip(*points)) if points else ()
            g, one[0], one[1] = Cut(one[1], *(np.concatenate(c) for c in zip(*one[0]))), [], None
            if points:
                use = points[3] != g.query_id
                ids, x, y = (c[use] for c in points[:3])
                f = g(x, y)
                at = best(f, ids, x, y, k, sign)
                found[chunk, g.query_id] = ids[at], x[at], y[at], f[at]

        for batch in batches:
            if not batch.num_rows:
                continue
            c, kind = (b.to_numpy() for b in batch.columns[:2])
            q, ids, x, y, own, w = (b.fill_null(-(1 << 62)).to_numpy() for b in batch.columns[2:])
            for at in np.split(np.arange(len(c)), np.flatnonzero((np.diff(c) != 0) | (np.diff(kind) != 0) | ((np.diff(q) != 0) & (kind[1:] == 1))) + 1):
                a = at[0]
                if c[a] != chunk or (kind[a] == 1 and one[1] != q[a]):
                    yield from close()
                if c[a] != chunk:
                    chunk, points = c[a], []
                if kind[a] == 0:
                    points.append((ids[at], x[at], y[at], own[at]))
                else:
                    one[0].append((x[at], y[at], w[at], own[at]))
                    one[1] = int(q[a])
        yield from close()
        if found:
            yield rows(found)

    return run


#: Points of a tile of a dealt scan, tiles along an axis at most, and points of least id of all tiles that travel with the plan.
TILE, SIDE, LEAST = 1024, 256, 500_000


#: Entries of the arrays that are made for many groups at once, and rows of a group beyond which it is sorted instead.
_AT_ONCE, _WIDE = 1 << 18, 64


def _values(v: np.ndarray, w: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Sums of w * abs(v - at) of many groups, a row each, at coordinates that are the same for all, or a row each."""
    if v.shape[1] > _WIDE:
        own = np.broadcast_to(at, (len(v), at.shape[-1]))
        return np.stack([Axis.of(a, b)(c) for a, b, c in zip(v, w, own)])
    out = np.zeros((len(v), at.shape[-1]), np.int64)
    for a, b in zip(v.T, w.T):
        out += b[:, None] * np.abs(at - a[:, None])
    return out


def _distances(qx, qy, w, x, y) -> np.ndarray:
    """Distances of many groups, a row each, to points: coordinates beyond all points make a line, only those between are summed one by one."""
    out = np.zeros((len(w), len(x)), np.int64)
    for v, p in ((qx, x), (qy, y)):
        lo, hi = p.min(), p.max()
        left, right = np.where(v <= lo, w, 0), np.where((v >= hi) & (v > lo), w, 0)
        out += (left.sum(axis=1) - right.sum(axis=1))[:, None] * p + ((right - left) * v).sum(axis=1)[:, None]
        inside = (v > lo) & (v < hi) & (w > 0)
        many = int(inside.sum(axis=1).max())
        if many:
            order = np.argsort(~inside, axis=1, kind="stable")[:, :many]
            out += _values(np.take_along_axis(v, order, 1), np.take_along_axis(np.where(inside, w, 0), order, 1), p)
    return out


def _padded(q, *cols):
    """Query rows with the groups one after the other -> (query_ids, their first rows, qx, qy, w): groups of like size, a row each, w 0 where there is none."""
    start = np.flatnonzero(np.r_[True, q[1:] != q[:-1]])
    size = np.diff(np.r_[start, len(q)])
    kind = np.ceil(np.log2(size)).astype(int)
    for one in np.unique(kind):
        every = np.flatnonzero(kind == one)
        wide = int(size[every].max())
        for a in range(0, len(every), max(1, (_AT_ONCE >> 2) // wide)):
            some = every[a : a + max(1, (_AT_ONCE >> 2) // wide)]
            place = np.minimum(np.arange(wide), size[some, None] - 1)
            qx, qy, w = (c[start[some, None] + place] for c in cols)
            w = np.where(np.arange(wide) < size[some, None], w, 0)
            if (w.sum(axis=1, dtype=float) * np.maximum(1, np.maximum(abs(qx), abs(qy)).max(axis=1)) * 4 >= LIMIT).any():
                raise OverflowError("weights times coordinates exceed 64 bits")
            yield q[start[some]], start[some], qx, qy, w


def _whole_groups(batches):
    """Batches whose first column names the group, groups one after the other -> arrays of their columns that hold whole groups."""
    held = None
    for batch in batches:
        if not batch.num_rows:
            continue
        now = [c.fill_null(LIMIT).to_numpy() for c in batch.columns]
        if held is not None:
            now = [np.concatenate(c) for c in zip(held, now)]
        cut = int(np.searchsorted(now[0] != now[0][-1], False)) if now[0][0] != now[0][-1] else 0
        held = [c[cut:] for c in now]
        if cut:
            yield [c[:cut] for c in now]
    if held is not None:
        yield held


class _Grid:
    """The tiles of a dealt scan, and bounds of many groups' distances over them.

    A group's distance over a tile lies between sums of an axis' least and greatest value in the tile's slab and
    band. All is counted with the direction's sign, so less is better.
    """

    def __init__(self, tiles: dict, sign: int):
        self.slab, self.band, self.n, self.parts = (tiles[c] for c in ("slab", "band", "n", "parts"))
        self.spans, self.sign = [(tiles["xlo"], tiles["xhi"]), (tiles["ylo"], tiles["yhi"])], sign
        self.at = np.full((len(tiles["xlo"]), len(tiles["ylo"])), -1)
        self.at[self.slab, self.band] = np.arange(len(self.n))

    def bounds(self, qx, qy, w):
        """Best and worst of each slab, best and worst of each band, a row per group."""
        out = []
        for v, (lo, hi) in zip((qx, qy), self.spans):
            order = np.argsort(v, axis=1, kind="stable")
            run = np.cumsum(np.take_along_axis(w, order, 1), axis=1)
            first = (2 * run >= run[:, -1:]).argmax(axis=1)[:, None]
            anchor = np.take_along_axis(np.take_along_axis(v, order, 1), first, 1)
            a, b = _values(v, w, lo), _values(v, w, hi)
            low, high = np.where(lo > anchor, a, np.where(hi < anchor, b, _values(v, w, anchor))), np.maximum(a, b)
            out += [low, high] if self.sign > 0 else [-high, -low]
        return out

    def first(self, qx, qy, w, need) -> np.ndarray:
        """For each group the tile of best bound among those that hold as many points as it needs, -1 if none does."""
        gx, _, gy, _ = self.bounds(qx, qy, w)
        tile = self.at[gx.argmin(axis=1), gy.argmin(axis=1)]
        for i in np.flatnonzero((tile < 0) | (self.n[tile] < need)).tolist():
            full = np.flatnonzero(self.n >= need[i])
            tile[i] = full[(gx[i, self.slab[full]] + gy[i, self.band[full]]).argmin()] if len(full) else -1
        return tile

    def live(self, qx, qy, w, need, tau) -> tuple[np.ndarray, ...]:
        """(group, tile, best, worst) of the tiles that can hold an answer, ties included: none worse than tau, or where that is
        LIMIT than what tiles with as many points as a group needs reach."""
        gx, wx, gy, wy = self.bounds(qx, qy, w)
        tau = tau.copy()
        for i in np.flatnonzero(tau == LIMIT).tolist():
            worst, full = wx[i, self.slab] + wy[i, self.band], self.n >= need[i]
            if full.any():
                tau[i] = worst[full].min()
            else:
                order = np.argsort(worst, kind="stable")
                at = int(np.searchsorted(np.cumsum(self.n[order]), need[i]))
                tau[i] = worst[order[at]] if at < len(order) else LIMIT
        g, slab = np.nonzero(gx <= (tau - gy.min(axis=1))[:, None])
        out = [(np.zeros(0, np.int64),) * 4]
        for a in range(0, len(g), max(1, _AT_ONCE // gy.shape[1])):
            i, s = (c[a : a + max(1, _AT_ONCE // gy.shape[1])] for c in (g, slab))
            r, band = np.nonzero((gx[i, s][:, None] + gy[i] <= tau[i, None]) & (self.at[s] >= 0))
            i, s = i[r], s[r]
            out.append((i, self.at[s, band], gx[i, s] + gy[i, band], wx[i, s] + wy[i, band]))
        return tuple(np.concatenate(c) for c in zip(*out))

    def few(self, q, *cols):
        """``_padded``, with as many groups at once as the tiles allow."""
        step = max(1, 4 * _AT_ONCE // max(self.at.shape))
        for ids, start, *rows in _padded(q, *cols):
            for a in range(0, len(ids), step):
                yield ids[a : a + step], start[a : a + step], *(c[a : a + step] for c in rows)


def _top(group, f, ids, x, y, k: int) -> np.ndarray:
    """Indices of the k best rows of each group in canonical order."""
    order = np.lexsort((y, x, ids, f, group))
    start = np.flatnonzero(np.r_[True, np.diff(group[order]) != 0]) if len(order) else np.zeros(0, int)
    return order[np.arange(len(order)) - np.repeat(start, np.diff(np.r_[start, len(order)])) < k]


def _sent(chunk, start, q, qx, qy, w, tau):
    """The rows of groups, which begin at start in the sorted query rows, for each of the chunks that they go to."""
    size = np.searchsorted(q, q[start], side="right") - start
    for a in range(0, len(start), 1 << 14):
        m = size[a : a + (1 << 14)]
        at = np.repeat(start[a : a + (1 << 14)] - (np.cumsum(m) - m), m) + np.arange(m.sum())
        cols = np.repeat(chunk[a : a + (1 << 14)], m), q[at], qx[at], qy[at], w[at], tau[at]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["chunk", "query_id", "qx", "qy", "w", "tau"])


_SENT = "chunk long, query_id long, qx long, qy long, w long, tau long"


def _started(tiles: dict, k: int, sign: int):
    """Query rows (query_id, qx, qy, w, away), sorted -> their rows for one chunk that shows how good a group's k best are at least."""

    def run(batches):
        grid = _Grid(tiles, sign)
        for q, qx, qy, w, away in _whole_groups(batches):
            for _, start, *rows in grid.few(q, qx, qy, w):
                tile = grid.first(*rows, k + away[start])
                yield from _sent(tile[tile >= 0] * 1024, start[tile >= 0], q, qx, qy, w, np.full(len(q), LIMIT))

    return run


def _wanted(tiles: dict, k: int, sign: int):
    """Query rows (query_id, qx, qy, w, away[, tau]), sorted -> their rows for every chunk of the tiles that can hold an answer, ties included.

    With the least points of each tile, tiles over which a distance does not change need no look at their points:
    a group's k best of such tiles come as rows of a negative chunk, with x, y, point_id and distance.
    """
    least = tiles.get("least")

    def run(batches):
        grid = _Grid(tiles, sign)
        for q, qx, qy, w, away, *tau in _whole_groups(batches):
            tau = tau[0] if tau else np.full(len(q), LIMIT)
            for _, start, *rows in grid.few(q, qx, qy, w):
                g, tile, good, worst = grid.live(*rows, k + away[start], tau[start])
                if least is not None and (good == worst).any():
                    first, ids, x, y = least
                    at = np.flatnonzero(good == worst)
                    many = first[tile[at] + 1] - first[tile[at]]
                    p = np.repeat(first[tile[at]] - (np.cumsum(many) - many), many) + np.arange(many.sum())
                    at = np.repeat(at, many)
                    top = _top(g[at], good[at], ids[p], x[p], y[p], k)
                    at, p = at[top], p[top]
                    own = q[start[g[at]]]
                    cols = -1 - own % 1024, own, x[p], y[p], ids[p], sign * good[at]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["chunk", "query_id", "qx", "qy", "w", "tau"])
                    g, tile = g[good != worst], tile[good != worst]
                many = grid.parts[tile]
                chunk = np.repeat(tile * 1024 - (np.cumsum(many) - many), many) + np.arange(many.sum())
                yield from _sent(chunk, np.repeat(start[g], many), q, qx, qy, w, tau)

    return run


def _meet_all(solve):
    """Rows (chunk, kind, query_id, point_id, x, y, own, w, tau) sorted by the first three: a chunk's points, then the groups; answers (kind 2) pass.

    solve gets the points (point_id, x, y, own), least ids first, and many groups (query_ids, taus, qx, qy, w).
    """

    def run(batches):
        chunk, points, groups = None, [], []

        def close(whole=True):
            nonlocal points, groups
            if not groups or not points:
                groups = []
                return
            if not isinstance(points, tuple):
                points = [np.concatenate(c) for c in zip(*points)]
                order = np.lexsort((points[2], points[1], points[0]))
                points = tuple(c[order] for c in points)
            q, x, y, w, tau = (np.concatenate(c) for c in zip(*groups))
            cut = len(q) if whole else int(np.flatnonzero(q == q[-1])[0])
            groups = [] if whole else [(q[cut:], x[cut:], y[cut:], w[cut:], tau[cut:])]
            if not cut:
                return
            step = max(1, _AT_ONCE // len(points[0]))
            for ids, start, *rows in _padded(q[:cut], x[:cut], y[:cut], w[:cut]):
                for a in range(0, len(ids), step):
                    yield solve(points, ids[a : a + step], tau[start[a : a + step]], *(c[a : a + step] for c in rows))

        for batch in batches:
            if not batch.num_rows:
                continue
            c, kind = (b.to_numpy() for b in batch.columns[:2])
            q, ids, x, y, own, w, tau = (b.fill_null(-LIMIT).to_numpy() for b in batch.columns[2:])
            edges = np.flatnonzero(np.r_[True, (c[1:] != c[:-1]) | (kind[1:] != kind[:-1]), True])
            for a, b in zip(edges[:-1], edges[1:]):
                if c[a] != chunk:
                    yield from close()
                    chunk, points = c[a], []
                if kind[a] == 2:
                    yield pa.RecordBatch.from_arrays([pa.array(v[a:b]) for v in (q, w, x, y, tau)], schema=SCHEMA)
                elif kind[a] == 0:
                    points.append((ids[a:b], x[a:b], y[a:b], own[a:b]))
                else:
                    groups.append((q[a:b], x[a:b], y[a:b], w[a:b], tau[a:b]))
                    if sum(len(g[0]) for g in groups) > 1 << 16:
                        yield from close(False)
        yield from close()

    return run


def _reached(k: int, sign: int):
    """The value that k points of a chunk reach for each group."""

    def solve(points, q, tau, *rows):
        _, x, y, own = points
        f = np.where(own == q[:, None], LIMIT, sign * _distances(*rows, x, y))
        tau = np.partition(f, k - 1, axis=1)[:, k - 1] if len(x) >= k else np.full(len(q), LIMIT)
        return pa.RecordBatch.from_arrays([pa.array(q[tau < LIMIT]), pa.array(tau[tau < LIMIT])], names=["query_id", "tau"])

    return _meet_all(solve)


def _answers(k: int, sign: int):
    """The k best of a chunk for each group, none worse than its tau."""

    def solve(points, q, tau, *rows):
        ids, x, y, own = points
        f = sign * _distances(*rows, x, y)
        ok = own != q[:, None]
        if len(x) > k and (tau == LIMIT).any():
            tau = np.minimum(tau, np.partition(np.where(ok, f, LIMIT), k - 1, axis=1)[:, k - 1])
        r, c = np.nonzero(ok & (f <= tau[:, None]))
        f = f[r, c]
        tie = f == tau[r]  # of those, which come by ascending id, the first k will do
        before = np.cumsum(tie)
        start = np.flatnonzero(np.r_[True, r[1:] != r[:-1]]) if len(r) else np.zeros(0, int)
        stay = ~tie | (before - np.repeat((before - tie)[start], np.diff(np.r_[start, len(r)])) <= k)
        r, c, f = r[stay], c[stay], f[stay]
        top = _top(r, f, ids[c], x[c], y[c], k)
        r, c, f = r[top], c[top], f[top]
        return pa.RecordBatch.from_arrays([pa.array(a) for a in (q[r], ids[c], x[c], y[c], sign * f)], schema=SCHEMA)

    return _meet_all(solve)


def _tiles(points: DataFrame, many: int) -> tuple[DataFrame, dict]:
    """Points with their tile's number, and what is known of the tiles: at most SIDE x SIDE rows."""
    side = max(1, min(SIDE, int((many / TILE) ** 0.5)))
    x_cuts, y_cuts = ([] if side == 1 else _cuts(points, c, side) for c in ("x", "y"))
    p = points.withColumn("slab", part_of(x_cuts, F.col("x"))).withColumn("band", part_of(y_cuts, F.col("y")))
    ends = [f(c).alias(c + n) for c in ("x", "y") for f, n in ((F.min, "lo"), (F.max, "hi"))]
    got = p.groupBy("slab", "band").agg(F.count("*").alias("n"), *ends).toPandas()
    tiles = {c: got[c].to_numpy(np.int64) for c in ("slab", "band", "n")}
    for at, cuts, c in (("slab", x_cuts, "x"), ("band", y_cuts, "y")):
        lo, hi = np.full(len(cuts) + 1, np.iinfo(np.int64).max), np.full(len(cuts) + 1, np.iinfo(np.int64).min)
        np.minimum.at(lo, tiles[at], got[c + "lo"].to_numpy(np.int64))
        np.maximum.at(hi, tiles[at], got[c + "hi"].to_numpy(np.int64))
        tiles[c + "lo"], tiles[c + "hi"] = np.where(lo > hi, 0, lo), np.where(lo > hi, 0, hi)  # parts without points are in no tile
    tiles["parts"] = np.minimum(1024, -(-tiles["n"] // CHUNK))
    return p, tiles


def scan_dealt(points: DataFrame, query: DataFrame, k: int, direction: str) -> DataFrame:
    """The k best of each group per tile, groups of any number: points are dealt once by small tiles, groups go by shuffle to the tiles that can hold their answers."""
    spark = points.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    sign, none = sign_of(direction), F.lit(None).cast("long")
    p, tiles = _tiles(points, points.count())
    numbers = spark.createDataFrame([(int(a), int(b), i, int(m)) for i, (a, b, m) in enumerate(zip(tiles["slab"], tiles["band"], tiles["parts"]))], "slab int, band int, tile long, parts int")
    chunk = F.col("tile") * 1024 + F.pmod(F.xxhash64("point_id", "x", "y"), F.col("parts"))
    own = F.col("own") if "own" in points.columns else F.lit(None)
    p = p.join(F.broadcast(numbers), ["slab", "band"])  # at most SIDE x SIDE rows
    if "own" not in points.columns and k * len(tiles["n"]) <= LEAST:
        rank = Window.partitionBy("tile").orderBy("point_id", "x", "y")
        few = p.withColumn("r", F.row_number().over(rank)).filter(F.col("r") <= k).select("tile", "point_id", "x", "y", "r").toPandas()
        few = few.sort_values(["tile", "r"])
        tiles["least"] = np.searchsorted(few["tile"], np.arange(len(tiles["n"]) + 1)), *(few[c].to_numpy(np.int64) for c in ("point_id", "x", "y"))
    p = p.select(chunk.alias("chunk"), F.lit(0).alias("kind"), none.alias("query_id"), "point_id", "x", "y", own.cast("long").alias("own"), none.alias("w"))
    q = query.select("query_id", "qx", "qy", "w")
    if "own" in points.columns:
        q = q.join(points.groupBy(F.col("own").alias("query_id")).agg(F.count("*").alias("away")), "query_id", "left").na.fill(0, ["away"])
    else:
        q = q.withColumn("away", F.lit(0).cast("long"))
    q = stage(q, "dealt-query")
    points_of = p.withColumn("tau", none)

    def met(sent, search, kinds):
        g = sent.select("chunk", F.when(F.col("chunk") < 0, 2).otherwise(1).alias("kind"), "query_id", none.alias("point_id"), F.col("qx").alias("x"), F.col("qy").alias("y"), none.alias("own"), "w", "tau")
        return points_of.unionByName(g).repartition(n, "chunk").sortWithinPartitions("chunk", "kind", "query_id").mapInArrow(search, kinds)

    def dealt(rows):
        return rows.repartition(n, "query_id").sortWithinPartitions("query_id")

    # a first look at one tile gives a value that k points reach; only tiles that can hold better ones, or ties, are looked at then
    tau = stage(met(dealt(q).mapInArrow(_started(tiles, k, sign), _SENT), _reached(k, sign), "query_id long, tau long"), "dealt-tau")
    q = q.join(tau.hint("merge"), "query_id", "left").select("query_id", "qx", "qy", "w", "away", "tau")
    return met(dealt(q).mapInArrow(_wanted(tiles, k, sign), _SENT), _answers(k, sign), FOUND)
