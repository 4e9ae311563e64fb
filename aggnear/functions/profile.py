"""Aggregate distance: direct, by prefix profile, and by merged scan; and the numpy form workers use."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import LIMIT
from . import weights


def _axes(points: DataFrame) -> list[tuple[str, str]]:
    return [(c, q) for c, q in (("x", "qx"), ("y", "qy")) if c in points.columns]


def agg_dist_direct(candidates: DataFrame, query: DataFrame) -> DataFrame:
    """candidates(query_id, point_id, x[, y], ...) plus agg_dist: one term per query point, summed."""
    axes = _axes(candidates)
    term = sum((F.abs(F.col(c) - F.col(q)) for c, q in axes[1:]), F.abs(F.col(axes[0][0]) - F.col(axes[0][1])))
    keys = candidates.columns
    x = candidates.withColumn("copies", F.lit(1)).groupBy(*keys).agg(F.sum("copies").alias("copies"))
    x = x.join(query, "query_id").groupBy(*keys, "copies").agg(F.sum(F.col("w") * term).alias("agg_dist"))
    return x.select(*keys, "agg_dist", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).drop("col")


#: Halving steps of a search in an array: 2**22 entries.
_STEPS = [1 << i for i in range(22, -1, -1)]


def upto(arr: Column, c: Column, value=lambda e: e, most: int = 1 << 22) -> Column:
    """How many entries of a sorted array, of at most ``most``, are <= c, by binary search: lg m looks, no pass over the array."""
    return F.aggregate(
        F.array(*[F.lit(s) for s in _STEPS if s <= most]),
        F.lit(0),
        lambda n, s: F.when((n + s <= F.size(arr)) & (value(F.get(arr, n + s - 1)) <= c), n + s).otherwise(n),
    )


def part_of(cuts: list[int], c: Column) -> Column:
    """The part between ascending cuts that holds c: how many cuts are <= c."""
    if not cuts:
        return F.lit(0)
    if len(cuts) <= 32:  # compiled comparisons are faster than a search step by step
        return sum((F.when(c >= v, 1).otherwise(0) for v in cuts[1:]), F.when(c >= cuts[0], 1).otherwise(0))
    return upto(F.array(*[F.lit(v) for v in cuts]).cast("array<bigint>"), c, most=len(cuts))


def _axis_value(arr: str, w: str, wv: str, c: str) -> Column:
    """Slope times coordinate plus intercept, from the profile entry at or below the coordinate."""
    at = F.get(F.col(arr), upto(F.col(arr), F.col(c), lambda e: e["v"]) - 1)
    cw, cwv = F.coalesce(at["cw"], F.lit(0)), F.coalesce(at["cwv"], F.lit(0))
    return F.col(c) * (2 * cw - F.col(w)) - 2 * cwv + F.col(wv)


def agg_dist_profile(candidates: DataFrame, query: DataFrame) -> DataFrame:
    """The same from prefix sums: no row per query point."""
    x = candidates
    total = F.lit(0).cast("long")
    for c, q in _axes(candidates):
        own = (weights.profile_of_sorted if "q" in query.columns else weights.profile)(query, c).withColumnsRenamed({"arr": f"arr_{c}", "w_total": f"w_{c}", "wv_total": f"wv_{c}"})
        x = x.join(own, "query_id")
        total = total + _axis_value(f"arr_{c}", f"w_{c}", f"wv_{c}", c)
    return x.select(*candidates.columns, total.alias("agg_dist"))


def agg_dist_merge(candidates: DataFrame, query: DataFrame) -> DataFrame:
    """The same by scanning candidates and query points together, sorted, once per axis."""
    out, total = candidates, F.lit(0).cast("long")
    for c, _ in _axes(candidates):
        steps = weights.merge_axis(query, c).select("query_id", F.col("v").alias(c), "w", (F.col("w") * F.col("v")).alias("wv"))
        both = out.withColumn("w", F.lit(0).cast("long")).withColumn("wv", F.lit(0).cast("long")).withColumn("is_point", F.lit(True))
        both = both.unionByName(steps.withColumn("is_point", F.lit(False)), allowMissingColumns=True)
        run = Window.partitionBy("query_id").orderBy(c).rangeBetween(Window.unboundedPreceding, 0)
        every = Window.partitionBy("query_id")
        value = F.col(c) * (2 * F.sum("w").over(run) - F.sum("w").over(every)) - 2 * F.sum("wv").over(run) + F.sum("wv").over(every)
        out = both.withColumn(f"f_{c}", value).filter("is_point").drop("w", "wv", "is_point")
        total = total + F.col(f"f_{c}")
    return out.select(*candidates.columns, total.alias("agg_dist"))


EVALUATORS = {"direct": agg_dist_direct, "prefix": agg_dist_profile, "merge": agg_dist_merge}


def agg_dist(candidates: DataFrame, query: DataFrame, evaluator: str = "prefix") -> DataFrame:
    return EVALUATORS[evaluator](candidates, query)


@dataclass(frozen=True)
class Axis:
    """One axis of one query group in numpy: sorted coordinates with prefix sums."""

    v: np.ndarray
    cw: np.ndarray  # with a leading 0
    cwv: np.ndarray

    @classmethod
    def of(cls, coords: np.ndarray, w: np.ndarray) -> "Axis":
        v, back = np.unique(np.asarray(coords, np.int64), return_inverse=True)
        own = np.zeros(len(v), np.int64)
        np.add.at(own, back, np.asarray(w, np.int64))
        if int(own.sum()) * max(1, int(np.abs(v).max(initial=0))) * 4 >= LIMIT:
            raise OverflowError("weights times coordinates exceed 64 bits")
        return cls(v, np.r_[0, np.cumsum(own)], np.r_[0, np.cumsum(own * v)])

    @property
    def total(self) -> int:
        return int(self.cw[-1])

    def slope_at(self, x: np.ndarray):
        """(slope, intercept) of the piece that holds each coordinate."""
        i = np.searchsorted(self.v, x, side="right")
        return 2 * self.cw[i] - self.cw[-1], self.cwv[-1] - 2 * self.cwv[i]

    def __call__(self, x: np.ndarray) -> np.ndarray:
        slope, rest = self.slope_at(x)
        return slope * x + rest

    @property
    def anchor(self) -> int:
        return int(self.v[np.searchsorted(2 * self.cw[1:], self.cw[-1])])

    def cut(self, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray, int]:
        """(coordinates, weights, rest): between lo and hi the function is that of these, plus the rest."""
        w, at = np.diff(self.cw), np.clip(self.v, lo, hi)
        rest = int((w * np.abs(self.v - at)).sum())
        first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
        return at[first], np.add.reduceat(w, first), rest

    @property
    def flat(self) -> tuple[int, int]:
        """The interval of all minimisers."""
        return self.anchor, int(self.v[np.searchsorted(2 * self.cw[1:], self.cw[-1], "right")])


@dataclass(frozen=True)
class Group:
    """A query group of the plane, ready for evaluation in a worker."""

    query_id: int
    qx: np.ndarray
    qy: np.ndarray
    w: np.ndarray
    fx: Axis
    fy: Axis

    @classmethod
    def of(cls, query_id, qx, qy, w) -> "Group":
        qx, qy, w = (np.asarray(a, np.int64) for a in (qx, qy, w))
        return cls(int(query_id), qx, qy, w, Axis.of(qx, w), Axis.of(qy, w))

    def __call__(self, x, y) -> np.ndarray:
        return self.fx(x) + self.fy(y)

    @property
    def anchor(self) -> tuple[int, int]:
        return self.fx.anchor, self.fy.anchor


#: Different query points that are handed to workers with the plan; larger batches are dealt out as a table.
BLOCK_ROWS = 200_000


def merged(query: DataFrame) -> DataFrame:
    """Equal points of a group as one row with their weights added up: the same distances from fewer rows."""
    return query.groupBy("query_id", "qx", "qy").agg(F.sum("w").alias("w"))


def few_groups(query: DataFrame) -> bool:
    """Whether a (staged) batch is small enough to travel with the plan."""
    return query.limit(BLOCK_ROWS + 1).count() <= BLOCK_ROWS


def groups_or_table(query: DataFrame) -> list[Group] | DataFrame:
    """A (staged, merged) batch as groups that travel with the plan, or as it is where it is too large for that."""
    return load_groups(query) if few_groups(query) else query


def each_group(batches):
    """Batches (query_id, qx, qy, w) with the rows of a group one after the other -> its Group."""
    held: list = []

    def close():
        q, *cols = (np.concatenate(c) for c in zip(*held))
        return Group.of(q[0], *cols)

    for batch in batches:
        cols = [c.to_numpy() for c in batch.columns]
        for at in np.split(np.arange(batch.num_rows), np.flatnonzero(np.diff(cols[0])) + 1):
            if not len(at):
                continue
            if held and held[-1][0][0] != cols[0][at[0]]:
                yield close()
                held = []
            held.append([c[at] for c in cols])
    if held:
        yield close()


def load_groups(query: DataFrame) -> list[Group]:
    """All groups of a batch, which must hold at most BLOCK_ROWS different points."""
    rows: dict[int, list] = {}
    got = merged(query).limit(BLOCK_ROWS + 1).collect()
    if len(got) > BLOCK_ROWS:
        raise ValueError(f"more than {BLOCK_ROWS} query points: use a strategy that deals the groups out (scan_dealt, scan_joins)")
    for r in got:
        rows.setdefault(r[0], []).append(r[1:])
    return [Group.of(q, *zip(*rows[q])) for q in sorted(rows)]
