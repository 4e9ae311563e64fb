"""The k least ids in ranges of positions, for any number of ranges of any length.

Positions are cut into blocks, and ``FAN`` blocks make a chunk. In each chunk every run of a power of two blocks keeps its
k least entries, and the chunks are the blocks of the next tier, until one chunk is left. A range then is two partly
covered blocks and at most four runs a tier (two on the last), instead of a row per position inside.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..staging import stage

#: Blocks of a chunk.
FAN = 1024
#: Positions of a block, or k rounded up to a power of two, if that is more.
BLOCK = 128

_ITEMS = "array<struct<point_id:bigint,x:bigint,pos:bigint>>"
_TABLE = f"tier int, level int, start long, items {_ITEMS}"
#: Levels beside those of runs: all entries of a block, and the least of a whole chunk.
_ALL, _WHOLE = -1, -2


def _lists(tier: int, level: int, starts: np.ndarray, sizes: np.ndarray, at: np.ndarray, cols: list) -> pa.RecordBatch:
    items = pa.StructArray.from_arrays([pa.array(c[at]) for c in cols], names=["point_id", "x", "pos"])
    lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(sizes)].astype(np.int32)), items)
    n = len(starts)
    return pa.RecordBatch.from_arrays([pa.array(np.full(n, tier, np.int32)), pa.array(np.full(n, level, np.int32)), pa.array(starts), lists], names=["tier", "level", "start", "items"])


def _of_chunk(tier: int, k: int, fan: int, chunk: int, block, ids, x, pos):
    """The table's rows of one chunk's entries."""
    order = np.lexsort((pos, x, ids))
    cols = [c[order] for c in (ids, x, pos)]
    own = block[order] - chunk * fan
    m, none = int(own.max()) + 1, len(own)
    by = np.argsort(own, kind="stable")
    sizes = np.bincount(own, minlength=m)
    first = np.cumsum(sizes) - sizes
    if tier == 0:
        yield _lists(tier, _ALL, chunk * fan + np.arange(m), sizes, by, cols)
    nth = np.arange(none) - np.repeat(first, sizes)
    runs = np.full((m, k), none, np.int64)
    runs[own[by][nth < k], nth[nth < k]] = by[nth < k]
    level = 0
    while True:
        yield _lists(tier, level, chunk * fan + np.arange(len(runs)), (runs < none).sum(1), runs[runs < none], cols)
        w = 1 << level
        if len(runs) <= w:
            break
        runs, level = np.sort(np.concatenate([runs[:-w], runs[w:]], 1), 1)[:, :k], level + 1
    yield _lists(tier, _WHOLE, np.array([chunk]), np.array([min(k, none)]), np.arange(min(k, none)), cols)


def _chunks(tier: int, k: int, fan: int):
    """Rows (chunk, block, point_id, x, pos) with the chunks one after the other -> the table's rows."""

    def run(batches):
        now, held = None, []
        for batch in batches:
            cols = [c.to_numpy() for c in batch.columns]
            for at in np.split(np.arange(batch.num_rows), np.flatnonzero(np.diff(cols[0])) + 1):
                if not len(at):
                    continue
                if cols[0][at[0]] != now:
                    if held:
                        yield from _of_chunk(tier, k, fan, now, *(np.concatenate(c) for c in zip(*held)))
                    now, held = int(cols[0][at[0]]), []
                held.append(tuple(c[at] for c in cols[1:]))
        if held:
            yield from _of_chunk(tier, k, fan, now, *(np.concatenate(c) for c in zip(*held)))

    return run


def _lookups(b: int, fan: int):
    """(query_id, lo, hi) -> query_id, tier, level, start and the positions [lo, hi) that this entry answers for."""

    def run(batches):
        for batch in batches:
            q, lo, hi = (c.to_numpy() for c in batch.columns)
            out = []

            def add(of, tier, level, start, lo, hi):
                full = lambda v: np.broadcast_to(np.asarray(v, np.int64), len(of))
                if len(of):
                    out.append([q[of], full(tier), full(level), start, lo, hi])

            def add_run(of, tier, unit, s, e):
                level = np.frexp((e - s).astype(np.float64))[1].astype(np.int64) - 1
                mid = s + (np.int64(1) << level)
                add(of, tier, level, s, s * unit, mid * unit)
                more = mid < e
                add(of[more], tier, level[more], (e - (np.int64(1) << level))[more], mid[more] * unit, e[more] * unit)

            of = np.flatnonzero(hi > lo)
            lo, hi = lo[of], hi[of]
            one = lo // b == (hi - 1) // b
            add(of[one], 0, _ALL, lo[one] // b, lo[one], hi[one])
            of, lo, hi = of[~one], lo[~one], hi[~one]
            left, right = lo % b > 0, hi % b > 0
            s, e = -(-lo // b), hi // b
            add(of[left], 0, _ALL, s[left] - 1, lo[left], s[left] * b)
            add(of[right], 0, _ALL, e[right], e[right] * b, hi[right])
            tier, unit = 0, b
            while (s < e).any():
                of, s, e = of[s < e], s[s < e], e[s < e]
                one = s // fan == (e - 1) // fan
                add_run(of[one], tier, unit, s[one], e[one])
                of, s, e = of[~one], s[~one], e[~one]
                s1, e1 = -(-s // fan), e // fan
                left, right = s < s1 * fan, e1 * fan < e
                add_run(of[left], tier, unit, s[left], s1[left] * fan)
                add_run(of[right], tier, unit, e1[right] * fan, e[right])
                s, e, tier, unit = s1, e1, tier + 1, unit * fan
            cols = [np.concatenate(c) for c in zip(*out)] if out else [np.zeros(0, np.int64)] * 6
            yield pa.RecordBatch.from_arrays([pa.array(cols[0]), *(pa.array(c.astype(np.int32)) for c in cols[1:3]), *map(pa.array, cols[3:])], names=["query_id", "tier", "level", "start", "lo", "hi"])

    return run


def least_ids(points: DataFrame, n: int, ranges: DataFrame, k: int) -> DataFrame:
    """points(point_id, x, pos: 0 to n - 1), ranges(query_id, lo, hi) -> the k least by (point_id, x) of each range: query_id, point_id, x.

    Up to k rows per entry that a range looks at; whoever ranks them keeps k.
    """
    fan, b = FAN, max(BLOCK, 1 << (k - 1).bit_length())
    parts = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = points.select(F.expr(f"pos div {b * fan}").alias("chunk"), F.expr(f"pos div {b}").alias("block"), "point_id", "x", "pos")
    chunks, tier, table = -(-n // (b * fan)), 0, None
    while True:
        own = rows.repartition(parts, "chunk").sortWithinPartitions("chunk").mapInArrow(_chunks(tier, k, fan), _TABLE)
        own = stage(own, "least-ids")
        table = own if table is None else table.unionByName(own)
        if chunks <= 1:
            break
        whole = own.filter(f"level = {_WHOLE}").select(F.col("start").alias("block"), F.inline("items"))
        rows = whole.select(F.expr(f"block div {fan}").alias("chunk"), "block", "point_id", "x", "pos")
        chunks, tier = -(-chunks // fan), tier + 1
    asks = ranges.select("query_id", F.col("lo").cast("long"), F.col("hi").cast("long")).mapInArrow(_lookups(b, fan), "query_id long, tier int, level int, start long, lo long, hi long")
    got = asks.join(table, ["tier", "level", "start"])
    mine = F.slice(F.filter("items", lambda e: (e["pos"] >= F.col("lo")) & (e["pos"] < F.col("hi"))), 1, k)
    return got.select("query_id", F.inline(mine)).select("query_id", "point_id", "x")
