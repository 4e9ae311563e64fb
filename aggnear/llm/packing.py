"""Best-fit packing by bin completion with branch and bound.

A document's ids (one end id included) are cut into pieces of at most ``capacity`` only if longer.
Pieces are packed whole. Lengths are whole numbers from 1 to the capacity, so what is to be packed is
a histogram of at most ``capacity`` classes, whatever the number of documents: the search runs on it.

A sequence is completed around the longest piece left. Its fillings are the undominated sets of
other pieces for the room left; filling A dominates B if B's pieces can be put into A's. Fillings are
tried by waste, then by larger pieces first; a branch ends once the waste it has closed reaches what
the best packing known leaves over. The first packing known is best-fit decreasing, and every search
result that needs fewer sequences takes its place. The search first looks at the few best fillings of
each sequence; where that tree is exhausted without reaching the bound, it is searched again with more
of them, till nothing was left out (then the packing is proved least), the bound is reached (likewise) or
the node budget is spent. The bound is the better of the volume and of what pieces that cannot
share a sequence, with the rest in the room they leave, need. Equal sequences are completed together, as often as the counts allow, so the depth of a
branch is bounded by the number of classes too.

The outcome is a list of patterns, each used a number of times. Pieces are ranked within their class
(task counts and prefix sums, no sort of the data) and read their sequence and offset off the
patterns' rank intervals.

Defined results: a null or empty text is one piece with the end id alone; repeated rows are packed
each; null ids are carried along; which of equally long pieces goes where follows their order in the
files; an empty table gives an empty result; extra columns are not read.
"""

from __future__ import annotations

from bisect import bisect_right
from collections import Counter
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import slices, stage, table
from .tokens import default_path, encode_batches

CAPACITY = 4096
#: Fillings looked at for one sequence and kept for branching at first, and sequences completed in all searches together.
LOOKS, WIDTH, NODES = 400, 3, 20_000
#: Looks that fillings may take in all searches together: what bounds the driver's time.
EFFORT = 4_000_000


def lower_bound(histogram: dict[int, int], capacity: int) -> int:
    """Sequences that any packing needs.

    For each limit k up to half the capacity: pieces above capacity - k stand alone, those from there
    down to half stand one to a sequence, and the pieces from k to half need what room the latter leave.
    """
    lengths = sorted(histogram)
    total = sum(x * n for x, n in histogram.items())
    best = -(-total // capacity)
    count, volume = [0], [0]
    for x in lengths:
        count.append(count[-1] + histogram[x])
        volume.append(volume[-1] + x * histogram[x])
    half = bisect_right(lengths, capacity // 2)  # pieces that two of can share a sequence
    for at in range(half + 1):
        k = lengths[at] if at < half else capacity // 2 + 1
        alone = bisect_right(lengths, capacity - k)
        alone = max(alone, half)
        single, room = count[alone] - count[half], capacity * (count[alone] - count[half]) - (volume[alone] - volume[half])
        small = volume[half] - volume[min(at, half)]
        best = max(best, count[-1] - count[alone] + single + max(0, -(-(small - room) // capacity)))
    return best


def fillings(lengths: list[int], counts: dict[int, int], room: int, looks: int = LOOKS, width: int = WIDTH, spent: list[int] | None = None) -> tuple[list[tuple[int, ...]], bool]:
    """Undominated fillings of the room from the sorted lengths with counts, least waste first; and whether these are all.

    Depth first, larger pieces first; only maximal fillings (no further piece fits) come up. A piece
    as long as the room dominates every other filling. The enumeration goes on after exact fillings
    until ``width`` of them are found.
    """
    if counts.get(room, 0) > 0:
        return [(room,)], True
    found: list[tuple[int, ...]] = []
    left, exact_found, whole = [looks], [0], [True]

    def pairs(room: int, below: int, taken: Counter) -> tuple[int, ...] | None:
        """Two pieces that fill the room exactly, as alike as may be: small pieces stay for later."""
        for b in range(bisect_right(lengths, min(below, room - 1)) - 1, -1, -1):
            x, y = lengths[b], room - lengths[b]
            if y > x:
                return None
            if counts.get(y, 0) - taken[y] > (x == y) and counts[x] - taken[x] > 0:
                return x, y
        return None

    def hit(filling: tuple[int, ...]) -> bool:
        """Notes an exact filling; False once there are enough."""
        found.append(filling)
        exact_found[0] += 1
        if exact_found[0] >= width:
            whole[0] = False
            return False
        return True

    def grow(room: int, below: int, chosen: list[int], taken: Counter) -> bool:
        """False once the looks are used up or enough exact fillings are found."""
        if left[0] <= 0:
            whole[0] = False
            return False
        left[0] -= 1
        if room == 0:
            return hit(tuple(chosen))
        if width <= WIDTH:  # short cuts to an exact filling
            if counts.get(room, 0) - taken[room] > 0 and room <= below:
                whole[0] = False
                found.append((*chosen, room))
                return False
            if two := pairs(room, below, taken):
                whole[0] = False
                found.append((*chosen, *two))
                return False
        fits = False
        for at in range(bisect_right(lengths, min(below, room)) - 1, -1, -1):
            x = lengths[at]
            if counts[x] - taken[x] <= 0:
                continue
            fits = True
            chosen.append(x)
            taken[x] += 1
            more = grow(room - x, x, chosen, taken)
            chosen.pop()
            taken[x] -= 1
            if not more:
                return False
        if not fits:
            smallest = next((x for x in lengths if counts[x] - taken[x] > 0), None)
            if smallest is None or smallest > room:
                found.append(tuple(chosen))
        return True

    grow(room, room, [], Counter())
    if spent is not None:
        spent[0] += looks - left[0]
    if not found:
        found.append(_best_fit_fill(lengths, counts, room))
    ranked = sorted(set(found), key=lambda f: (room - sum(f), [-x for x in f]))
    kept: list[tuple[int, ...]] = []
    for f in ranked:
        if any(_dominates(k, f) for k in kept):
            continue
        if len(kept) == width:
            whole[0] = False
            break
        kept.append(f)
    return kept, whole[0]


def _best_fit_fill(lengths: list[int], counts: dict[int, int], room: int) -> tuple[int, ...]:
    taken, out = Counter(), []
    at = bisect_right(lengths, room) - 1
    while at >= 0:
        x = lengths[at]
        if x <= room and counts[x] - taken[x] > 0:
            taken[x] += 1
            out.append(x)
            room -= x
        else:
            at = min(at - 1, bisect_right(lengths, room) - 1)
    return tuple(out)


def _dominates(a: tuple[int, ...], b: tuple[int, ...]) -> bool:
    """Whether the pieces of b can be put into the pieces of a (searched for short fillings only)."""
    if len(b) < len(a) or sum(b) > sum(a) or len(b) > 8:
        return False

    def put(i: int, room: list[int]) -> bool:
        if i == len(b):
            return True
        for j in {r: j for j, r in enumerate(room) if r >= b[i]}.values():
            room[j] -= b[i]
            if put(i + 1, room):
                return True
            room[j] += b[i]
        return False

    return put(0, list(a))


def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Patterns of a best-fit decreasing packing, equal sequences together."""
    open_bins: Counter = Counter()  # (room, pattern) -> how many
    rooms: dict[int, list[tuple[int, ...]]] = {}
    order: list[int] = []  # rooms with open bins, sorted
    for x in sorted(counts, reverse=True):
        n = counts[x]
        while n > 0:
            at = np.searchsorted(order, x)
            if at == len(order):
                each = 1 if capacity < 2 * x else capacity // x
                times = n // each
                if times == 0:
                    each, times = n, 1
                pattern, room = (x,) * each, capacity - x * each
            else:
                was = order[at]
                old = rooms[was][-1]
                each = min(max(1, was // x), n)
                times = min(open_bins[was, old], n // each)
                open_bins[was, old] -= times
                if not open_bins[was, old]:
                    del open_bins[was, old]
                    rooms[was].pop()
                    if not rooms[was]:
                        del rooms[was]
                        order.pop(at)
                pattern, room = old + (x,) * each, was - x * each
            n -= each * times
            if room not in rooms:
                rooms[room] = []
                order.insert(int(np.searchsorted(order, room)), room)
            if not open_bins[room, pattern]:
                rooms[room].append(pattern)
            open_bins[room, pattern] += times
    return [(p, n) for (_, p), n in open_bins.items() if n]


@dataclass
class Packing:
    """Patterns (lengths of a sequence) with the number of sequences of each, the bound, and whether fewer sequences are impossible."""

    patterns: list[tuple[tuple[int, ...], int]]
    bound: int
    proved: bool
    nodes: int = 0

    @property
    def sequences(self) -> int:
        return sum(n for _, n in self.patterns)


def pack_lengths(histogram: dict[int, int], capacity: int = CAPACITY, nodes: int = NODES, effort: int = EFFORT) -> Packing:
    """Histogram of lengths -> packing: ever wider searches from the best packing known."""
    if not histogram:
        return Packing([], 0, True)
    bound = lower_bound(histogram, capacity)
    best = Packing(best_fit_decreasing(dict(histogram), capacity), bound, False)
    width, looks, spent = WIDTH, LOOKS, [0, 0]  # sequences completed, looks taken
    while best.sequences > bound and spent[0] < nodes and spent[1] < effort:
        patterns, exhausted, whole = _search(histogram, capacity, best, width, looks, spent, nodes, effort)
        best = Packing(patterns, bound, exhausted and whole)
        if best.proved or not exhausted:
            break
        width, looks = width * 8, looks * 8
    best.proved, best.nodes = best.proved or best.sequences == bound, spent[0]
    return best


def _search(histogram: dict[int, int], capacity: int, start: Packing, width: int, looks: int, spent: list[int], nodes: int, effort: int):
    """(best patterns, whether the tree was exhausted, whether no filling was left out of it)."""
    total = sum(x * n for x, n in histogram.items())
    used = lambda p: sum(n for _, n in p)
    best, bound, whole = start.patterns, start.bound, True
    counts, lengths = dict(histogram), sorted(histogram)
    takes = [0]

    def remove(pattern, times, sign):
        for x, k in Counter(pattern).items():
            counts[x] = counts.get(x, 0) - sign * k * times
            if counts[x] == 0:
                lengths.pop(bisect_right(lengths, x) - 1)
            elif sign < 0 and counts[x] == k * times:
                lengths.insert(bisect_right(lengths, x), x)

    # depth-first with an explicit stack: (fillings left to try, pattern placed, times, waste so far)
    path: list[tuple[tuple[int, ...], int]] = []
    stack: list[list] = []
    waste = 0

    def open_node():
        nonlocal whole
        top = lengths[-1]
        counts[top] -= 1
        if not counts[top]:
            lengths.pop()
        options, all_ = fillings(lengths, counts, capacity - top, looks, width, takes)
        whole = whole and all_
        counts[top] += 1
        if counts[top] == 1:
            lengths.append(top)
        stack.append([iter([(top, *f) for f in options]), None, 0])

    if lengths:
        open_node()
    done = spent[1]
    while stack and used(best) > bound and spent[0] < nodes and spent[1] < effort:
        spent[1] = done + takes[0]
        node = stack[-1]
        if node[1] is not None:  # come back from below
            waste -= (capacity - sum(node[1])) * node[2]
            remove(node[1], node[2], -1)
            path.pop()
            node[1] = None
        pattern = next(node[0], None)
        if pattern is None:
            stack.pop()
            continue
        need = Counter(pattern)
        times = min(counts[x] // k for x, k in need.items())
        if times > 1:
            whole = False  # repeats are taken together, fewer of them are not tried
        over = capacity - sum(pattern)
        allowed = (used(best) - 1) * capacity - total
        if waste + over * times > allowed:
            times = (allowed - waste) // over if over and allowed >= waste + over else 0
            if times <= 0:
                continue
        if over:  # a wasteful sequence is placed once: its repeats are decided again
            times = 1 if over * times * 2 > allowed - waste + 1 else times
        spent[0] += 1
        waste += over * times
        remove(pattern, times, 1)
        path.append((pattern, times))
        node[1], node[2] = pattern, times
        if not lengths:
            if used(path) < used(best):
                best = list(path)
        else:
            open_node()
    return best, not stack, whole


class Plan:
    """Where the r-th piece of a length goes: patterns as rank intervals per length."""

    def __init__(self, patterns: list[tuple[tuple[int, ...], int]]):
        rows: dict[int, list[tuple[int, int, int, int]]] = {}
        given: Counter = Counter()
        first = 0
        for pattern, times in patterns:
            offset = 0
            for x, k in sorted(Counter(pattern).items(), reverse=True):
                rows.setdefault(x, []).append((given[x], first, k, offset))
                given[x] += k * times
                offset += k * x
            first += times
        self.sequences = first
        self.rows = {x: np.array(r, np.int64).T for x, r in rows.items()}

    def place(self, length: int, rank: np.ndarray):
        """(sequence, offset) of pieces of one length by rank: k pieces of a sequence stand together."""
        start, first, each, offset = self.rows[length]
        at = np.searchsorted(start, rank, side="right") - 1
        inside = rank - start[at]
        return first[at] + inside // each[at], offset[at] + inside % each[at] * length


_PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long, part long, nth long"


def _cut(path: str, capacity: int):
    def run(batches):
        part = TaskContext.get().partitionId()
        seen = np.zeros(capacity + 1, np.int64)
        for batch in slices(batches, 256):
            out = []
            for i, ids in encode_batches(path, batch.column(1).to_pylist()):
                for p, a in enumerate(range(0, len(ids), capacity)):
                    piece = ids[a : a + capacity]
                    out.append((i, p, a, len(piece), crc32(piece.tobytes()), seen[len(piece)]))
                    seen[len(piece)] += 1
            if out:
                at, p, start, length, crc, nth = (np.array(x, np.int64) for x in zip(*out))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(pa.array(at)), pa.array(p.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc), pa.array(np.full(len(p), part)), pa.array(nth)],
                    names=["doc_id", "piece", "start", "length", "ids_crc32", "part", "nth"],
                )

    return run


def _place(plan: Plan):
    def run(batches):
        for batch in batches:
            length, rank = batch.column(3).to_numpy(), batch.column(5).to_numpy()
            seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            order = np.argsort(length, kind="stable")
            for at in np.split(order, np.flatnonzero(np.diff(length[order])) + 1) if len(order) else []:
                seq[at], off[at] = plan.place(int(length[at[0]]), rank[at])
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(seq), pa.array(off)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """docs(doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset; and of the whole packing

    ``sequences_least`` (a bound: no packing needs fewer) and ``proved`` (whether this one is as small as any).
    """
    path = path or default_path()
    x = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    pieces = stage(x.mapInArrow(_cut(path, capacity), _PIECE), "pack-pieces")
    tasks = pieces.groupBy("length", "part").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    tasks = stage(tasks.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))), "pack-ranks")
    histogram = {r.length: r.n for r in tasks.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    packing = pack_lengths(histogram, capacity)
    plan = Plan(packing.patterns)
    x = pieces.join(tasks.drop("n").hint("merge"), ["length", "part"])  # the ranks grow with the tasks: never broadcast
    x = x.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("nth")).alias("rank"))
    x = x.mapInArrow(_place(plan), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
    return x.withColumn("sequences_least", F.lit(packing.bound)).withColumn("proved", F.lit(packing.proved))


def op2_packing(spark, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents").select("doc_id", "text"))
