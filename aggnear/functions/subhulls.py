"""Hulls of stretches of a path of points, and the best point of any stretch under a linear function.

The points stand in a fixed order (of height). Hulls are kept for aligned blocks of points whose sizes
are powers of two; which sizes are kept is the trade of space against search time:

* ``dyadic_full``: every size (the earlier structure: a hull in every subtree);
* ``fast``: sizes whose level is 0, 1, 2, 4, 8, .. above the leaves: lglg many;
* ``middle``: every fourth level;
* ``small``: the leaves alone.

A stretch is the union of the largest kept blocks inside it and single points at its ends. On a
hull the best vertex is found by binary search, as the values along a hull chain first fall, then rise.
"""

from __future__ import annotations

import numpy as np

#: Points of a leaf block.
LEAF = 8


def kept_levels(mode: str, top: int) -> list[int]:
    """Levels (0: leaves) from 0 to top at which a layout keeps hulls."""
    if mode == "dyadic_full":
        return list(range(top + 1))
    if mode == "fast":
        return [0, *[1 << i for i in range(max(0, top).bit_length()) if 1 << i <= top]]
    if mode == "middle":
        return list(range(0, top + 1, 4))
    if mode == "small":
        return [0]
    raise ValueError(f"no layout {mode!r}")


def lower_chain(points: list[tuple[int, int, int]], turn: int) -> list[tuple[int, int, int]]:
    """Lower (turn 1) or upper (-1) hull chain of (u, v, index) sorted by u, then turn * v; the first of each u counts, points on an edge are kept."""
    out: list[tuple[int, int, int]] = []
    for p in points:
        if out and out[-1][0] == p[0]:
            continue
        while len(out) > 1 and turn * ((out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0])) < 0:
            out.pop()
        out.append(p)
    return out


class SubHulls:
    """Points of one cell in order of height; ``f`` is linear on them, ``names`` break ties."""

    def __init__(self, u, v, f, names: list[tuple], mode: str = "fast"):
        self.u, self.v, self.f, self.names = u.tolist(), v.tolist(), f.tolist(), names
        blocks = max(1, -(-len(self.u) // LEAF))
        self.levels = kept_levels(mode, (blocks - 1).bit_length())
        self.made: dict = {}
        self.runs = self.looked = 0
        self.rising = self._rising()

    def _rising(self) -> int:
        """1 if the function grows with v (its best points are on lower chains), -1 if it falls."""
        v, f, u = self.v, self.f, self.u
        by_u: dict = {}
        for a, b, c in zip(u, v, f):
            if a in by_u and by_u[a][0] != b:
                return 1 if (c - by_u[a][1]) * (b - by_u[a][0]) >= 0 else -1
            by_u.setdefault(a, (b, c))
        return 0  # no two points above each other: both chains are looked at

    def hull(self, level: int, block: int) -> list[list[int]]:
        """Chains of a block as indices, made from those of the kept blocks below it."""
        key = level, block
        if key not in self.made:
            below = [x for x in self.levels if x < level]
            if below:
                step = 1 << (level - below[-1])
                inside = sorted({i for b in range(block * step, (block + 1) * step) if (b << below[-1]) * LEAF < len(self.u) for chain in self.hull(below[-1], b) for i in chain})
            else:
                inside = range(block * LEAF << level, min(len(self.u), (block + 1) * LEAF << level))
            out = []
            for turn in (1, -1):
                if self.rising != -turn:
                    pts = sorted(((self.u[i], self.v[i], i) for i in inside), key=lambda p: (p[0], turn * p[1], self.names[p[2]]))
                    out.append([i for _, _, i in lower_chain(pts, turn)])
            self.made[key] = out
        return self.made[key]

    def size(self) -> int:
        """Vertices that are kept, all blocks made."""
        for level in self.levels:
            for block in range(-(-len(self.u) // (LEAF << level))):
                self.hull(level, block)
        return sum(len(c) for chains in self.made.values() for c in chains)

    def extreme(self, chain: list[int]) -> int:
        """Index of the best point of a chain by (f, names): binary search, then along the vertices of equal value."""
        f, lo, hi = self.f, 0, len(chain) - 1
        while lo < hi:
            mid = (lo + hi) // 2
            self.looked += 1
            a, b = f[chain[mid]], f[chain[mid + 1]]
            if a <= b:
                hi = mid
            else:
                lo = mid + 1
        best, value = chain[lo], f[chain[lo]]
        for at, step in ((lo - 1, -1), (lo + 1, 1)):
            while 0 <= at < len(chain) and f[chain[at]] <= value:
                self.looked += 1
                if (f[chain[at]], self.names[chain[at]]) < (f[best], self.names[best]):
                    best = chain[at]
                at += step
        return best

    def best(self, lo: int, hi: int) -> int:
        """Index of the best point of the stretch [lo, hi)."""
        self.runs = self.looked = 0
        found, at = -1, lo

        def take(i):
            nonlocal found
            if found < 0 or (self.f[i], self.names[i]) < (self.f[found], self.names[found]):
                found = i

        while at < hi:
            level = next((x for x in reversed(self.levels) if at % (LEAF << x) == 0 and at + (LEAF << x) <= hi), None)
            if level is None:
                self.looked += 1
                take(at)
                at += 1
                continue
            self.runs += 1
            for chain in self.hull(level, at // (LEAF << level)):
                take(self.extreme(chain))
            at += LEAF << level
        return found
