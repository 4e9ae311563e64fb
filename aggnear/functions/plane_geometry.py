"""Quadrants, cells and dominance of the plane, in numpy for workers."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .profile import Axis, Group

#: quad -> (sign on x, sign on y); a coordinate is on the + side only if it is above the anchor.
QUADS = {1: (1, 1), 2: (-1, 1), 3: (-1, -1), 4: (1, -1)}


def quad_of(x, y, ax: int, ay: int) -> np.ndarray:
    right, up = np.asarray(x) > ax, np.asarray(y) > ay
    return np.where(up, np.where(right, 1, 2), np.where(right, 4, 3))


@dataclass(frozen=True)
class Frame:
    """A quadrant's own coordinates: both axes turned so that the search starts at small values.

    Nearest: away from the anchor. Farthest: from the far corner (the largest values) inwards.
    """

    sx: int
    sy: int
    ox: int
    oy: int
    farthest: bool

    @classmethod
    def of(cls, group: Group, quad: int, direction: str, far: tuple[int, int] = (0, 0)) -> "Frame":
        (sx, sy), (ax, ay) = QUADS[quad], group.anchor
        if direction == "nearest":
            return cls(sx, sy, -sx * ax, -sy * ay, False)
        return cls(-sx, -sy, sx * far[0], sy * far[1], True)

    def __call__(self, x, y):
        return self.sx * np.asarray(x, np.int64) + self.ox, self.sy * np.asarray(y, np.int64) + self.oy

    def axes(self, group: Group) -> tuple[Axis, Axis]:
        u, v = self(group.qx, group.qy)
        return Axis.of(u, group.w), Axis.of(v, group.w)


def narrowed(c: np.ndarray, lines: np.ndarray, flat: tuple[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Coordinates and lines with the stretch ``flat`` taken out: what lies on it falls together."""
    lo, hi = flat
    put = lambda x: np.where(x <= lo, x, np.maximum(x - (hi - lo), lo))
    return put(c), np.unique(put(lines))


def minimal(u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Mask of the points that no other dominates."""
    n = len(u)
    out = np.zeros(n, bool)
    if not n:
        return out
    order = np.lexsort((v, u))
    su, sv = u[order], v[order]
    before = np.r_[np.iinfo(np.int64).max, np.minimum.accumulate(sv)[:-1]]
    new = np.r_[True, (su[1:] != su[:-1]) | (sv[1:] != sv[:-1])]
    first = np.maximum.accumulate(np.where(new, np.arange(n), 0))  # a twin shares its first one's fate
    out[order] = (sv < before)[first]
    return out


def band(u: np.ndarray, v: np.ndarray, k: int) -> np.ndarray:
    """Mask of the points that fewer than k others dominate."""
    from bisect import bisect_right, insort

    order = np.lexsort((v, u))
    out, seen = np.zeros(len(u), bool), []
    i = 0
    while i < len(order):
        j = i
        while j < len(order) and u[order[j]] == u[order[i]] and v[order[j]] == v[order[i]]:
            j += 1
        above = bisect_right(seen, int(v[order[i]]))
        out[order[i:j]] = above < k
        if above < k:  # what k points dominate adds nothing: its own dominators cover what it dominates
            for _ in range(j - i):
                insort(seen, int(v[order[i]]))
        i = j
    return out
