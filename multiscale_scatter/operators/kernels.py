"""Kernels on arrays: the placing of marks of one level, the repair along a split, and hulls.

Rows come in order of importance.  Places are in units of the mark box (x / width, y / height), so the
distance of two marks is the larger of their coordinate differences.
"""

from __future__ import annotations

import math

import numpy as np


def place_with_grid(u: np.ndarray, v: np.ndarray, theta: float) -> np.ndarray:
    """Row that each row merges into; its own number if it is placed.

    Cells have side theta.  Two placed marks are never closer than theta, so a cell holds one at most and
    any mark closer than theta lies in one of nine cells.
    """
    n = len(u)
    into = np.arange(n)
    if theta <= 0:
        return into
    cells: dict[tuple[int, int], int] = {}
    cu, cv = np.floor(u / theta).astype(np.int64).tolist(), np.floor(v / theta).astype(np.int64).tolist()
    us, vs = u.tolist(), v.tolist()
    around = [(a, b) for a in (0, -1, 1) for b in (0, -1, 1)]
    get = cells.get
    for i in range(n):
        x, y, a, b = us[i], vs[i], cu[i], cv[i]
        best, to = theta, -1
        for da, db in around:
            j = get((a + da, b + db))
            if j is not None:
                d = max(abs(x - us[j]), abs(y - vs[j]))
                if d < best or (d == best and to >= 0 and j < to):
                    best, to = d, j
        if to < 0:
            cells[(a, b)] = i
        else:
            into[i] = to
    return into


def place_with_scan(u: np.ndarray, v: np.ndarray, theta: float) -> np.ndarray:
    """The same by looking at every placed mark."""
    into = np.arange(len(u))
    kept: list[int] = []
    for i in range(len(u)):
        if kept and theta > 0:
            at = np.array(kept)
            d = np.maximum(np.abs(u[at] - u[i]), np.abs(v[at] - v[i]))
            k = int(np.argmin(d))  # the first of equals is the most important
            if d[k] < theta:
                into[i] = at[k]
                continue
        kept.append(i)
    return into


def place_with_tree(u: np.ndarray, v: np.ndarray, theta: float) -> np.ndarray:
    """The same with a search tree that grows with the placed marks, split by x and y in turn."""
    into = np.arange(len(u))
    point, left, right = [], [], []
    for i in range(len(u)):
        here = (float(u[i]), float(v[i]))
        best, to = theta, -1
        if point and theta > 0:
            stack = [(0, 0)]
            while stack:
                node, axis = stack.pop()
                j = point[node]
                d = max(abs(here[0] - u[j]), abs(here[1] - v[j]))
                if d < best or (d == best and to >= 0 and j < to):
                    best, to = d, j
                gap = here[axis] - (u[j], v[j])[axis]
                near, far = (left[node], right[node]) if gap < 0 else (right[node], left[node])
                if far >= 0 and abs(gap) <= best:
                    stack.append((far, 1 - axis))
                if near >= 0:
                    stack.append((near, 1 - axis))
        if to >= 0:
            into[i] = to
            continue
        point.append(i)
        left.append(-1)
        right.append(-1)
        if len(point) > 1:
            node, axis = 0, 0
            while True:
                j = point[node]
                side = left if here[axis] < (u[j], v[j])[axis] else right
                if side[node] < 0:
                    side[node] = len(point) - 1
                    break
                node, axis = side[node], 1 - axis
    return into


PLACERS = {"grid": place_with_grid, "scan": place_with_scan, "tree": place_with_tree}


def place_levels(u: np.ndarray, v: np.ndarray, theta: float, levels: int, zoom: float, index: str = "grid", top: int = 1):
    """For each level from the bottom to `top`: (level, rows that come in, rows they merge into).

    u and v are places on the bottom level.
    """
    alive = np.arange(len(u))
    place = PLACERS[index]
    for level in range(levels, top - 1, -1):
        scale = zoom ** (level - levels)
        into = place(u[alive] * scale, v[alive] * scale, theta)
        yield level, alive, alive[into]
        alive = alive[into == np.arange(len(alive))]


def sweep_split(along: np.ndarray, across: np.ndarray, rank: np.ndarray, theta: float) -> np.ndarray:
    """Repair of the rows near a split: the row that each merges into, its own number if it stays.

    Rows are taken in order along the split (ties by importance) and compared with the last one that
    stands; of a pair that is too close the less important goes.
    """
    into = np.arange(len(along))
    last = -1
    for i in np.lexsort((rank, along)).tolist():
        if last >= 0 and max(abs(along[i] - along[last]), abs(across[i] - across[last])) < theta:
            if rank[i] < rank[last]:
                into[last] = i
                last = i
            else:
                into[i] = last
        else:
            last = i
    return settle(into)


def settle(into: np.ndarray) -> np.ndarray:
    """Follows merges to the row that stands at last."""
    while True:
        further = into[into]
        if (further == into).all():
            return into
        into = further


def convex_hull(points: np.ndarray) -> np.ndarray:
    """Corners of the hull, counter-clockwise from the lowest x; corners on an edge are left out."""
    points = np.unique(np.asarray(points, float).reshape(-1, 2), axis=0)
    if len(points) < 3:
        return points

    def chain(order: np.ndarray) -> list:
        out: list = []
        for p in order:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0]) <= 0:
                out.pop()
            out.append(p)
        return out[:-1]

    return np.array(chain(points) + chain(points[::-1]))


def polygon_area(corners: np.ndarray) -> float:
    if len(corners) < 3:
        return 0.0
    x, y = corners[:, 0], corners[:, 1]
    return abs(float(np.dot(x, np.roll(y, -1)) - np.dot(y, np.roll(x, -1)))) / 2


def tree_depth(parts: int) -> int:
    return max(0, math.ceil(math.log2(max(parts, 1))))
