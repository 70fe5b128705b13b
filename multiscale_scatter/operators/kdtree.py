"""Space partition by medians: a binary tree of splits, alternating between the axes.

`build_kdtree` takes medians of a bounded sketch, which is enough to balance the leaves of a layout;
`build_exact` takes them of all rows, one depth after the other, for any number of rows.

Left of a split are the values below it.  Where a median would leave one side empty the next distinct
value is tried, then the other axis; equal points stay together in one leaf, however many they are.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..plans.materialize import discard, materialize

#: Rows of the sketch from which a tree is built; the driver never sees more.
SKETCH_ROWS = 200_000


@dataclass
class Split:
    axis: int
    value: float
    left: int | Split
    right: int | Split
    depth: int
    number: int = 0
    #: Leaves below: first to middle - 1 on the left, middle to end - 1 on the right.
    first: int = 0
    middle: int = 0
    end: int = 0


@dataclass
class KDTree:
    root: int | Split
    leaves: int
    splits: list[Split] = field(default_factory=list)

    @property
    def depth(self) -> int:
        return max((s.depth + 1 for s in self.splits), default=0)

    def leaf(self, x: Column, y: Column) -> Column:
        """Leaf number as one expression; for trees of a few hundred leaves."""

        def walk(node: int | Split) -> Column:
            if not isinstance(node, Split):
                return F.lit(node)
            return F.when((x if node.axis == 0 else y) < F.lit(node.value), walk(node.left)).otherwise(walk(node.right))

        return walk(self.root)

    def leaf_of(self, xs: np.ndarray, ys: np.ndarray) -> np.ndarray:
        out = np.zeros(len(xs), np.int64)

        def walk(node: int | Split, rows: np.ndarray) -> None:
            if not isinstance(node, Split):
                out[rows] = node
                return
            below = (xs if node.axis == 0 else ys)[rows] < node.value
            walk(node.left, rows[below])
            walk(node.right, rows[~below])

        walk(self.root, np.arange(len(xs)))
        return out

    def leaves_meeting(self, x0: float, y0: float, x1: float, y1: float) -> list[int]:
        """Leaves whose points can lie in the closed rectangle."""
        out: list[int] = []
        stack = [self.root]
        while stack:
            node = stack.pop()
            if not isinstance(node, Split):
                out.append(node)
                continue
            lo, hi = (x0, x1) if node.axis == 0 else (y0, y1)
            if lo < node.value:
                stack.append(node.left)
            if hi >= node.value:
                stack.append(node.right)
        return sorted(out)

    def path(self, leaf: int) -> list[Split]:
        """Splits above a leaf, the root first."""
        out, node = [], self.root
        while isinstance(node, Split):
            out.append(node)
            node = node.left if leaf < node.middle else node.right
        return out

    def splits_over(self, low: int, high: int, depths: range) -> list[Split]:
        """Splits of some depths with leaves between low and high below them, deepest first."""
        out, stack = [], [self.root]
        while stack:
            node = stack.pop()
            if isinstance(node, Split) and node.first <= high and node.end > low and node.depth < depths.stop:
                if node.depth in depths:
                    out.append(node)
                stack += [node.left, node.right]
        return sorted(out, key=lambda s: (-s.depth, s.first))

    def paths(self) -> list[list[Split]]:
        """Splits above each leaf, the root first."""
        out: list[list[Split]] = [[] for _ in range(self.leaves)]

        def walk(node: int | Split, path: list[Split]) -> None:
            if isinstance(node, Split):
                walk(node.left, [*path, node])
                walk(node.right, [*path, node])
            else:
                out[node] = path

        walk(self.root, [])
        return out

    def boxes(self) -> list[tuple[float, float, float, float]]:
        """x0, y0, x1, y1 of each leaf's region, infinite at the rim."""
        out = [(0.0, 0.0, 0.0, 0.0)] * self.leaves

        def walk(node: int | Split, box: tuple[float, float, float, float]) -> None:
            if not isinstance(node, Split):
                out[node] = box
                return
            x0, y0, x1, y1 = box
            if node.axis == 0:
                walk(node.left, (x0, y0, node.value, y1))
                walk(node.right, (node.value, y0, x1, y1))
            else:
                walk(node.left, (x0, y0, x1, node.value))
                walk(node.right, (x0, node.value, x1, y1))

        inf = float("inf")
        walk(self.root, (-inf, -inf, inf, inf))
        return out


def _cut(values: np.ndarray) -> float | None:
    """A value that leaves something below it and something at or above it."""
    ordered = np.sort(values)
    middle = ordered[len(ordered) // 2]
    if ordered[0] < middle:
        return float(middle)
    above = ordered[ordered > middle]
    return float(above[0]) if len(above) else None


def build(points: np.ndarray, most: int, weight: float = 1.0, first_axis: int = 0) -> KDTree:
    """points (n x 2), each standing for `weight` objects; splits until a leaf has at most `most` objects."""
    tree = KDTree(0, 0)

    def grow(rows: np.ndarray, axis: int, depth: int) -> int | Split:
        if len(rows) * weight > most and len(rows) > 1:
            for a in (axis, 1 - axis):
                value = _cut(points[rows, a])
                if value is not None:
                    below = points[rows, a] < value
                    split = Split(a, value, 0, 0, depth, first=tree.leaves)
                    split.left = grow(rows[below], 1 - a, depth + 1)
                    split.middle = tree.leaves
                    split.right = grow(rows[~below], 1 - a, depth + 1)
                    split.end = tree.leaves
                    tree.splits.append(split)
                    return split
        tree.leaves += 1
        return tree.leaves - 1

    tree.root = grow(np.arange(len(points)), first_axis, 0)
    tree.splits.sort(key=lambda s: s.depth)
    for k, s in enumerate(tree.splits):
        s.number = k
    return tree


def build_kdtree(objects: DataFrame, most: int, sketch_rows: int = SKETCH_ROWS, count: int | None = None) -> KDTree:
    """From objects(obj_id, x, y).  Exact if they fit into the sketch, else from a sample picked by a hash of the id."""
    total = objects.count() if count is None else count
    share = min(1.0, sketch_rows / max(total, 1))
    picked = objects
    if share < 1:
        picked = objects.where(F.pmod(F.xxhash64("obj_id"), F.lit(1 << 30)) < int(share * (1 << 30)))
    rows = picked.select("obj_id", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y")).limit(2 * sketch_rows).toPandas()
    rows = rows.sort_values(["x", "y", "obj_id"])
    points = rows[["x", "y"]].to_numpy(float)
    return build(points, most, total / max(len(points), 1))


def _value_at(rows: DataFrame, column: str, ranks: dict[int, int]) -> dict[int, tuple[float, float]]:
    """For each node its least value, and the value at a rank (from 0) in order; rows(node, x, y).

    Values are counted and dealt by ranges of (node, value); how many each task holds of a node tells in which
    task the rank falls, so no task sorts a node and only those sums reach the driver.
    """
    spark = rows.sparkSession
    wanted = F.broadcast(spark.createDataFrame([(n,) for n in ranks], "node long"))
    counted = rows.join(wanted, "node").groupBy("node", F.col(column).alias("c")).agg(F.count(F.lit(1)).alias("n"))
    dealt = materialize(counted.repartitionByRange("node", "c").withColumn("part", F.spark_partition_id()), "values")
    sums = dealt.groupBy("node", "part").agg(F.sum("n").alias("n"), F.min("c").alias("lo")).collect()
    low: dict[int, float] = {}
    targets = []
    of_node: dict[int, list] = {}
    for r in sorted(sums, key=lambda r: r["part"]):
        of_node.setdefault(r["node"], []).append(r)
    for node, rank in ranks.items():
        before = 0
        for r in of_node.get(node, ()):
            low[node] = min(low.get(node, r["lo"]), r["lo"])
            if before <= rank < before + r["n"]:
                targets.append((node, r["part"], rank - before))
            before += r["n"]
    place = F.broadcast(spark.createDataFrame(targets, "node long, part int, at long"))
    until = W.partitionBy("node", "part").orderBy("c").rowsBetween(W.unboundedPreceding, 0)
    found = dealt.join(place, ["node", "part"]).withColumn("upto", F.sum("n").over(until)).where((F.col("at") < F.col("upto")) & (F.col("at") >= F.col("upto") - F.col("n")))
    out = {r["node"]: (low[r["node"]], r["c"]) for r in found.select("node", "c").collect()}
    discard(dealt)
    return out


def _cuts(rows: DataFrame, axis: dict[int, int], sizes: dict[int, int]) -> dict[int, float]:
    """Where each node is cut along its axis; nodes whose values are all one are left out."""
    out: dict[int, float] = {}
    for a, column in enumerate("xy"):
        ranks = {n: sizes[n] // 2 for n, k in axis.items() if k == a}
        if not ranks:
            continue
        found = _value_at(rows, column, ranks)
        out |= {n: m for n, (lo, m) in found.items() if lo < m}
        low = [(n, m) for n, (lo, m) in found.items() if lo == m]
        if low:
            above = rows.join(F.broadcast(rows.sparkSession.createDataFrame(low, "node long, m double")), "node").where(F.col(column) > F.col("m"))
            out |= {r["node"]: r["c"] for r in above.groupBy("node").agg(F.min(column).alias("c")).collect()}
    return out


def build_exact(objects: DataFrame, most: int, first_axis: int = 0, turns: int | None = None) -> KDTree:
    """The tree that `build` makes of all objects(x, y): exact medians, every depth by a few jobs over all rows.

    With turns the axes take so many turns in all, x and y one after the other; a node that its axis cannot cut
    waits for the next turn.  Ties at a median make sides of unequal size, which would else be cut once more.
    """
    rows = materialize(objects.select(F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), F.lit(1).cast("long").alias("node")), "points")
    axis = {1: first_axis}
    cut: dict[int, tuple[int, float]] = {}
    taken = 0
    while axis and taken != turns:
        taken += 1
        sizes = {r["node"]: r["count"] for r in rows.groupBy("node").count().collect()}
        axis = {n: a for n, a in axis.items() if sizes.get(n, 0) > max(most, 1)}
        if not axis:
            break
        found = {n: (axis[n], v) for n, v in _cuts(rows, axis, sizes).items()}
        other = {n: 1 - a for n, a in axis.items() if n not in found}
        waiting, other = (other, {}) if turns is not None else ({}, other)
        found |= {n: (other[n], v) for n, v in (_cuts(rows, other, sizes) if other else {}).items()}
        cut |= found
        if not found:
            axis = waiting
            continue
        table = F.broadcast(rows.sparkSession.createDataFrame([(n, a, float(v)) for n, (a, v) in found.items()], "node long, axis int, v double"))
        below = F.when(F.col("axis") == 0, F.col("x")).otherwise(F.col("y")) < F.col("v")
        moved = rows.join(table, "node", "left").select("x", "y", F.when(F.col("v").isNull(), F.col("node")).otherwise(F.col("node") * 2 + F.when(below, 0).otherwise(1)).alias("node"))
        before, rows = rows, materialize(moved, "points")
        discard(before)
        axis = {2 * n + k: 1 - a for n, (a, _) in found.items() for k in (0, 1)} | waiting
    discard(rows)
    tree = KDTree(0, 0)

    def grow(node: int, depth: int) -> int | Split:
        if node not in cut:
            tree.leaves += 1
            return tree.leaves - 1
        split = Split(*cut[node], 0, 0, depth, first=tree.leaves)
        split.left = grow(2 * node, depth + 1)
        split.middle = tree.leaves
        split.right = grow(2 * node + 1, depth + 1)
        split.end = tree.leaves
        tree.splits.append(split)
        return split

    tree.root = grow(1, 0)
    tree.splits.sort(key=lambda s: s.depth)
    for k, s in enumerate(tree.splits):
        s.number = k
    return tree


def tree_rows(tree: KDTree) -> list[tuple]:
    """(split, depth, axis, value, leaves below) for reports."""
    return [(s.number, s.depth, "xy"[s.axis], s.value, s.end - s.first) for s in tree.splits]
