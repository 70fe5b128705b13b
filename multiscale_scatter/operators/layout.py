"""Multi-level layouts: which objects stand for clusters on which zoom level.

Every layout is a table of edges (level, child, parent): the clusters of the level below (on the bottom
level: the objects) and the cluster of this level that they merge into; a cluster that stays is its own
parent.  A cluster is named by its representative object, its most important one.  Ties of importance go
to the smaller id, so the order is total.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions import geometry as G
from ..plans.materialize import discard, materialize
from . import kdtree, kernels

EDGES = "level int, child long, parent long"
#: Trees up to this many leaves become one expression; larger ones are looked up in batches.
EXPRESSION_LEAVES = 256


@dataclass(frozen=True)
class LayoutPlan:
    x_extent: tuple[float, float]
    y_extent: tuple[float, float]
    theta: float = 1.0
    box: tuple[float, float] = (100.0, 100.0)
    top: tuple[float, float] = (1000.0, 1000.0)
    levels: int = 6
    zoom: float = 2.0
    descending: bool = True
    #: Objects that one task can hold.
    mem_cap: int = 2_000_000

    def capacity(self, level: int) -> int:
        return G.level_capacity(*(G.level_size(s, self.zoom, level) for s in self.top), *self.box, self.theta)

    def with_(self, **changes) -> LayoutPlan:
        return replace(self, **changes)


@dataclass
class Layout:
    plan: LayoutPlan
    objects: DataFrame
    edges: DataFrame
    tree: kdtree.KDTree | None = None
    #: Levels that were placed in a single task, for reports.
    single_levels: tuple[int, ...] = ()
    #: Seconds by phase: tree, redistribution, clustering, boundary, top.
    phases: dict[str, float] = field(default_factory=dict)
    #: Whether some objects share an id; the edges name an id once, the statistics count each of its objects.
    shared_ids: bool = False

    def visible(self, level: int | None = None) -> DataFrame:
        """(level, cluster_id) of the marks."""
        rows = self.edges.where("child = parent").select("level", F.col("child").alias("cluster_id"))
        return rows if level is None else rows.where(F.col("level") == level)

    def marks(self, level: int | None = None) -> DataFrame:
        """visible with raw and pixel places: level, cluster_id, x, y, z, cx, cy."""
        p = self.plan
        places = self.objects.select(F.col("obj_id").alias("cluster_id"), "x", "y", "z")
        if self.shared_ids:  # the object that stands for its id
            first = F.min(F.struct(_weight(p), "x", "y", "z")).alias("m")
            places = places.groupBy("cluster_id").agg(first).select("cluster_id", "m.x", "m.y", "m.z")
        scale = F.pow(F.lit(float(p.zoom)), F.col("level") - p.levels)
        px = G.to_level(F.col("x"), *p.x_extent, p.top[0], p.zoom, p.levels) * scale
        py = G.to_level(F.col("y"), *p.y_extent, p.top[1], p.zoom, p.levels) * scale
        return self.visible(level).join(places, "cluster_id").select("level", "cluster_id", "x", "y", "z", px.alias("cx"), py.alias("cy"))

    def members(self, level: int) -> DataFrame:
        """(obj_id, cluster_id): the cluster of each object on a level."""
        current = self.edges.where(F.col("level") == self.plan.levels).select(F.col("child").alias("obj_id"), F.col("parent").alias("cluster_id"))
        for k in range(self.plan.levels - 1, level - 1, -1):
            step = self.edges.where(F.col("level") == k).select(F.col("child").alias("cluster_id"), "parent")
            current = current.join(step, "cluster_id").select("obj_id", F.col("parent").alias("cluster_id"))
        return current


def prepare(objects: DataFrame, plan: LayoutPlan, outside: str = "drop") -> DataFrame:
    """objects(obj_id, x, y, z, ...) with finite places, inside the extents, importance last if null."""
    x, y = F.col("x").cast("double"), F.col("y").cast("double")
    good = x.isNotNull() & y.isNotNull() & ~F.isnan(x) & ~F.isnan(y)
    if outside == "drop":
        good = good & x.between(*plan.x_extent) & y.between(*plan.y_extent)
    return objects.where(good).withColumns({"x": x, "y": y, "z": F.col("z").cast("double")})


def _units(plan: LayoutPlan) -> tuple[Column, Column]:
    """Places on the bottom level in units of the mark box."""
    return tuple(
        (G.to_level(F.col(c), *e, plan.top[k], plan.zoom, plan.levels) / plan.box[k]).alias("uv"[k])
        for k, (c, e) in enumerate((("x", plan.x_extent), ("y", plan.y_extent)))
    )


def _weight(plan: LayoutPlan) -> Column:
    """w: smaller is more important; objects without importance come last."""
    worst = F.lit(float("inf"))
    return F.when(F.col("z").isNull() | F.isnan("z"), worst).otherwise(-F.col("z") if plan.descending else F.col("z")).alias("w")


def _keyed(objects: DataFrame, plan: LayoutPlan) -> DataFrame:
    return objects.select("obj_id", *_units(plan), _weight(plan))


def _by_importance(pdf: pd.DataFrame) -> pd.DataFrame:
    return pdf.sort_values(["w", "obj_id"], kind="stable").reset_index(drop=True)


def _all_levels(plan: LayoutPlan, first: int, index: str):
    """Kernel for one task: all levels from `first` to the top."""
    scale = plan.zoom ** (first - plan.levels)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = _by_importance(pdf)
        ids = pdf["obj_id"].to_numpy(np.int64)
        parts = [
            pd.DataFrame({"level": level, "child": ids[a], "parent": ids[b]})
            for level, a, b in kernels.place_levels(pdf["u"].to_numpy() * scale, pdf["v"].to_numpy() * scale, plan.theta, first, plan.zoom, index)
        ]
        return pd.concat(parts).astype({"level": "int32"}) if parts else pd.DataFrame({"level": [], "child": [], "parent": []})

    return run


def layout_single(objects: DataFrame, plan: LayoutPlan, index: str = "grid") -> Layout:
    """All levels in one task; the reference for the others, and the way for levels that fit into memory."""
    objects = prepare(objects, plan)
    edges = _keyed(objects, plan).groupBy(F.lit(0).alias("one")).applyInPandas(_all_levels(plan, plan.levels, index), EDGES)
    return Layout(plan, objects, materialize(edges, "edges"), single_levels=tuple(range(1, plan.levels + 1)))


def _neighbours(rows: DataFrame, others: DataFrame, theta: float) -> DataFrame:
    """Pairs of rows(id, u, v, w) and others(...) closer than theta; others' columns end in 2."""
    cell = lambda c: F.floor(F.col(c) / theta)
    steps = F.array(*(F.lit(k) for k in (-1, 0, 1)))
    spread = rows.withColumn("dx", F.explode(steps)).withColumn("dy", F.explode(steps))
    spread = spread.withColumn("a", cell("u") + F.col("dx")).withColumn("b", cell("v") + F.col("dy")).drop("dx", "dy")
    there = others.select(*(F.col(c).alias(f"{c}2") for c in ("obj_id", "u", "v", "w")), cell("u").alias("a2"), cell("v").alias("b2"))
    near = F.greatest(F.abs(F.col("u") - F.col("u2")), F.abs(F.col("v") - F.col("v2")))
    return spread.join(there.hint("merge"), (F.col("a") == F.col("a2")) & (F.col("b") == F.col("b2")) & (near < theta)).withColumn("d", near)


_BEFORE = "w2 < w or (w2 = w and obj_id2 < obj_id)"


def _first_of_places(rows: DataFrame) -> DataFrame:
    """The most important of rows(obj_id, u, v, w) at each place; no other can stand beside it."""
    return rows.groupBy("u", "v").agg(F.min(F.struct("w", "obj_id")).alias("m")).select("m.obj_id", "u", "v", "m.w")


#: Cells of theta along a tile's side, and rows of a tile that one task takes in one round.
TILE, TILE_ROWS = 128, 200_000
_PLACED = "obj_id long, u double, v double, w double"


def _decide_tile(theta: float):
    """Kernel for the undecided rows of a tile and those closer than theta to it, in order of importance.

    A row is placed if nothing before it is close; what is close to a placed one is out.  Rows around the tile may
    hang on others that the task doesn't see: unless they are out they stay open, and so does what is close to them.
    """
    around = [(a, b) for a in (0, -1, 1) for b in (0, -1, 1)]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = _by_importance(pdf)
        us, vs, home = pdf["u"].tolist(), pdf["v"].tolist(), pdf["home"].tolist()
        cu, cv = np.floor(pdf["u"].to_numpy() / theta).astype(np.int64).tolist(), np.floor(pdf["v"].to_numpy() / theta).astype(np.int64).tolist()
        placed: dict[tuple[int, int], int] = {}
        waiting: dict[tuple[int, int], list[int]] = {}
        chosen = []
        for i in range(len(us)):
            x, y = us[i], vs[i]
            cells = [(cu[i] + a, cv[i] + b) for a, b in around]
            if any((j := placed.get(c)) is not None and max(abs(x - us[j]), abs(y - vs[j])) < theta for c in cells):
                continue
            if not home[i] or any(max(abs(x - us[j]), abs(y - vs[j])) < theta for c in cells for j in waiting.get(c, ())):
                waiting.setdefault((cu[i], cv[i]), []).append(i)
                continue
            placed[(cu[i], cv[i])] = i
            chosen.append(i)
        return pdf.iloc[chosen][["obj_id", "u", "v", "w"]]

    return run


def _placed_in_rounds(rows: DataFrame, theta: float, max_rounds: int, places: bool = False) -> DataFrame:
    """Which rows(obj_id, u, v, w) are placed, one after the other by importance, if placed ones keep theta apart.

    Of the rows at one place only the first can be placed.  In each round tiles of the plane are worked off on
    their own, as far as their rows don't hang on open rows of other tiles; then what is close to a placed row is
    out.  The tiles lie otherwise in the next round, so a chain of rows costs a round for each tile that it
    crosses, not for each row.  A tile of more rows than a task takes is begun with the most important ones.
    Where all rows are no more than a task takes, they are one tile.  places: no two rows are at one place.
    """
    undecided = rows if places else materialize(_first_of_places(rows), "undecided")
    if undecided.count() <= TILE_ROWS:
        placed_at_once = undecided.withColumn("home", F.lit(True)).groupBy(F.lit(0).alias("one")).applyInPandas(_decide_tile(theta), _PLACED)
        out = materialize(placed_at_once, "placed")
        discard(undecided)
        return out
    placed: list[DataFrame] = []
    side = TILE * theta
    before = W.partitionBy("tu", "tv").orderBy("w", "obj_id")
    for k in range(max_rounds):
        shift = side / 2 * (k % 2)
        tile = lambda c, d: F.floor((F.col(c) + (shift + d * theta)) / side)  # noqa: E731, B023
        # every tile that a row's square of theta reaches; a hair more, so that rounding leaves none out
        ends = {c: F.sequence(tile(c, -1 - 1e-9), tile(c, 1 + 1e-9)) for c in "uv"}
        dealt = undecided.withColumn("tu", F.explode(ends["u"])).withColumn("tv", F.explode(ends["v"]))
        dealt = dealt.withColumn("home", (F.col("tu") == tile("u", 0)) & (F.col("tv") == tile("v", 0)))
        dealt = dealt.withColumn("place", F.row_number().over(before)).where(F.col("place") <= TILE_ROWS).drop("place")
        chosen = materialize(dealt.groupBy("tu", "tv").applyInPandas(_decide_tile(theta), _PLACED), "chosen")
        placed.append(chosen)
        covered = _neighbours(undecided, chosen, theta).select("obj_id").distinct().hint("merge")  # small as files, not as rows
        old, undecided = undecided, materialize(undecided.join(covered, "obj_id", "left_anti"), "undecided")
        discard(old)
        if undecided.isEmpty():
            out = placed[0]
            for more in placed[1:]:
                out = out.unionByName(more)
            out = materialize(out, "placed")
            discard(undecided, *placed)
            return out
    raise RuntimeError("not settled; use the distributed layout")


def layout_rounds(objects: DataFrame, plan: LayoutPlan, max_rounds: int = 200) -> Layout:
    """The same layout as one task makes, by DataFrame operations alone, however large the level.

    Each row that is not placed goes to the nearest placed row that is more important than itself.
    """
    objects = prepare(objects, plan)
    rows = materialize(_keyed(objects, plan), "rows")
    edges: DataFrame | None = None
    for level in range(plan.levels, 0, -1):
        if plan.theta <= 0:
            step = rows.select(F.lit(level).cast("int").alias("level"), F.col("obj_id").alias("child"), F.col("obj_id").alias("parent"))
            edges = step if edges is None else edges.unionByName(step)
            continue
        scale = plan.zoom ** (level - plan.levels)
        here = rows.withColumns({"u": F.col("u") * scale, "v": F.col("v") * scale})
        placed = _placed_in_rounds(here, plan.theta, max_rounds)
        out = here.join(placed.select("obj_id"), "obj_id", "left_anti")
        nearest = _neighbours(out, placed, plan.theta).where(_BEFORE).groupBy("obj_id").agg(F.min(F.struct("d", "w2", "obj_id2")).alias("m"))
        step = nearest.select(F.lit(level).cast("int").alias("level"), F.col("obj_id").alias("child"), F.col("m.obj_id2").alias("parent"))
        step = step.unionByName(placed.select(F.lit(level).cast("int").alias("level"), F.col("obj_id").alias("child"), F.col("obj_id").alias("parent")))
        step = materialize(step, f"edges-{level}")
        edges = step if edges is None else edges.unionByName(step)
        before, rows = rows, materialize(rows.join(placed.select("obj_id"), "obj_id", "left_semi"), "rows")
        discard(before)
    return Layout(plan, objects, edges)


def assign_leaf(rows: DataFrame, tree: kdtree.KDTree, x: str = "x", y: str = "y") -> DataFrame:
    """rows with pid, the leaf that holds their place."""
    if tree.leaves <= EXPRESSION_LEAVES:
        return rows.withColumn("pid", tree.leaf(F.col(x), F.col(y)).cast("int"))

    @F.pandas_udf("int")
    def leaf(xs: pd.Series, ys: pd.Series) -> pd.Series:
        return pd.Series(tree.leaf_of(xs.to_numpy(float), ys.to_numpy(float)))

    return rows.withColumn("pid", leaf(x, y))


class _Borders:
    """Splits of a tree in box units of one level: which rows are near them, and the repair.

    A task looks at the splits above its own leaves only, so its work doesn't grow with the tree.
    """

    def __init__(self, tree: kdtree.KDTree, plan: LayoutPlan, level: int):
        self.tree, self.theta = tree, plan.theta
        self.extents = (plan.x_extent, plan.y_extent)
        self.sizes = [G.level_size(plan.top[k], plan.zoom, level) / plan.box[k] for k in (0, 1)]

    def _from_split(self, split: kdtree.Split, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        lo, hi = self.extents[split.axis]
        return np.abs((u, v)[split.axis] - (split.value - lo) / (hi - lo) * self.sizes[split.axis])

    def near(self, u: np.ndarray, v: np.ndarray, leaf: int) -> np.ndarray:
        """Rows of one leaf that lie near a split above it."""
        out = np.zeros(len(u), bool)
        for split in self.tree.path(leaf):
            out |= self._from_split(split, u, v) < self.theta
        return out

    def repair(self, u: np.ndarray, v: np.ndarray, leaf: np.ndarray, rank: np.ndarray, depths: range) -> np.ndarray:
        """Row that each row merges into once the splits of these depths are closed, deepest first."""
        into = np.arange(len(u))
        if not len(u):
            return into
        for split in self.tree.splits_over(int(leaf.min()), int(leaf.max()), depths):
            alive = into == np.arange(len(u))
            near = np.flatnonzero(alive & (leaf >= split.first) & (leaf < split.end) & (self._from_split(split, u, v) < self.theta))
            along, across = (v, u) if split.axis == 0 else (u, v)
            into[near] = near[kernels.sweep_split(along[near], across[near], rank[near], self.theta)]
        return kernels.settle(into)


_LOCAL = "child long, parent long, u double, v double, w double, pid int, border boolean"


def _place_leaf(plan: LayoutPlan, scale: float, borders: _Borders, index: str):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = _by_importance(pdf)
        u, v = pdf["u"].to_numpy() * scale, pdf["v"].to_numpy() * scale
        into = kernels.PLACERS[index](u, v, plan.theta)
        ids = pdf["obj_id"].to_numpy(np.int64)
        stays = into == np.arange(len(into))
        border = np.zeros(len(into), bool)
        border[stays] = borders.near(u[stays], v[stays], int(pdf["pid"].iloc[0]))
        return pd.DataFrame({"child": ids, "parent": ids[into], "u": pdf["u"], "v": pdf["v"], "w": pdf["w"], "pid": pdf["pid"], "border": border})

    return run


def _close(scale: float, borders: _Borders, depths: range):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["w", "child"], kind="stable").reset_index(drop=True)
        ids = pdf["child"].to_numpy(np.int64)
        into = borders.repair(pdf["u"].to_numpy() * scale, pdf["v"].to_numpy() * scale, pdf["pid"].to_numpy(), np.arange(len(pdf)), depths)
        gone = into != np.arange(len(into))
        return pd.DataFrame({"loser": ids[gone], "winner": ids[into[gone]]})

    return run


def _ancestors(spark, tree: kdtree.KDTree, depth: int) -> DataFrame:
    """(pid, ancestor): the split of this depth above each leaf; leaves that are higher stand for themselves."""
    rows = [(k, path[depth].number if len(path) > depth else -1 - k) for k, path in enumerate(tree.paths())]
    return spark.createDataFrame(rows, "pid int, ancestor int")


def layout_distributed(
    objects: DataFrame,
    plan: LayoutPlan,
    tree: kdtree.KDTree | None = None,
    repair: bool = True,
    hybrid: bool = True,
    supernode_depth: int = 8,
    index: str = "grid",
) -> Layout:
    """Levels from the bottom up: leaves of a median tree in parallel, then repair along its splits.

    The tree is built once, over the bottom level.  Rows near no split are final after the first step.
    The repair closes whole subtrees of `supernode_depth` depths in one task, lowest first.  With hybrid,
    the rest is done by one task as soon as no input can exceed what one holds.

    Objects that share an id are one to the layout, at the place of the most important of them.
    """
    objects = prepare(objects, plan)
    spark = objects.sparkSession
    phases = dict.fromkeys(("tree", "redistribution", "clustering", "boundary", "top"), 0.0)
    clock = _Clock(phases)
    total = objects.count()
    tree = tree or kdtree.build_kdtree(objects.select("obj_id", "x", "y"), plan.mem_cap, count=total)
    clock.lap("tree")
    rows = assign_leaf(objects, tree).select("obj_id", "pid", *_units(plan), _weight(plan))
    rows = materialize(rows, "rows")
    rows, shared_ids = _one_for_each_id(rows)
    rows, copies = _without_copies(rows, plan)
    clock.lap("redistribution")
    edges: list[DataFrame] = []
    single: tuple[int, ...] = ()
    for level in range(plan.levels, 0, -1):
        # no more can come in than the level below holds; what did come in is known from its files
        if hybrid and (level < plan.levels and plan.capacity(level + 1) <= plan.mem_cap or rows.count() <= plan.mem_cap):
            last = rows.groupBy(F.lit(0).alias("one")).applyInPandas(_all_levels(plan, level, index), EDGES)
            edges.append(materialize(last, "edges-top"))
            single = tuple(range(1, level + 1))
            clock.lap("top")
            break
        scale = plan.zoom ** (level - plan.levels)
        borders = _Borders(tree, plan, level)
        local = materialize(rows.groupBy("pid").applyInPandas(_place_leaf(plan, scale, borders, index), _LOCAL), f"local-{level}")
        clock.lap("clustering")
        step = local.select("child", "parent")
        gone: DataFrame | None = None
        tables = []
        if repair and tree.splits and plan.theta > 0:
            live = local.where("border")
            for low in range(((tree.depth - 1) // supernode_depth) * supernode_depth, -1, -supernode_depth):
                depths = range(low, low + supernode_depth)
                grouped = live.join(F.broadcast(_ancestors(spark, tree, low)), "pid")
                merged = materialize(grouped.groupBy("ancestor").applyInPandas(_close(scale, borders, depths), "loser long, winner long"), f"merged-{level}-{low}")
                tables.append(merged)
                live = live.join(merged, live["child"] == merged["loser"], "left_anti")
                if gone is None:
                    gone = merged
                else:  # winners of a lower round may lose in a higher one
                    later = merged.select(F.col("loser").alias("winner"), F.col("winner").alias("to"))
                    gone = gone.join(later, "winner", "left").select("loser", F.coalesce("to", "winner").alias("winner")).unionByName(merged)
            step = step.join(gone, step["parent"] == gone["loser"], "left").select("child", F.coalesce("winner", "parent").alias("parent"))
        step = materialize(step.select(F.lit(level).cast("int").alias("level"), "child", "parent"), f"edges-{level}")
        edges.append(step)
        stays = step.where("child = parent").select("child")
        below, rows = rows, materialize(local.join(stays, "child", "left_semi").select(F.col("child").alias("obj_id"), "pid", "u", "v", "w"), f"rows-{level}")
        discard(local, below, *tables)
        clock.lap("boundary")
    if copies is not None:  # a copy goes where what stands for it goes on the bottom level
        bottom = edges[0].where(F.col("level") == plan.levels).select(F.col("child").alias("first"), "parent")
        edges.append(materialize(copies.join(bottom, "first").select(F.lit(plan.levels).cast("int").alias("level"), F.col("obj_id").alias("child"), "parent"), "edges-copies"))
    discard(rows)
    out = edges[0]
    for e in edges[1:]:
        out = out.unionByName(e)
    return Layout(plan, objects, out, tree, single, phases, shared_ids)


def _one_for_each_id(rows: DataFrame) -> tuple[DataFrame, bool]:
    """(rows, whether objects share ids): of the objects with one id the most important one.

    Edges are joined by id, so two edges of an id would count each of its objects twice.
    """
    shared = materialize(rows.groupBy("obj_id").count().where("count > 1").select("obj_id"), "shared-ids")
    if shared.isEmpty():
        discard(shared)
        return rows, False
    firsts = rows.join(shared, "obj_id", "left_semi").groupBy("obj_id").agg(F.min(F.struct("w", "u", "v", "pid")).alias("m"))
    out = rows.join(shared, "obj_id", "left_anti").unionByName(firsts.select("obj_id", "m.pid", "m.u", "m.v", "m.w"))
    out = materialize(out, "rows")
    discard(rows, shared)
    return out, True


def _without_copies(rows: DataFrame, plan: LayoutPlan) -> tuple[DataFrame, DataFrame | None]:
    """(rows, copies): without the objects at a place that more than one holds than a leaf should, but for the
    most important one; copies(obj_id, first).

    No tree can split equal points.  Only leaves with more objects than a task holds are looked at, and no
    place is gathered: its first object is a minimum, its copies are found by a join that can be split.
    """
    if plan.theta <= 0:
        return rows, None
    large = [r["pid"] for r in rows.groupBy("pid").count().where(F.col("count") > plan.mem_cap).collect()]
    if not large:
        return rows, None
    crowded = rows.join(F.broadcast(rows.sparkSession.createDataFrame([(p,) for p in large], "pid int")), "pid", "left_semi")
    places = crowded.groupBy("u", "v").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("w", "obj_id")).alias("m")).where(F.col("n") > max(plan.mem_cap // 4, 1))
    copies = crowded.join(places.select("u", "v", F.col("m.obj_id").alias("first")), ["u", "v"]).where("obj_id <> first").select("obj_id", "first")
    copies = materialize(copies, "copies")
    return materialize(rows.join(copies.select("obj_id"), "obj_id", "left_anti").select(*rows.columns), "rows"), copies




class _Clock:
    """Adds the seconds since the last lap to a phase."""

    def __init__(self, phases: dict[str, float]):
        self.phases, self.at = phases, time.perf_counter()

    def lap(self, phase: str) -> None:
        now = time.perf_counter()
        self.phases[phase] += now - self.at
        self.at = now


def band_sizes(layout: Layout) -> DataFrame:
    """(level, split, depth, rows): how many rows that enter a level lie near each split of the tree.

    These are what the repair looks at; the splits are few and known to the driver, a row meets those above its leaf.
    """
    plan, tree = layout.plan, layout.tree
    entering = layout.edges.select("level", F.col("child").alias("obj_id")).join(assign_leaf(layout.objects, tree).select("obj_id", "x", "y", "pid"), "obj_id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for (level, pid), part in pdf.groupby(["level", "pid"]):
                borders = _Borders(tree, plan, int(level))
                size = borders.sizes
                u, v = ((part[c].to_numpy() - e[0]) / (e[1] - e[0]) * size[k] for k, (c, e) in enumerate((("x", plan.x_extent), ("y", plan.y_extent))))
                for split in tree.path(int(pid)):
                    n = int((borders._from_split(split, u, v) < plan.theta).sum())
                    if n:
                        yield pd.DataFrame({"level": [level], "split": [split.number], "depth": [split.depth], "n": [n]})

    counted = entering.select("level", "pid", "x", "y").mapInPandas(run, "level int, split int, depth int, n long")
    return counted.groupBy("level", "split", "depth").agg(F.sum("n").alias("rows"))


def layout_hash_partition(objects: DataFrame, plan: LayoutPlan, parts: int) -> Layout:
    """Baseline: parts by a hash of the id, each laid out on its own, nothing repaired."""
    objects = prepare(objects, plan)
    keyed = objects.select("obj_id", *_units(plan), _weight(plan), F.pmod(F.xxhash64("obj_id"), F.lit(parts)).alias("part"))
    edges = keyed.groupBy("part").applyInPandas(_all_levels(plan, plan.levels, "grid"), EDGES)
    return Layout(plan, objects, materialize(edges, "edges"))


def layout_top_down(objects: DataFrame, plan: LayoutPlan, max_rounds: int = 200) -> Layout:
    """Baseline: minimum-distance sampling from the top level down.

    The kept of a level stay kept below, and whatever else fits is added; every other object is assigned
    to no mark, so there are no aggregates.  Edges name only the marks themselves.  A level takes rounds over
    all objects that no kept one is close to.
    """
    objects = prepare(objects, plan)
    rows = _keyed(objects, plan)
    rows = materialize(_first_of_places(rows) if plan.theta > 0 else rows, "rows")
    kept: DataFrame | None = None
    edges: DataFrame | None = None
    for level in range(1, plan.levels + 1):
        scale = plan.zoom ** (level - plan.levels)
        here = rows.withColumns({"u": F.col("u") * scale, "v": F.col("v") * scale})
        if plan.theta <= 0:
            kept = rows.select("obj_id")
        else:
            free = here
            if kept is not None:
                above = here.join(kept, "obj_id", "left_semi")
                free = materialize(here.join(_neighbours(here, above, plan.theta).select("obj_id").distinct().hint("merge"), "obj_id", "left_anti"), "free")
            new = _placed_in_rounds(free, plan.theta, max_rounds, places=True).select("obj_id")
            kept = new if kept is None else kept.unionByName(new)
        step = kept.select(F.lit(level).cast("int").alias("level"), F.col("obj_id").alias("child"), F.col("obj_id").alias("parent"))
        edges = step if edges is None else edges.unionByName(step)
    return Layout(plan, objects, materialize(edges, "edges"))


def relayout(layout: Layout, added: DataFrame, imbalance: float = 2.0) -> Layout:
    """Layout of the old objects and the added ones with the old tree; a new tree if a leaf has grown too large."""
    both = layout.objects.unionByName(added.select(*layout.objects.columns))
    tree = layout.tree
    if tree is not None:
        sizes = assign_leaf(prepare(both, layout.plan), tree).groupBy("pid").count()
        row = sizes.agg(F.max("count"), F.avg("count")).first()
        if row[0] and row[0] > imbalance * max(row[1], layout.plan.mem_cap / 2):
            tree = None
    return layout_distributed(both, layout.plan, tree=tree)


def visible_iterator(layout: Layout) -> Iterator[tuple[int, int]]:
    """(level, number of marks), from the top."""
    rows = layout.visible().groupBy("level").count().orderBy("level").collect()
    return iter((r["level"], r["count"]) for r in rows)
