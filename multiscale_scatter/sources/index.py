"""The stored layout, and what serves viewports from it.

Marks lie in Parquet, by level and shard of leaves, in Morton order within a file, so that the reader
skips by folder first and by the ranges of cx and cy next.  The lowest levels are the large ones; the top
levels, which fit into one task, are one file each and can be cached.

Spark writes and scans the index; `fetch` is one such scan.  A serving session answers single requests and
has no use for a job: it knows the ranges of all row groups from the files' footers and reads the few that a
viewport meets.
"""

from __future__ import annotations

import json
import re
import time
from collections import OrderedDict
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, fields

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators import kdtree
from ..operators.layout import Layout, LayoutPlan, assign_leaf

#: Leaves that share a folder; bytes of a row group, the least that a request reads of a level.
LEAVES_IN_SHARD, ROW_GROUP_BYTES = 64, 1 << 20


@dataclass
class StoredLayout:
    path: str
    plan: LayoutPlan
    tree: kdtree.KDTree | None
    top_levels: int
    marks: DataFrame


def write_index(layout: Layout, path: str, payload: DataFrame | None = None) -> StoredLayout:
    """Writes all levels; payload(level, cluster_id, ...) adds columns to the marks."""
    spark = layout.objects.sparkSession
    plan, tree = layout.plan, layout.tree
    marks = layout.marks()
    marks = assign_leaf(marks, tree) if tree is not None else marks.withColumn("pid", F.lit(0))
    if payload is not None:
        marks = marks.join(payload, ["level", "cluster_id"], "left")
    top = max((k for k in range(1, plan.levels + 1) if plan.capacity(k) <= plan.mem_cap), default=0)
    # top levels are one table each: their marks are few and every viewport would meet many leaves
    shard = F.when(F.col("level") <= top, F.lit(-1)).otherwise(F.floor(F.col("pid") / LEAVES_IN_SHARD)).cast("int")
    box = G.mark_box(F.col("cx"), F.col("cy"), *plan.box)
    marks = marks.withColumn("shard", shard).withColumn("bbox", box)
    size = [G.level_size(s, plan.zoom, plan.levels) for s in plan.top]
    place = G.morton(F.floor(F.col("cx") / size[0] * 65535), F.floor(F.col("cy") / size[1] * 65535))
    laid = marks.withColumn("m", place).repartition("level", "shard", F.when(F.col("shard") >= 0, F.col("pid"))).sortWithinPartitions("level", "shard", "m")
    laid.drop("m").write.mode("overwrite").option("parquet.block.size", ROW_GROUP_BYTES).partitionBy("level", "shard").parquet(path)
    return StoredLayout(path, plan, tree, top, spark.read.parquet(path))


@dataclass(frozen=True)
class Viewport:
    level: int
    x0: float
    y0: float
    x1: float
    y1: float


def prune(stored: StoredLayout, view: Viewport, pad: tuple[float, float] | None = None) -> list[int]:
    """Leaves whose marks can reach into the viewport: it is grown by half a box, since boxes stick out of their leaf."""
    if stored.tree is None:
        return [0]
    plan = stored.plan
    pad = pad or (plan.box[0] / 2, plan.box[1] / 2)
    raw = []
    for k, (lo, hi) in enumerate((plan.x_extent, plan.y_extent)):
        size = G.level_size(plan.top[k], plan.zoom, view.level)
        a, b = ((view.x0, view.x1), (view.y0, view.y1))[k]
        slack = (hi - lo) * 1e-9
        raw.append(((a - pad[k]) / size * (hi - lo) + lo - slack, (b + pad[k]) / size * (hi - lo) + lo + slack))
    return stored.tree.leaves_meeting(raw[0][0], raw[1][0], raw[0][1], raw[1][1])


def fetch(stored: StoredLayout, view: Viewport, pruned: bool = True, pushdown: bool = True, bandwidth: float | None = None) -> DataFrame:
    """Marks whose box meets the closed viewport, or that lie within bandwidth of it.

    One scan with ranges of stored columns, restricted to the folders of the leaves; without pushdown the
    box is computed first, which no reader can use.
    """
    rows = stored.marks.where(F.col("level") == view.level)
    if pruned and stored.tree is not None and view.level > stored.top_levels:
        pad = (bandwidth, bandwidth) if bandwidth is not None else None
        leaves = prune(stored, view, pad)
        rows = rows.where(F.col("shard").isin(sorted({p // LEAVES_IN_SHARD for p in leaves})) & F.col("pid").isin(leaves))
    wb, hb = (2 * bandwidth, 2 * bandwidth) if bandwidth is not None else stored.plan.box
    if pushdown:
        return rows.where(G.viewport_predicate(view.x0, view.y0, view.x1, view.y1, wb, hb))
    box = G.mark_box(F.col("cx"), F.col("cy"), wb, hb)
    meets = lambda b: (b["x0"] <= view.x1) & (b["x1"] >= view.x0) & (b["y0"] <= view.y1) & (b["y1"] >= view.y0)
    return rows.withColumn("box", box).where(meets(F.col("box"))).drop("box")


#: Files that a session keeps open.
OPEN_FILES = 128


class RowGroups:
    """The row groups of an index: where they are, their level, and the ranges of cx and cy in them.

    Files are opened when a request meets them, and the ones asked for last stay open.
    """

    def __init__(self, path: str):
        self.fs, root = pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (pafs.LocalFileSystem(), path)
        files = self.files = [f.path for f in self.fs.get_file_info(pafs.FileSelector(root, recursive=True)) if f.path.endswith(".parquet")]
        self.readers: OrderedDict[int, pq.ParquetFile] = OrderedDict()
        rows = []

        def footer(path: str) -> pq.FileMetaData:
            with self.fs.open_input_file(path) as f:
                return pq.read_metadata(f)

        with ThreadPoolExecutor(16) as pool:
            for k, meta in enumerate(pool.map(footer, files)):
                at = {meta.schema.column(c).path: c for c in range(meta.num_columns)}
                level = int(re.search(r"level=(\d+)", files[k])[1])
                for g in range(meta.num_row_groups):
                    stats = [meta.row_group(g).column(at[c]).statistics for c in ("cx", "cy")]
                    known = [(s.min, s.max) if s is not None and s.has_min_max else (-np.inf, np.inf) for s in stats]
                    rows.append((k, g, level, *known[0], *known[1]))
        self.table = np.array(rows, float).reshape(-1, 7)

    def reader(self, k: int) -> pq.ParquetFile:
        if k in self.readers:
            self.readers.move_to_end(k)
            return self.readers[k]
        while len(self.readers) >= OPEN_FILES:
            self.readers.popitem(last=False)[1].close(force=True)
        self.readers[k] = pq.ParquetFile(self.fs.open_input_file(self.files[k]))
        return self.readers[k]

    def fetch(self, view: Viewport, wb: float, hb: float, columns: list[str] | None = None) -> tuple[pa.Table, int]:
        """(marks whose box meets the viewport, row groups read)."""
        t = self.table
        x0, x1, y0, y1 = view.x0 - wb / 2, view.x1 + wb / 2, view.y0 - hb / 2, view.y1 + hb / 2
        hit = t[(t[:, 2] == view.level) & (t[:, 4] >= x0) & (t[:, 3] <= x1) & (t[:, 6] >= y0) & (t[:, 5] <= y1)]
        names = columns and sorted({*columns, "cx", "cy"})
        parts = []
        for k in np.unique(hit[:, 0]).astype(int):
            part = self.reader(k).read_row_groups(hit[hit[:, 0] == k, 1].astype(int).tolist(), columns=names, use_threads=False)
            cx, cy = part.column("cx"), part.column("cy")
            inside = pc.and_(pc.and_(pc.greater_equal(cx, x0), pc.less_equal(cx, x1)), pc.and_(pc.greater_equal(cy, y0), pc.less_equal(cy, y1)))
            parts.append(part.filter(inside))
        if parts:
            out = pa.concat_tables(parts)
        else:
            schema = self.reader(0).schema_arrow if self.files else pa.schema([("cluster_id", pa.int64()), ("cx", pa.float64()), ("cy", pa.float64())])
            out = schema.empty_table()
        return (out.select(columns) if columns else out), len(hit)


@dataclass
class ServingSession:
    """Requests of one user: the current viewport, its marks, and listeners for what happens.

    engine "groups" reads row groups in this process, "spark" runs a job for each request.  A sample has the
    time of planning and reading, the marks, the bytes that go to the client, and how many pieces were read.
    """

    stored: StoredLayout
    view: Viewport
    cache_levels: bool = True
    listeners: list[Callable[[str, Viewport], None]] = field(default_factory=list)
    samples: list[dict] = field(default_factory=list)
    engine: str = "groups"

    def __post_init__(self) -> None:
        self._top = self._groups = None
        if self.engine == "groups":
            self._groups = RowGroups(self.stored.path)
        elif self.cache_levels and self.stored.top_levels:
            top = self.stored.marks.where(F.col("level") <= self.stored.top_levels).cache()
            self._top = StoredLayout(self.stored.path, self.stored.plan, None, self.stored.plan.levels, top)

    def request(self, action: str, view: Viewport, columns: list[str] | None = None) -> pa.Table:
        """The marks of a viewport, with all their columns if none are named."""
        began = time.perf_counter()
        if self._groups is not None:
            planned = began
            items, pieces = self._groups.fetch(view, *self.stored.plan.box, columns)
        else:
            source = self._top if self._top is not None and view.level <= self.stored.top_levels else self.stored
            rows = fetch(source, view)
            rows = rows.select(*columns) if columns else rows.drop("level", "shard")
            planned = time.perf_counter()
            items = rows.toArrow()
            pieces = 1 if source is not self.stored else len(prune(self.stored, view))
        ended = time.perf_counter()
        self.samples.append(
            {
                "action": action, "level": view.level, "plan_ms": 1000 * (planned - began), "fetch_ms": 1000 * (ended - began), "items": items.num_rows,
                "bytes": items.nbytes, "partitions": pieces,
            }
        )
        self.view = view
        for tell in self.listeners:
            tell(action, view)
        return items

    def pan(self, dx: float, dy: float) -> pa.Table:
        v = self.view
        return self.request("pan", Viewport(v.level, v.x0 + dx, v.y0 + dy, v.x1 + dx, v.y1 + dy))

    def zoom(self, steps: int, anchor: tuple[float, float] | None = None) -> pa.Table:
        """Keeps the anchor, or the middle, in the middle of the viewport."""
        v, f = self.view, self.stored.plan.zoom**steps
        cx, cy = anchor or ((v.x0 + v.x1) / 2, (v.y0 + v.y1) / 2)
        w, h = v.x1 - v.x0, v.y1 - v.y0
        level = min(max(v.level + steps, 1), self.stored.plan.levels)
        return self.request("zoom_in" if steps > 0 else "zoom_out", Viewport(level, cx * f - w / 2, cy * f - h / 2, cx * f + w / 2, cy * f + h / 2))

    def jump(self, level: int, cx: float, cy: float) -> pa.Table:
        v = self.view
        w, h = v.x1 - v.x0, v.y1 - v.y0
        return self.request("jump", Viewport(level, cx - w / 2, cy - h / 2, cx + w / 2, cy + h / 2))

    def visible_items(self) -> DataFrame:
        return fetch(self.stored, self.view)


def pan_delta(stored: StoredLayout, old: Viewport, new: Viewport) -> DataFrame:
    """Marks of the new viewport that the old one did not have."""
    before = G.viewport_predicate(old.x0, old.y0, old.x1, old.y1, *stored.plan.box)
    return fetch(stored, new).where(~before if old.level == new.level else F.lit(True))


def linked_fetch(other: StoredLayout, ids: DataFrame, level: int) -> DataFrame:
    """Marks of another visualisation for ids(obj_id) picked in this one."""
    marks = other.marks.where(F.col("level") == level)
    return marks.join(ids.select(F.col("obj_id").alias("cluster_id")), "cluster_id", "left_semi")


def densest_window(stored: StoredLayout, level: int, width: float, height: float) -> Viewport:
    """Of windows on a lattice of half viewports, the one with most marks; ties to the smaller x, then y."""
    marks = stored.marks.where(F.col("level") == level)
    spot = marks.select(F.floor(F.col("cx") / (width / 2)).alias("a"), F.floor(F.col("cy") / (height / 2)).alias("b")).groupBy("a", "b").count()
    steps = F.explode(F.array(F.lit(0), F.lit(1)))
    spread = spot.withColumn("da", steps).withColumn("db", steps)
    windows = spread.groupBy((F.col("a") - F.col("da")).alias("a"), (F.col("b") - F.col("db")).alias("b")).agg(F.sum("count").alias("n"))
    best = windows.where("a >= 0 and b >= 0").orderBy(F.desc("n"), "a", "b").limit(1).collect()
    a, b = (best[0]["a"], best[0]["b"]) if best else (0, 0)
    return Viewport(level, a * width / 2, b * height / 2, a * width / 2 + width, b * height / 2 + height)


def generate_trace(stored: StoredLayout, width: float, height: float) -> list[tuple[str, Viewport]]:
    """Down to the bottom through the densest windows, then back to the top."""
    levels = stored.plan.levels
    out: list[tuple[str, Viewport]] = [("start", Viewport(1, 0.0, 0.0, width, height))]
    view = out[0][1]
    for level in range(1, levels + 1):
        dense = densest_window(stored, level, width, height)
        out.append(("pan", Viewport(level, (view.x0 + dense.x0) / 2, (view.y0 + dense.y0) / 2, (view.x0 + dense.x0) / 2 + width, (view.y0 + dense.y0) / 2 + height)))
        out.append(("pan", dense))
        view = dense
        if level < levels:
            f = stored.plan.zoom
            cx, cy = (view.x0 + view.x1) / 2 * f, (view.y0 + view.y1) / 2 * f
            view = Viewport(level + 1, cx - width / 2, cy - height / 2, cx + width / 2, cy + height / 2)
            out.append(("zoom_in", view))
    for level in range(levels - 1, 0, -1):
        f = 1 / stored.plan.zoom
        cx, cy = (view.x0 + view.x1) / 2 * f, (view.y0 + view.y1) / 2 * f
        view = Viewport(level, cx - width / 2, cy - height / 2, cx + width / 2, cy + height / 2)
        out.append(("zoom_out", view))
    return out


def run_trace(session: ServingSession, trace: list[tuple[str, Viewport]]) -> list[dict]:
    for action, view in trace:
        session.request(action, view)
    return session.samples


def nearest_rank(values: list[float], share: float = 0.95) -> float:
    """The least value that at least the given share of values do not exceed."""
    ordered = sorted(values)
    return ordered[max(0, -(-int(round(share * 1_000_000)) * len(ordered) // 1_000_000) - 1)] if ordered else float("nan")


def nearest_rank_of(column: str, share: float = 0.95) -> Column:
    """nearest_rank as an aggregate."""
    return F.expr(f"percentile_disc({share!r}) WITHIN GROUP (ORDER BY {column})")


def latency_report(samples: list[dict]) -> dict[str, float]:
    return {
        "requests": len(samples),
        "fetch_p95_ms": nearest_rank([s["fetch_ms"] for s in samples]),
        "items_p95": nearest_rank([s["items"] for s in samples]),
        "bytes_p95": nearest_rank([s["bytes"] for s in samples]),
        "partitions_p95": nearest_rank([s["partitions"] for s in samples]),
    }


def payload_json(rows: DataFrame) -> DataFrame:
    """One JSON document for each mark, as a client gets it."""
    return rows.select(F.to_json(F.struct(*rows.columns)).alias("value"))


def plan_to_json(stored: StoredLayout) -> str:
    """What a client and a later session need to know of a stored layout."""
    p = stored.plan
    return json.dumps({"path": stored.path, "top_levels": stored.top_levels, **{f.name: getattr(p, f.name) for f in fields(p)}})


def open_index(spark: SparkSession, text: str) -> StoredLayout:
    """The stored layout of plan_to_json; without its tree, which row groups have no use for."""
    known = json.loads(text)
    path, top = known.pop("path"), known.pop("top_levels")
    plan = LayoutPlan(**{k: tuple(v) if isinstance(v, list) else v for k, v in known.items()})
    return StoredLayout(path, plan, None, top, spark.read.parquet(path))


def read_objects(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """User data of any format Spark reads; jdbc takes its options, ranges of a column among them."""
    reader = spark.read.format(fmt).options(**options)
    return reader.load() if fmt == "jdbc" else reader.load(path)
