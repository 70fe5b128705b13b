"""The declarative specification: marks, layout, data, config; read from JSON, checked, compiled.

A document is a JSON object with the keys "marks", "layout", "data" and "config", as written by
`ScatterSpec.to_json`.
"""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from enum import Enum
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import geometry as G
from ..operators.layout import LayoutPlan


class Mode(str, Enum):
    CIRCLE = "circle"
    CONTOUR = "contour"
    HEATMAP = "heatmap"
    RADAR = "radar"
    PIE = "pie"
    CUSTOM = "custom"


class AggFn(str, Enum):
    COUNT = "count"
    SUM = "sum"
    AVG = "avg"
    MIN = "min"
    MAX = "max"
    SQRSUM = "sqrsum"


class Boundary(str, Enum):
    HULL = "convex hull"
    BBOX = "bbox"


@dataclass(frozen=True)
class CustomRef:
    """A renderer by name; fn gets the payload of a cluster as a dict."""

    name: str
    fn: Callable[[dict], dict] | None = field(default=None, compare=False)


@dataclass(frozen=True)
class Dimension:
    field: str
    domain: tuple[str, ...] | None = None


@dataclass(frozen=True)
class Measure:
    field: str
    function: AggFn
    extent: tuple[float, float] | None = None


@dataclass(frozen=True)
class Aggregate:
    measures: tuple[Measure, ...]
    dimensions: tuple[Dimension, ...] = ()


@dataclass(frozen=True)
class ClusterMark:
    mode: Mode
    aggregate: Aggregate
    custom: CustomRef | None = None
    config: dict = field(default_factory=dict)


@dataclass(frozen=True)
class Ranklist:
    k: int
    template: str | CustomRef = "tabular"


@dataclass(frozen=True)
class HoverMark:
    ranklist: Ranklist | None = None
    boundary: Boundary | None = None
    config: dict = field(default_factory=dict)


@dataclass(frozen=True)
class Marks:
    cluster: ClusterMark
    hover: HoverMark | None = None


@dataclass(frozen=True)
class Axis:
    field: str
    extent: tuple[float, float] | None = None


@dataclass(frozen=True)
class Importance:
    field: str
    order: str = "descending"


@dataclass(frozen=True)
class LayoutSpec:
    x: Axis
    y: Axis
    z: Importance
    theta: float | None = None


@dataclass(frozen=True)
class Config:
    id: str | None = None
    top_width: float = 1000.0
    top_height: float = 1000.0
    num_levels: int = 6
    zoom_factor: float = 2.0
    viewport: tuple[float, float] | None = None
    density_cap: int = 1000
    mem_cap: int = 2_000_000
    box_width: float | None = None
    box_height: float | None = None
    bandwidth: float = 30.0
    pie_inner: float = 0.0
    pie_outer: float = 35.0
    max_radius: float = 25.0
    axes: bool = True
    grid: bool = False
    legend: bool = False
    annotation: str | None = None


@dataclass(frozen=True)
class Issue:
    where: str
    message: str


#: Box sides by mode where the document gives none; custom marks must give theirs.
_SIDE = {Mode.CIRCLE: lambda c: 2 * c.max_radius, Mode.PIE: lambda c: 2 * c.pie_outer, Mode.RADAR: lambda c: 80.0, Mode.HEATMAP: lambda c: 2 * c.bandwidth, Mode.CONTOUR: lambda c: 2 * c.bandwidth}
#: Least distance where the document gives none: marks apart, but for density marks, which add up.
_THETA = {Mode.HEATMAP: 0.0, Mode.CONTOUR: 0.0}
NUMERIC = (T.NumericType, T.TimestampType, T.TimestampNTZType, T.DateType)


@dataclass(frozen=True)
class ScatterSpec:
    marks: Marks
    layout: LayoutSpec
    data: str
    config: Config = Config()

    def with_mode(self, mode: Mode | str) -> ScatterSpec:
        """The same visualisation with other cluster marks."""
        return replace(self, marks=replace(self.marks, cluster=replace(self.marks.cluster, mode=Mode(mode))))

    @property
    def box(self) -> tuple[float, float]:
        c, side = self.config, _SIDE.get(self.marks.cluster.mode)
        w = c.box_width if c.box_width is not None else side(c) if side else 0.0
        h = c.box_height if c.box_height is not None else side(c) if side else 0.0
        return float(w), float(h)

    @property
    def theta(self) -> float:
        c = self.config
        view = c.viewport or (c.top_width, c.top_height)
        overlap = self.layout.theta if self.layout.theta is not None else _THETA.get(self.marks.cluster.mode, 1.0)
        return G.effective_theta(overlap, G.density_theta_exact(*view, *self.box, c.density_cap))

    # documents -------------------------------------------------------------------------------------

    @staticmethod
    def from_json(text: str) -> ScatterSpec:
        """Raises ValueError with all that is wrong with the document's form."""
        try:
            doc = json.loads(text)
        except json.JSONDecodeError as e:
            raise ValueError(f"not JSON: {e}") from None
        return _read(doc)

    def to_json(self) -> str:
        return json.dumps(_plain(self), indent=2, sort_keys=False)

    def validate(self, schema: T.StructType | None = None) -> list[Issue]:
        """What is wrong; with the schema of the data query, fields and types too."""
        out: list[Issue] = []
        say = lambda w, m: out.append(Issue(w, m))
        cluster, hover, layout, config = self.marks.cluster, self.marks.hover, self.layout, self.config
        if layout.theta is not None and not 0 <= layout.theta <= 1:
            say("layout.theta", "must lie between 0 and 1")
        if not cluster.aggregate.measures:
            say("marks.cluster.aggregate", "needs a measure")
        if cluster.mode is Mode.CUSTOM:
            if cluster.custom is None:
                say("marks.cluster", "a custom mark needs a renderer")
            if config.box_width is None or config.box_height is None:
                say("config", "a custom mark needs box_width and box_height")
        if cluster.mode is Mode.PIE and not cluster.aggregate.dimensions:
            say("marks.cluster.aggregate", "a pie needs a dimension")
        if hover:
            if hover.ranklist is None and hover.boundary is None:
                say("marks.hover", "needs a ranklist or a boundary")
            if hover.ranklist and hover.ranklist.k < 1:
                say("marks.hover.ranklist.k", "must be positive")
        extents = [("layout.x", layout.x.extent), ("layout.y", layout.y.extent), *((f"measure {m.field}", m.extent) for m in cluster.aggregate.measures)]
        for where, extent in extents:
            if extent is not None and not extent[0] < extent[1]:
                say(where, "extent must grow")
        if layout.z.order not in ("ascending", "descending"):
            say("layout.z.order", "ascending or descending")
        if config.num_levels < 1 or config.zoom_factor <= 1 or config.top_width <= 0 or config.top_height <= 0 or config.density_cap < 1:
            say("config", "sizes, levels, zoom factor or density cap out of range")
        if schema is not None:
            fields = {f.name: f.dataType for f in schema.fields}
            used = [("layout.x", layout.x.field, True), ("layout.y", layout.y.field, True), ("layout.z", layout.z.field, True)]
            used += [("measure", m.field, m.function is not AggFn.COUNT) for m in cluster.aggregate.measures if m.field != "*"]
            used += [("dimension", d.field, False) for d in cluster.aggregate.dimensions]
            for where, name, number in used:
                if name not in fields:
                    say(where, f"no column {name}")
                elif number and not isinstance(fields[name], NUMERIC):
                    say(where, f"{name} is not a number")
        return out


def _plain(x: Any) -> Any:
    if isinstance(x, Enum):
        return x.value
    if isinstance(x, CustomRef):
        return {"custom": x.name}
    if hasattr(x, "__dataclass_fields__"):
        default = {n: f.default for n, f in x.__dataclass_fields__.items()}
        values = {n: getattr(x, n) for n in x.__dataclass_fields__}
        return {n: _plain(v) for n, v in values.items() if v is not None and v != () and v != {} and not (isinstance(x, Config) and v == default[n])}
    if isinstance(x, (list, tuple)):
        return [_plain(v) for v in x]
    return x


def _read(doc: dict) -> ScatterSpec:
    wrong: list[str] = []

    def part(d: Any, where: str, known: set[str], needed: set[str] = frozenset()) -> dict:
        if not isinstance(d, dict):
            wrong.append(f"{where}: not an object")
            return {}
        wrong.extend(f"{where}: unknown key {k}" for k in d if k not in known)
        wrong.extend(f"{where}: missing {k}" for k in sorted(needed) if k not in d)
        return d

    def one_of(kind: type[Enum], value: Any, where: str) -> Any:
        try:
            return kind(value)
        except ValueError:
            wrong.append(f"{where}: unknown {value!r}")
            return None

    pair = lambda v: tuple(map(float, v)) if v is not None else None
    top = part(doc, "document", {"marks", "layout", "data", "config"}, {"marks", "layout", "data"})
    marks = part(top.get("marks", {}), "marks", {"cluster", "hover"}, {"cluster"})
    cl = part(marks.get("cluster", {}), "marks.cluster", {"mode", "aggregate", "custom", "config"}, {"mode", "aggregate"})
    agg = part(cl.get("aggregate", {}), "marks.cluster.aggregate", {"dimensions", "measures"}, {"measures"})
    measures = tuple(Measure(m["field"], one_of(AggFn, m["function"], "measure"), pair(m.get("extent"))) for m in agg.get("measures", ()) if part(m, "measure", {"field", "function", "extent"}, {"field", "function"}) and {"field", "function"} <= set(m))
    dimensions = tuple(Dimension(d["field"], tuple(d["domain"]) if d.get("domain") else None) for d in agg.get("dimensions", ()) if part(d, "dimension", {"field", "domain"}, {"field"}) and "field" in d)
    custom = CustomRef(cl["custom"]["custom"] if isinstance(cl["custom"], dict) else cl["custom"]) if cl.get("custom") else None
    hover = None
    if marks.get("hover") is not None:
        h = part(marks["hover"], "marks.hover", {"ranklist", "boundary", "config"})
        ranks = None
        if h.get("ranklist") is not None:
            r = part(h["ranklist"], "marks.hover.ranklist", {"k", "template"}, {"k"})
            t = r.get("template", "tabular")
            ranks = Ranklist(int(r.get("k", 0)), CustomRef(t["custom"]) if isinstance(t, dict) else t)
        hover = HoverMark(ranks, one_of(Boundary, h["boundary"], "marks.hover.boundary") if h.get("boundary") else None, h.get("config", {}))
    lay = part(top.get("layout", {}), "layout", {"x", "y", "z", "theta"}, {"x", "y", "z"})
    axis = {}
    for k in "xy":
        a = part(lay.get(k, {}), f"layout.{k}", {"field", "extent"}, {"field"})
        axis[k] = Axis(a.get("field", ""), pair(a.get("extent")))
    z = part(lay.get("z", {}), "layout.z", {"field", "order"}, {"field"})
    c = part(top.get("config", {}), "config", set(Config.__dataclass_fields__))
    c = {k: tuple(v) if isinstance(v, list) else v for k, v in c.items() if k in Config.__dataclass_fields__}
    mode = one_of(Mode, cl.get("mode"), "marks.cluster.mode")
    if wrong:
        raise ValueError("; ".join(wrong))
    return ScatterSpec(
        Marks(ClusterMark(mode, Aggregate(measures, dimensions), custom, cl.get("config", {})), hover),
        LayoutSpec(axis["x"], axis["y"], Importance(z["field"], z.get("order", "descending")), lay.get("theta")),
        top["data"], Config(**c),
    )


@dataclass
class Compiled:
    spec: ScatterSpec
    objects: DataFrame
    plan: LayoutPlan


def number(column: str, kind: T.DataType):
    """A column as a double; times as seconds."""
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        return F.unix_micros(F.col(column).cast("timestamp")) / 1e6
    return F.col(column).cast("double")


def compile_spec(spark: SparkSession, spec: ScatterSpec) -> Compiled:
    """Objects(obj_id, x, y, z, further columns) and layout plan of a document; one aggregate job for extents it doesn't give."""
    rows = spark.sql(spec.data)
    issues = spec.validate(rows.schema)
    if issues:
        raise ValueError("; ".join(f"{i.where}: {i.message}" for i in issues))
    kinds = {f.name: f.dataType for f in rows.schema.fields}
    ident = F.col(spec.config.id).cast("long") if spec.config.id else F.xxhash64(*rows.columns)
    lay = spec.layout
    taken = {"obj_id", "x", "y", "z"}
    rest = [F.col(c) for c in rows.columns if c not in taken]
    objects = rows.select(
        ident.alias("obj_id"), *(number(a, kinds[a]).alias(n) for n, a in (("x", lay.x.field), ("y", lay.y.field), ("z", lay.z.field))), *rest
    )
    extents = [lay.x.extent, lay.y.extent]
    if None in extents:
        row = objects.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y")).first()
        for k in (0, 1):
            lo, hi = row[2 * k], row[2 * k + 1]
            if extents[k] is None:
                extents[k] = (0.0, 1.0) if lo is None else (lo, hi if hi > lo else lo + 1.0)
    c = spec.config
    plan = LayoutPlan(
        tuple(extents[0]), tuple(extents[1]), spec.theta, spec.box, (c.top_width, c.top_height), c.num_levels, c.zoom_factor,
        lay.z.order == "descending", c.mem_cap,
    )
    return Compiled(spec, objects, plan)


def drill(target: ScatterSpec, condition: str) -> ScatterSpec:
    """Semantic zoom: another visualisation, of the rows that a mark of this one points to."""
    return replace(target, data=f"SELECT * FROM ({target.data}) WHERE {condition}")


def expand_low_level(compiled: Compiled) -> dict:
    """What an author writes without a layout generator: a canvas, a query and a renderer for every level."""
    p, spec = compiled.plan, compiled.spec
    measures = [{"field": m.field, "function": m.function.value} for m in spec.marks.cluster.aggregate.measures]
    canvases = []
    for level in range(1, p.levels + 1):
        w, h = (G.level_size(s, p.zoom, level) for s in p.top)
        canvases.append(
            {
                "id": f"level{level}", "width": w, "height": h,
                "layers": [
                    {
                        "query": spec.data,
                        "placement": {
                            "cx": f"({spec.layout.x.field} - {p.x_extent[0]}) / {p.x_extent[1] - p.x_extent[0]} * {w}",
                            "cy": f"({spec.layout.y.field} - {p.y_extent[0]}) / {p.y_extent[1] - p.y_extent[0]} * {h}",
                            "width": p.box[0], "height": p.box[1],
                        },
                        "select": {"order": [spec.layout.z.field, spec.layout.z.order], "distance": p.theta},
                        "columns": measures, "renderer": spec.marks.cluster.mode.value, "hover": _plain(spec.marks.hover) if spec.marks.hover else None,
                    },
                ],
            }
        )
    jumps = [{"from": f"level{k}", "to": f"level{k + d}", "type": "zoom", "factor": p.zoom**d} for k in range(1, p.levels + 1) for d in (-1, 1) if 1 <= k + d <= p.levels]
    return {"canvases": canvases, "jumps": jumps, "view": {"width": p.top[0], "height": p.top[1], "initial": "level1"}}


def authoring_effort(compiled: Compiled) -> dict[str, float]:
    """Lines and tokens of both documents as indented JSON, and their ratios."""
    high, low = compiled.spec.to_json(), json.dumps(expand_low_level(compiled), indent=2)
    lines = lambda t: sum(bool(x.strip()) for x in t.split("\n"))
    tokens = lambda t: len([x for x in __import__("re").findall(r'"(?:[^"\\]|\\.)*"|[-\w.]+|[{}\[\]:,]', t)])
    return {"lines": lines(high), "low_lines": lines(low), "line_ratio": lines(low) / lines(high), "tokens": tokens(high), "low_tokens": tokens(low), "token_ratio": tokens(low) / tokens(high)}
