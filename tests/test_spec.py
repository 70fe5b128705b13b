import json
from dataclasses import replace

import pytest
from conftest import SMALL

from multiscale_scatter.plans import workloads as W
from multiscale_scatter.plans.spec import Axis, Mode, ScatterSpec, authoring_effort, compile_spec, drill, expand_low_level
from multiscale_scatter.sources.fixtures import register
from multiscale_scatter.sources.synthetic import register_source


@pytest.mark.parametrize("name", list(W.SPECS))
def test_round_trip(name):
    spec = W.SPECS[name]
    assert ScatterSpec.from_json(spec.to_json()) == spec
    assert not spec.validate()


@pytest.mark.parametrize(
    "change,word",
    [
        (lambda d: d["layout"].update(theta=1.2), "between"),
        (lambda d: d["marks"]["hover"]["ranklist"].update(k=0), "positive"),
        (lambda d: d["layout"]["x"].update(extent=[5, 5]), "grow"),
        (lambda d: d["marks"]["cluster"]["aggregate"].update(measures=[]), "measure"),
        (lambda d: d["marks"]["cluster"].update(mode="custom"), "custom"),
        (lambda d: d["marks"]["cluster"].update(mode="cube"), "unknown"),
        (lambda d: d["layout"].pop("z"), "missing"),
        (lambda d: d.update(extra=1), "unknown key"),
    ],
)
def test_bad_documents(change, word):
    doc = json.loads(W.PIES.to_json())
    change(doc)
    try:
        issues = " ".join(i.message for i in ScatterSpec.from_json(json.dumps(doc)).validate())
    except ValueError as e:
        issues = str(e)
    assert word in issues


def test_schema_issues(spark):
    register(spark, SMALL)
    bad = replace(W.CIRCLE, layout=replace(W.CIRCLE.layout, x=Axis("nothing"), y=Axis("event_type")))
    with pytest.raises(ValueError, match="no column nothing.*event_type is not a number"):
        compile_spec(spark, bad)


def test_mode_is_one_parameter():
    contour = W.HEATMAP.with_mode("contour")
    assert contour.marks.cluster.mode is Mode.CONTOUR and contour.theta == W.HEATMAP.theta
    assert W.PROFILE.theta == 0.5 and W.TEXT.theta == 1.0


def test_effort(spark):
    for name in ("pie_lineitem", "circle_events", "profile_customer"):
        c = W.compiled(spark, SMALL, W.SPECS[name])
        assert len(expand_low_level(c)["canvases"]) == c.plan.levels
        assert authoring_effort(c)["line_ratio"] > 3


def test_drill(spark):
    register(spark, SMALL)
    whole = compile_spec(spark, W.CIRCLE).objects
    part = compile_spec(spark, drill(W.CIRCLE, "event_type = 'click'")).objects
    assert part.count() == whole.where("event_type = 'click'").count() > 0


def test_synthetic_source(spark):
    register_source(spark)
    a = spark.read.format("scatter_synth").option("rows", 5000).option("partitions", 3).load()
    b = spark.read.format("scatter_synth").option("rows", 5000).option("partitions", 7).load()
    assert a.exceptAll(b).count() == 0
    half = 0.2**0.5 / 2
    inside = a.where(f"x between {0.5 - half} and {0.5 + half} and y between {0.5 - half} and {0.5 + half}").count()
    assert 0.8 <= inside / 5000 <= 0.88
