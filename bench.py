"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from multiscale_scatter.operators import layout as L  # noqa: E402
from multiscale_scatter.plans import workloads as W  # noqa: E402
from multiscale_scatter.plans.materialize import fresh_path, materialize  # noqa: E402
from multiscale_scatter.sources import index as I  # noqa: E402
from multiscale_scatter.sources import synthetic  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session() -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )


def timed(f, *args, **kwargs):
    began = time.perf_counter()
    out = f(*args, **kwargs)
    return out, round(time.perf_counter() - began, 3)


def serve(name: str, stored: I.StoredLayout, view: float = 1000.0) -> dict[str, float]:
    """Times of a trace to the densest places and back; all columns of the marks are fetched."""
    serving = I.ServingSession(stored, I.Viewport(1, 0.0, 0.0, view, view))
    I.run_trace(serving, I.generate_trace(stored, view, view))
    report = I.latency_report(serving.samples)
    return {f"{name}_{k}": round(v, 1) for k, v in report.items()}


def main() -> None:
    spark = session()
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).withColumn("k", F.col("id") % 7).groupBy("k").applyInPandas(lambda p: p, "id long, k long").count()  # starts the workers
    took: dict[str, float] = {}
    extra: dict[str, float] = {}
    specs = {"heatmap": W.HEATMAP, "contour": W.EVENT_CONTOUR, "pies": W.PIES, "text": W.TEXT, "circles": W.CIRCLE}
    for name, spec in specs.items():
        layout, took[f"layout_{name}"] = timed(W.lay_out, spark, SF_DIR, spec)
        payload, took[f"payload_{name}"] = timed(W.payload, layout, spec)
        stored, took[f"index_{name}"] = timed(I.write_index, layout, fresh_path(spark, name), payload)
        extra |= {f"{name}_phase_{k}_s": round(v, 2) for k, v in layout.phases.items()} | {f"{name}_objects": layout.objects.count()}
        report, took[f"trace_{name}"] = timed(serve, name, stored)
        extra |= report
    synthetic.register_source(spark)
    for millions in (0.5, 1, 2, 4):
        objects = spark.read.format("scatter_synth").option("rows", int(millions * 1_000_000)).load()
        objects, took[f"synth_write_{millions}m"] = timed(materialize, objects, "synth")
        plan = L.LayoutPlan((0.0, 1.0), (0.0, 1.0), levels=10, mem_cap=int(millions * 1_000_000) // 32)
        layout, took[f"synth_layout_{millions}m"] = timed(L.layout_distributed, objects, plan)
        stored, took[f"synth_index_{millions}m"] = timed(I.write_index, layout, fresh_path(spark, "synth"))
        extra |= {f"synth_{millions}m_phase_{k}_s": round(v, 2) for k, v in layout.phases.items()}
        extra |= serve(f"synth_{millions}m", stored)
    print(json.dumps({"metric": "scatter_layout_index_serve_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(SF_DIR), "measures": extra}))


if __name__ == "__main__":
    main()
