"""Pieces that several corpus operators use: word counts and graph components."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import discard, materialize, scratch, shared_folder

__all__ = ["WORD", "components", "discard", "materialize", "scratch", "shared_folder", "words_of"]

#: White space that separates words, as a class for Java and DuckDB patterns.
WORD = r"[^\x20\x09-\x0D]+"


def words_of(text: Column) -> Column:
    """Number of words, JVM-side."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def _components_here(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, component) of all edges of one task; nodes are numbers."""
    parts = [(b.column("a").to_numpy(zero_copy_only=False), b.column("b").to_numpy(zero_copy_only=False)) for b in batches]
    if not parts:
        return
    a, b = (np.concatenate([p[k] for p in parts]) for k in (0, 1))
    nodes, place = np.unique(np.concatenate([a, b]), return_inverse=True)
    a, b = place[: len(a)], place[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        # hook both ends' roots to the lower label, then halve the paths
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        while (new[new] != new).any():
            new = new[new]
        if (new == label).all():
            break
        label = new
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[label])], names=["node", "component"])


def components(edges: DataFrame, one_task: int = 0, max_rounds: int = 60) -> DataFrame:
    """(node, component) for the nodes of edges(a, b); a component's id is its smallest node.

    At most `one_task` edges between numbers are left to one task; more of them take rounds.

    Alternating star contraction.  Each round needs only a minimum per node (combined before the
    shuffle) and an equi-join of the edges with those minima, which adaptive execution splits when a
    hub holds a large share of the edges.  Every round is written to the shared folder.  No neighbour
    list is ever gathered.  An empty input gives an empty result.
    """
    current = materialize(
        edges.where(F.col("a") != F.col("b"))
        .select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        .distinct(),
        "edges",
    )
    before = _fingerprint(current)
    if 0 < before[0] <= one_task:
        found = materialize(current.coalesce(1).mapInArrow(_components_here, "node long, component long"), "components")
        discard(current)
        return found
    for _ in range(max_rounds):
        if before[0] == 0:
            break
        both = current.unionByName(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.unionByName(low.where("a != m").select("a", F.col("m").alias("b"))).distinct()
        # small step: each node hands its smaller neighbours, and itself, to the smallest of them
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        after = materialize(
            small.unionByName(least.select("a", F.col("m").alias("b"))).where("a != b").distinct(), "edges"
        )
        now = _fingerprint(after)
        discard(current)
        current, same = after, now == before
        before = now
        if same:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = current.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return current.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(
        F.count(F.lit(1)).alias("n"),
        F.bit_xor(F.xxhash64("a", "b")).alias("x"),
        F.sum(F.pmod(F.xxhash64("b", "a"), F.lit(1 << 31))).alias("s"),
    ).first()
    return tuple(row)
