"""Mixing sources to target weights, block by block.

The words of a source, in a pseudorandom order of its documents, are cut into blocks of fixed length.  A
source's target is its share of all words by weight, at most `max_repeats` times its size.  The output
is a row of shards with as many slots each; how many slots of a shard go to which source is drawn from
the multinomial law given the sources' totals, by halving the row of shards again and again, so that any
shard's counts, and the number of its first slot per source, follow from the seed alone.  A source's
slots run through a pseudorandom permutation of its block numbers, another one for each pass, and the
blocks are joined by number.  No block is used more than `max_repeats` times.

Defined cases: a null or empty text has no words and takes no part; a null source is a source of its
own, last in order; repeated rows are documents of their own; an empty table gives an empty result;
further columns are ignored.  More than `MAX_SOURCES` sources are refused: their totals are sent to every
task.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .shared import materialize, words_of

WEIGHTS = (5, 2, 1)
BLOCK_WORDS, SHARD_SLOTS, BUCKET_DOCS, MAX_SOURCES, SEED = 64, 4096, 4096, 100_000, 7
#: What numpy draws from; more slots than this are drawn from the same law by `picked`.
GENERATOR_LIMIT = 900_000_000


@dataclass
class Mix:
    """documents: doc_id, source, rank, size, first_word.  sources: source, rank, source_size, target,
    n_blocks, n_slots.  blocks: rank, block, doc_id, first_word, words (pieces of documents).  slots:
    shard, position, rank, block."""

    documents: DataFrame
    sources: DataFrame
    blocks: DataFrame
    slots: DataFrame


def targets(sources: DataFrame, weights: tuple = WEIGHTS, max_repeats: int = 3) -> DataFrame:
    """sources(source, source_size) with rank (from 0) and target."""
    ranked = sources.withColumn("rank", F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1)
    pick = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.col("rank") % len(weights) + 1).cast("int"))
    ranked = materialize(ranked.withColumn("weight", pick), "sources")
    total = ranked.agg(F.sum("source_size")).first()[0] or 0
    level, full = 0.0, -1
    while True:  # what sources at their limit leave over raises the level of the others; a few rounds
        limit = F.col("source_size") * max_repeats
        at_limit = limit <= F.lit(level) * F.col("weight")
        row = ranked.agg(
            F.sum(F.when(at_limit, limit).otherwise(0)), F.sum(F.when(~at_limit, F.col("weight"))), F.sum(at_limit.cast("long"))
        ).first()
        if row[2] == full or not row[1]:
            break
        full, level = row[2], (total - row[0]) / row[1]
    return ranked.withColumn("target", F.least((F.col("source_size") * max_repeats).cast("double"), F.lit(level) * F.col("weight")))


def _scramble(x: np.ndarray, key: np.ndarray) -> np.ndarray:
    x = (x ^ key) * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(29))


def permuted(index: np.ndarray, size: np.ndarray, key: np.ndarray) -> np.ndarray:
    """A permutation of 0..size-1 picked by key, applied to index; a Feistel network walked until inside."""
    index, size, key = (np.asarray(x).astype(np.uint64) for x in (index, size, key))
    half = np.ceil(np.log2(np.maximum(size, 2).astype(np.float64)) / 2 + 1e-9).astype(np.uint64)
    half = np.maximum(half, 1)
    mask = (np.uint64(1) << half) - np.uint64(1)
    out, todo = index.copy(), np.arange(len(index))
    while len(todo):
        h, m, k = half[todo], mask[todo], key[todo]
        left, right = out[todo] >> h, out[todo] & m
        for turn in range(4):
            left, right = right, left ^ (_scramble(right, k + np.uint64(turn * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) & m)
        out[todo] = (left << h) | right
        todo = todo[out[todo] >= size[todo]]
    return out.astype(np.int64)


def _halved(slots: np.ndarray, left: int, total: int, seed: tuple) -> np.ndarray:
    """How many of each source's slots fall into the first left of total places."""
    draw = np.random.Generator(np.random.PCG64(list(seed)))
    if total < GENERATOR_LIMIT:
        return draw.multivariate_hypergeometric(slots, left, method="marginals")
    out, rest = np.zeros(len(slots), np.int64), total
    for k, n in enumerate(slots.tolist()):  # source by source: what is left of the places, out of what is left of the slots
        rest -= n
        out[k] = picked(draw, n, rest, left - int(out.sum()))
    return out


def _deviance(x: float, mean: float) -> float:
    """x log(x / mean) + mean - x without cancellation where the two are close."""
    if abs(x - mean) >= 0.1 * (x + mean):
        return x * math.log(x / mean) + mean - x
    v = (x - mean) / (x + mean)
    out, term, j = (x - mean) * v, 2 * x * v, 1
    while True:
        term *= v * v
        more = out + term / (2 * j + 1)
        if more == out:
            return out
        out, j = more, j + 1


def _stirling_rest(n: float) -> float:
    """log n! less Stirling's formula."""
    if n < 16:
        return math.lgamma(n + 1) - (n + 0.5) * math.log(n) + n - 0.5 * math.log(2 * math.pi)
    return (1 / 12 - (1 / 360 - 1 / (1260 * n * n)) / (n * n)) / n


def _log_binomial(k: int, n: int, p: float, q: float) -> float:
    """log of the binomial law at k, by deviances: exact to rounding at any size."""
    if k in (0, n):
        return n * (math.log1p(-p) if p < 0.5 else math.log(q)) if k == 0 else n * (math.log1p(-q) if q < 0.5 else math.log(p))
    rest = _stirling_rest(n) - _stirling_rest(k) - _stirling_rest(n - k) - _deviance(k, n * p) - _deviance(n - k, n * q)
    return rest + 0.5 * (math.log(n) - math.log(2 * math.pi) - math.log(k) - math.log(n - k))


def picked(draw: np.random.Generator, good: int, bad: int, sample: int) -> int:
    """How many of a sample without replacement are good: the hypergeometric law for numbers of any size.

    Ratio of uniforms under a hat for laws of this shape; a proposal is accepted by the law's own values.
    """
    total = good + bad
    low, high = max(0, sample - bad), min(good, sample)
    if low == high:
        return low
    p, q = sample / total, (total - sample) / total
    value = lambda k: _log_binomial(k, good, p, q) + _log_binomial(sample - k, bad, p, q)
    top = value((sample + 1) * (good + 1) // (total + 2))
    mean = sample * good / total
    width = 2 * math.sqrt(2 / math.e) * math.sqrt(mean * (bad / total) * q + 0.5) + 3 - 2 * math.sqrt(3 / math.e)
    while True:
        u, v = draw.random(2)
        k = math.floor(mean + 0.5 + width * (v - 0.5) / u) if u else low - 1
        if low <= k <= high and 2 * math.log(u) <= value(k) - top:
            return k


def shard_counts(slots: np.ndarray, shard: int, n_shards: int, width: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(slots of each source in the shard, the number of each source's first slot there)."""
    first = np.zeros(len(slots), np.int64)
    lo, hi = 0, n_shards
    while hi - lo > 1:
        mid = (lo + hi) // 2
        total = int(slots.sum())
        left = min((mid - lo) * width, total)
        part = _halved(slots, left, total, (seed, lo, hi))
        if shard < mid:
            slots, hi = part, mid
        else:
            first, slots, lo = first + part, slots - part, mid
    return slots, first


def mix(
    docs: DataFrame, weights: tuple = WEIGHTS, max_repeats: int = 3, block_words: int = BLOCK_WORDS, shard_slots: int = SHARD_SLOTS, seed: int = SEED
) -> Mix:
    sized = materialize(docs.select("doc_id", "source", words_of(F.col("text")).alias("size")), "sizes")
    sources = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    sources = targets(sources, weights, max_repeats)
    n_blocks = F.ceil(F.col("source_size") / block_words)
    n_slots = F.when(F.col("source_size") > 0, F.round(F.col("target") * F.col("n_blocks") / F.col("source_size"))).otherwise(0).cast("long")
    sources = materialize(sources.withColumn("n_blocks", n_blocks).withColumn("n_slots", n_slots), "targets")
    rows = sources.select("rank", "n_blocks", "n_slots").orderBy("rank").limit(MAX_SOURCES + 1).collect()
    if len(rows) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    # documents in a pseudorandom order, summed by bucket first: a hot source is many buckets
    named = F.broadcast(sources.select(F.col("source").alias("of"), "rank", F.ceil(F.col("n_docs") / BUCKET_DOCS).alias("n_buckets")))
    placed = sized.join(named, sized["source"].eqNullSafe(named["of"])).withColumn("h", F.xxhash64("doc_id", F.lit(seed)))
    placed = placed.withColumn("bucket", F.pmod("h", "n_buckets")).drop("of", "n_buckets")
    before = W.partitionBy("rank").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    sums = placed.groupBy("rank", "bucket").agg(F.sum("size").alias("s"))
    sums = sums.select("rank", "bucket", F.coalesce(F.sum("s").over(before), F.lit(0)).alias("base"))
    inside = W.partitionBy("rank", "bucket").orderBy("h", "doc_id", "size").rowsBetween(W.unboundedPreceding, -1)
    placed = placed.withColumn("before", F.coalesce(F.sum("size").over(inside), F.lit(0))).join(sums, ["rank", "bucket"])
    documents = materialize(placed.select("doc_id", "source", "rank", "size", (F.col("base") + F.col("before")).alias("first_word")), "placed")
    block_at = lambda word: F.floor(word / block_words)
    spread = documents.where("size > 0").select(
        "rank", "doc_id", F.col("first_word").alias("f"), (F.col("first_word") + F.col("size")).alias("e"),
        F.explode(F.sequence(block_at(F.col("first_word")), block_at(F.col("first_word") + F.col("size") - 1))).alias("block"),
    )
    begin, end = F.greatest("f", F.col("block") * block_words), F.least("e", (F.col("block") + 1) * block_words)
    blocks = spread.select("rank", "block", "doc_id", F.col("f").alias("first_word"), (end - begin).alias("words"))
    rank = np.array([r["rank"] for r in rows], np.int64)
    sizes = np.array([r["n_blocks"] for r in rows], np.int64)
    slots = np.array([r["n_slots"] for r in rows], np.int64)
    n_shards = max(1, -(-int(slots.sum()) // shard_slots)) if len(rows) else 0

    def draw(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for shard in pdf["id"]:
                n, first = shard_counts(slots, int(shard), n_shards, shard_slots, seed)
                which = np.repeat(np.arange(len(n)), n)
                number = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n) + first[which]
                size = np.maximum(sizes[which], 1)
                key = _scramble(rank[which].astype(np.uint64) * np.uint64(1 << 20) + (number // size).astype(np.uint64), np.full(len(which), seed, np.uint64))
                order = permuted(np.arange(len(which)), np.full(len(which), max(len(which), 1)), np.full(len(which), int(shard) + seed * 1_000_003))
                yield pd.DataFrame({"shard": shard, "position": order, "rank": rank[which], "block": permuted(number % size, size, key)})

    numbers = docs.sparkSession.range(n_shards, numPartitions=min(max(1, n_shards), 100_000)) if n_shards < 2048 else docs.sparkSession.range(n_shards)
    drawn = numbers.mapInPandas(draw, "shard long, position long, rank long, block long")
    return Mix(documents, sources, blocks, drawn)


def taken(mixed: Mix) -> DataFrame:
    """For each document: doc_id, size, source_size, target of its source, words taken with repeats."""
    uses = mixed.slots.groupBy("rank", "block").agg(F.count(F.lit(1)).alias("uses"))
    # the planner takes the drawn slots for as few as the shards they come from: never broadcast them
    pieces = mixed.blocks.hint("merge").join(uses, ["rank", "block"]).groupBy("rank", "first_word").agg(F.sum(F.col("words") * F.col("uses")).alias("taken"))
    named = F.broadcast(mixed.sources.select("rank", "source_size", "target"))
    sized = mixed.documents.join(named, "rank")
    has = sized.where("size > 0").hint("merge").join(pieces, ["rank", "first_word"], "left")
    cols = ["doc_id", "source", "size", "source_size", "target"]
    none = sized.where("size = 0").select(*cols, F.lit(0).cast("long").alias("taken"))
    return has.select(*cols, F.coalesce("taken", F.lit(0)).cast("long").alias("taken")).unionByName(none)


def op7_mixing(spark, sf_dir) -> DataFrame:
    return taken(mix(spark.read.parquet(f"{sf_dir}/documents.parquet"))).drop("source")
