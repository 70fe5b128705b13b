"""Quality rules of documents, and of their hosts.

Per document: word, symbol, line, repeated-line and repeated-window counts, from which the rules follow.  The
base rule rejects a document by itself.  The other rules misfire on single documents (a table, a refrain), so
what they say depends on the host (the source): per rule, the share of a host's documents that fail it is
shrunk towards the corpus by a beta prior whose two parameters are fitted to the hosts' rates by their moments.
A host breaks a rule if its shrunk rate reaches the rule's bar; the verdicts are joined back, and a document is
rejected if it fails a rule that its host breaks.  A host that breaks the base rule is rejected as a whole.

Defined cases: a null or empty text has no words and fails; a null source is a host of its own; repeated
rows count each and give a row each; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textvec
from .shared import materialize

WINDOW, MIN_WORDS, MAX_REPEAT_PERCENT = 5, 10, 20


@dataclass(frozen=True)
class Rule:
    """fails: SQL over the counts, true for a document that fails; bar: the shrunk rate from which a host breaks the rule."""

    name: str
    fails: str
    bar: float
    whole_host: bool = False


RULES = (
    Rule("base", f"(n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words)", 0.5, True),
    Rule("symbols", "(10 * n_symbols > n_words)", 0.05),
    Rule("lines", "(10 * n_dup_lines > 3 * n_lines)", 0.05),
    Rule("word_length", "(n_words > 0 AND (word_chars < 3 * n_words OR word_chars > 12 * n_words))", 0.05),
)
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
#: A hot host's rows are dealt to this many tasks in the join with the verdicts.
SALTS = 16

_COUNTS = "doc_id long, source string, key long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long"


def _per_row(flags: np.ndarray, at: np.ndarray) -> np.ndarray:
    return np.diff(np.concatenate(([0], np.cumsum(flags)))[at])


def _repeats(keys: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Flags of keys that their row has twice or more, and of those that are not the first of their value."""
    k = textvec.mix(keys ^ textvec.mix(rows.astype(np.uint64) + np.uint64(1)))
    order = np.argsort(k, kind="stable")
    s = k[order]
    equal = s[1:] == s[:-1]
    twice, later = np.zeros(len(k), bool), np.zeros(len(k), bool)
    twice[order[1:]] |= equal
    twice[order[:-1]] |= equal
    later[order[1:]] = equal
    return twice, later


def measure(raw: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines (those with a word) of each row."""
    rows = len(at) - 1
    starts, ends, n_words = textvec.word_bounds(raw, at)
    word_chars = _per_row(~textvec._SPACE[raw] & ((raw & 0xC0) != 0x80), at)
    symbols = _per_row(_SYMBOL[raw], at)
    breaks = np.flatnonzero(raw == 10)
    line_start = np.sort(np.concatenate([at[:-1], breaks + 1]), kind="stable")
    line_end = np.sort(np.concatenate([at[1:], breaks]), kind="stable")
    filled = np.concatenate(([0], np.cumsum(~textvec._SPACE[raw])))
    use = filled[line_end] > filled[line_start]
    line_start, line_end = line_start[use], line_end[use]
    line_row = np.searchsorted(at, line_start, side="right") - 1
    _, later = _repeats(textvec.span_hashes(raw, line_start, line_end), line_row)
    dup_lines = np.bincount(line_row[later], minlength=rows)
    words = textvec.span_hashes(raw, starts, ends)
    windows, n = textvec.shingle_hashes(words, n_words, WINDOW)
    row = np.repeat(np.arange(rows), n)
    twice, _ = _repeats(windows, row)
    begin = (np.cumsum(n_words) - n_words)[row] + np.arange(len(row)) - (np.cumsum(n) - n)[row]
    cover = np.zeros(len(words) + WINDOW + 1, np.int64)
    cover[begin[twice]] += 1
    cover[begin[twice] + WINDOW] -= 1
    covered = np.cumsum(cover)[: len(words)] > 0
    repeat_words = _per_row(covered, np.concatenate(([0], np.cumsum(n_words))))
    return [n_words, word_chars, symbols, dup_lines, repeat_words, np.bincount(line_row, minlength=rows)]


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for a, b, raw, at in textvec.pieces(batch.column("text")):
            yield pa.RecordBatch.from_arrays(
                [batch.column(c).slice(a, b - a) for c in ("doc_id", "source", "key")]
                + [pa.array(x.astype(np.int64)) for x in measure(raw, at)],
                names=[x.split()[0] for x in _COUNTS.split(", ")],
            )


def _shrunk(hosts: DataFrame, rules: tuple[Rule, ...]) -> list[Column]:
    """The shrunk rate of each rule, from hosts(n_docs, failed_<rule>...); two passes over the hosts for all rules."""
    sums = hosts.agg(F.sum("n_docs"), F.count(F.lit(1)), *(F.sum(f"failed_{r.name}") for r in rules)).first()
    n, h = sums[0] or 0, sums[1]
    means = [f / n if n else 0.0 for f in sums[2:]]
    gaps = [F.col(f"failed_{r.name}") / F.col("n_docs") - F.lit(float(m)) for r, m in zip(rules, means, strict=True)]
    spread = hosts.agg(*(F.sum(F.col("n_docs") * g * g) for g in gaps)).first()
    out = []
    for rule, mean, around in zip(rules, means, spread, strict=True):
        # variance between hosts: what the rates vary by, less what sampling alone would give
        between = max((around or 0.0) / n - mean * (1 - mean) * h / n, 1e-9) if n else 1e-9
        strength = min(max(mean * (1 - mean) / between - 1, 1.0), 1e6)
        out.append((F.col(f"failed_{rule.name}") + F.lit(float(mean * strength))) / (F.col("n_docs") + F.lit(float(strength))))
    return out


def host_rates(judged: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(source, n_docs, rate_<rule> of each rule, broken: array of the rules that the host breaks) from rows with source and the counts."""
    hosts = judged.groupBy("source").agg(
        F.count(F.lit(1)).alias("n_docs"), *(F.sum(F.expr(r.fails).cast("long")).alias(f"failed_{r.name}") for r in rules)
    )
    hosts = materialize(hosts, "hosts")
    rates = hosts.select("source", "n_docs", *(c.alias(f"rate_{r.name}") for r, c in zip(rules, _shrunk(hosts, rules), strict=True)))
    broken = F.filter(F.array(*(F.when(F.col(f"rate_{r.name}") >= r.bar, r.name) for r in rules)), lambda x: x.isNotNull())
    return rates.withColumn("broken", broken)


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """For each row of docs(doc_id, source, text): key (a hash of the text), the counts, base_failed, failed and
    broken (rules that the document fails, that its host breaks), host_rate (of base failures), kept.  The first rule is the base."""
    counts = docs.select("doc_id", "source", "text", F.xxhash64("text").alias("key")).mapInArrow(_measure, _COUNTS)
    judged = materialize(counts, "counts")
    rates = host_rates(judged, rules).select(
        F.col("source").alias("host"), F.col(f"rate_{rules[0].name}").alias("host_rate"), "broken", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("host_salt")
    )
    dealt = judged.withColumn("salt", F.pmod(F.xxhash64("doc_id", "n_words", "word_chars"), F.lit(SALTS)).cast("int"))
    joined = dealt.join(rates, dealt["source"].eqNullSafe(rates["host"]) & (dealt["salt"] == rates["host_salt"]), "left")
    failed = F.filter(F.array(*(F.when(F.expr(r.fails), r.name) for r in rules)), lambda x: x.isNotNull())
    whole = [F.array_contains("broken", r.name) for r in rules if r.whole_host]
    bad = F.col("base_failed") | F.arrays_overlap("failed", "broken")
    for w in whole:
        bad = bad | w
    joined = joined.withColumn("base_failed", F.expr(rules[0].fails)).withColumn("failed", failed)
    return joined.withColumn("kept", ~bad).drop("salt", "host", "host_salt")


def keep_good(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs whose document is kept."""
    bad = judge(docs, **options).where("not kept").select(F.col("doc_id").alias("bad_id"), F.col("source").alias("bad_source"), F.col("key").alias("bad_key")).distinct()
    same = docs["doc_id"].eqNullSafe(bad["bad_id"]) & docs["source"].eqNullSafe(bad["bad_source"]) & (F.xxhash64(docs["text"]) == bad["bad_key"])
    return docs.join(bad, same, "left_anti")


def op4_quality_rules(spark, sf_dir) -> DataFrame:
    judged = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return judged.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept",
        F.array_join("failed", ",").alias("failed_rules"), F.array_join("broken", ",").alias("host_breaks"),
    )


def oracle_sql(rules: tuple[Rule, ...] = RULES) -> str:
    """judge in DuckDB's SQL."""
    name = lambda r: r.name
    each = lambda f, sep=", ": sep.join(f(r) for r in rules)
    listed = lambda f: f"array_to_string(list_filter([{each(f)}], lambda x: x IS NOT NULL), ',')"
    between = "greatest(sum(h.n * (h.f_{0} / h.n - t.m_{0}) * (h.f_{0} / h.n - t.m_{0})) / any_value(t.n) - any_value(t.m_{0}) * (1 - any_value(t.m_{0})) * any_value(t.h) / any_value(t.n), 1e-9)"
    return rf"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS text,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws
  FROM documents),
lines AS (
  SELECT r, list_filter(string_split(text, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS ls FROM d),
win AS (
  SELECT r, i, array_to_string(ws[i:i+4], ' ') AS k
  FROM (SELECT r, ws, unnest(range(1, len(ws) - 3)) AS i FROM d WHERE len(ws) >= 5)),
rep AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, k) AS c FROM win) WHERE c > 1),
cov AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(range(i, i + 5)) AS p FROM rep) GROUP BY r),
m AS (
  SELECT d.r, d.doc_id, d.source, CAST(len(ws) AS BIGINT) AS n_words,
         CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
         CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(cov.n, 0) AS BIGINT) AS n_repeat_words, CAST(len(ls) AS BIGINT) AS n_lines
  FROM d JOIN lines ON d.r = lines.r LEFT JOIN cov ON d.r = cov.r),
h AS (SELECT source, count(*) AS n, {each(lambda r: f"count(*) FILTER {r.fails} AS f_{name(r)}")} FROM m GROUP BY source),
t AS (SELECT sum(n) AS n, count(*) AS h, {each(lambda r: f"sum(f_{name(r)}) / sum(n) AS m_{name(r)}")} FROM h),
s AS (SELECT {each(lambda r: f"any_value(t.m_{name(r)}) AS m_{name(r)}, {between.format(name(r))} AS v_{name(r)}")} FROM h, t),
p AS (SELECT {each(lambda r: f"m_{name(r)}, least(greatest(m_{name(r)} * (1 - m_{name(r)}) / v_{name(r)} - 1, 1.0), 1e6) AS k_{name(r)}")} FROM s),
rate AS (SELECT source, {each(lambda r: f"(f_{name(r)} + m_{name(r)} * k_{name(r)}) / (n + k_{name(r)}) >= {r.bar} AS breaks_{name(r)}")} FROM h, p)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, {rules[0].fails} AS base_failed,
       NOT ({rules[0].fails} OR {each(lambda r: f"(breaks_{name(r)}{'' if r.whole_host else f' AND {r.fails}'})", " OR ")}) AS kept,
       {listed(lambda r: f"CASE WHEN {r.fails} THEN '{name(r)}' END")} AS failed_rules,
       {listed(lambda r: f"CASE WHEN breaks_{name(r)} THEN '{name(r)}' END")} AS host_breaks
FROM m JOIN rate ON m.source IS NOT DISTINCT FROM rate.source
"""


OP4_SQL = oracle_sql()
