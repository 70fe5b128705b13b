"""Benchmark decontamination: every passage of every document queries a BM25 index of the test items.

Items are cut into units of equal length, at most `UNIT_WORDS` words, the index's entries, documents into passages of two
strides of `STRIDE` words, so any run of a stride's length lies within a passage.  A passage scores for a
unit the share of the unit's own BM25 score that its words bring; all units above `threshold` are found by a
walk over the posting lists of the passage's terms in the order of units, with weak lists left behind:

- the lists of a passage stand at their next unit; the first unit at which the greatest impacts of the lists up
  to it reach the threshold is the pivot, none before it can;
- the greatest impacts within the pivot's block of units bound it closer; below the threshold, the lists go on
  behind the block, or to where the next list stands;
- else the pivot is scored in full, and the lists go on behind it.

All passages of a batch take their steps together, so a step is a few numpy operations.

An item that is found is then verified on the whole document: the three-word runs of its question, and of
its answer, must occur there.  The answer is what follows an "answer:" mark, else the last sentence, else
the last third of the words.

The index is sent to every task.  A benchmark of more than `SLICE_BYTES` of text is searched slice by slice;
document frequencies, the number of units and their mean length are those of the whole benchmark, counted
before, so scores and pairs don't depend on how many slices there are.

Defined cases: null or empty texts and items match nothing; repeated rows match each; null ids are kept;
empty tables give an empty result; further columns are ignored by the search and kept by the filter.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec
from .shared import materialize

UNIT_WORDS, STRIDE, BLOCK_UNITS, SLICE_BYTES = 40, 48, 16, 16 << 20
#: Bytes of text whose passages are searched together; a longer text is searched on its own.
TOGETHER = 1 << 20
#: Passages that take their steps together.
PASSAGES = 4096
K1, B = 1.2, 0.75
THRESHOLD, OVERLAP = 0.6, 0.7


def hashed_words(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words without punctuation, and how many each row has; texts come in lower case."""
    starts, ends, n = textvec.word_bounds(raw, at, textvec.BREAKS)
    return textvec.span_hashes(raw, starts, ends), n


def question_and_answer(text: str) -> tuple[str, str]:
    if m := re.search(r"(?is)^(.*\w.*)\b(?:answer|a)\s*:\s*(.*\w.*)$", text):
        return m[1], m[2]
    sentences = [s for s in re.split(r"(?<=[.?!])\s+", text.strip()) if re.search(r"\w", s)]
    if len(sentences) > 1:
        return " ".join(sentences[:-1]), sentences[-1]
    words = text.split()
    cut = len(words) - len(words) // 3
    return " ".join(words[:cut]), " ".join(words[cut:])


def _words(text: str) -> np.ndarray:
    raw = np.frombuffer(text.encode(), np.uint8)
    return hashed_words(raw, np.array([0, len(raw)]))[0]


def _halves(text: str) -> tuple[np.ndarray, ...]:
    """Three-word runs of the question, of the answer and of the item; one of fewer words is filled up from the other."""
    question, answer = (_words(x) for x in question_and_answer(text))
    every = _words(text)
    question, answer = (w if len(w) >= 3 else part for w, part in ((question, every[:3]), (answer, every[-3:])))
    return tuple(np.unique(textvec.shingle_hashes(w, np.array([len(w)]), 3)[0]) for w in (question, answer, every))


@dataclass
class Index:
    """Postings by term, then unit; one more row ends them: no term, a unit behind all others, no impact.

    greatest and block_greatest: the greatest impact of a posting's term, in all units and in the posting's block.
    """

    terms: np.ndarray
    first: np.ndarray
    term: np.ndarray
    unit: np.ndarray
    impact: np.ndarray
    greatest: np.ndarray
    block_greatest: np.ndarray
    post_key: np.ndarray
    block_key: np.ndarray
    block_max: np.ndarray
    n_blocks: int
    item_of: np.ndarray
    question: list
    answer: list
    whole: list
    item_ids: list
    threshold: float


def _units(text: str) -> list[np.ndarray]:
    """The words of each unit of an item's text, which is in lower case."""
    words = _words(text)
    return np.array_split(words, -(-len(words) // UNIT_WORDS)) if len(words) else []


@dataclass
class Statistics:
    """Of all units of a benchmark: how many, their mean length, and in how many a term occurs, by its hash."""

    n_units: int
    mean: float
    frequency: dict[int, int]


def build_index(items: list[tuple], threshold: float = THRESHOLD, statistics: Statistics | None = None) -> Index:
    """items: (item_id, text); statistics: of the benchmark, if items are a part of it."""
    items = [(i, pc.utf8_lower(t).as_py()) for i, t in items if t and re.search(r"[^\W_]", t)]
    units, owner = [], []
    for k, (_, text) in enumerate(items):
        for part in _units(text):
            units.append(part)
            owner.append(k)
    lengths = np.array([len(u) for u in units], np.float64)
    counts = [np.unique(u, return_counts=True) for u in units]
    unit = np.repeat(np.arange(len(units)), [len(c[0]) for c in counts])
    word = np.concatenate([c[0] for c in counts]) if units else np.zeros(0, np.uint64)
    tf = np.concatenate([c[1] for c in counts]).astype(np.float64) if units else np.zeros(0)
    terms, term, df = np.unique(word, return_inverse=True, return_counts=True)
    n_units, mean = len(units), lengths.mean() if len(units) else 1.0
    if statistics is not None:
        n_units, mean = statistics.n_units, statistics.mean
        df = np.array([statistics.frequency[int(t)] for t in terms], np.int64)
    idf = np.log(1 + (n_units - df + 0.5) / (df + 0.5))
    score = idf[term] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * lengths[unit] / mean))
    impact = score / np.bincount(unit, score, len(units))[unit] if len(units) else score
    by = np.lexsort((unit, term))
    term, unit, impact = term[by], unit[by], impact[by]
    greatest = np.zeros(len(terms))
    np.maximum.at(greatest, term, impact)
    n_blocks = len(units) // BLOCK_UNITS + 1
    key, place = np.unique(term * n_blocks + unit // BLOCK_UNITS, return_inverse=True)
    block_max = np.zeros(len(key))
    np.maximum.at(block_max, place, impact)
    halves = [_halves(t) for _, t in items]
    end = lambda values, last: np.append(values, np.array(last, values.dtype))
    return Index(
        terms, np.searchsorted(term, np.arange(len(terms) + 1)), end(term, len(terms)), end(unit, len(units)), end(impact, 0), end(greatest[term], 0),
        end(block_max[place], 0), term * len(units) + unit, key, block_max, n_blocks, np.array(owner, np.int64),
        [q for q, _, _ in halves], [a for _, a, _ in halves], [w for _, _, w in halves], [i for i, _ in items], threshold,
    )


def _lookup(sorted_keys: np.ndarray, values: np.ndarray, keys: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(sorted_keys, keys), len(sorted_keys) - 1)
    return np.where(sorted_keys[at] == keys, values[at], 0.0)


def _next_at(index: Index, post: np.ndarray, goal: np.ndarray) -> np.ndarray:
    """The first posting behind each given one, in its list, of a unit that isn't before the goal."""
    term, out = index.term[post], post + 1
    far = np.flatnonzero((index.term[out] == term) & (index.unit[out] < goal))
    out[far] = np.searchsorted(index.post_key, term[far] * len(index.item_of) + goal[far])
    return np.where(index.term[out] == term, out, len(index.post_key))


def search_passages(index: Index, begin: np.ndarray, terms: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(passage, unit, score) above the threshold; passage k has the distinct terms terms[begin[k]:begin[k + 1]]."""
    found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
    for k in range(0, len(begin) - 1, PASSAGES):
        some = begin[k : k + PASSAGES + 1]
        for passage, unit, score in _walk(index, some - some[0], terms[some[0] : some[-1]]):
            found.append((passage + k, unit, score))
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def _walk(index: Index, begin: np.ndarray, terms: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """What each step of all passages finds.

    A row of `stand` has a passage's lists, each as its unit and posting in one number, so a sorted row has the
    lists in the order of their units.
    """
    least, n_units, last = index.threshold - 2e-9, len(index.item_of), len(index.post_key)
    bits = last.bit_length()
    encode = lambda post: index.unit[post] << bits | post
    size = np.diff(begin)
    row = np.repeat(np.arange(len(size)), size)
    lane = np.flatnonzero(np.bincount(row, index.greatest[index.first[terms]], len(size)) >= least)
    place = np.full(len(size), -1)
    place[lane] = np.arange(len(lane))
    stand = np.full((len(lane), int(size[lane].max(initial=0))), encode(np.int64(last)))
    of, column = place[row], np.arange(len(row)) - np.repeat(begin[:-1], size)
    stand[of[of >= 0], column[of >= 0]] = encode(index.first[terms[of >= 0]])
    while True:
        stand.sort(axis=1)
        post = stand & ((1 << bits) - 1)
        pivot = (np.cumsum(index.greatest[post], axis=1) < least).sum(axis=1)
        on = pivot < stand.shape[1]
        if not on.any():
            break
        # passages that are done go, and columns where all lists have ended
        used = int((stand[on, :] >> bits < n_units).any(axis=0).sum())
        lane, pivot, stand, post = lane[on], pivot[on], stand[on, :used], post[on, :used]
        unit = stand >> bits
        here = unit[np.arange(len(lane)), pivot]
        up_to = unit <= here[:, None]
        r, c = np.nonzero(up_to)
        q, target = post[r, c], here[r]
        bound = index.block_greatest[q]
        behind = np.flatnonzero(index.unit[q] // BLOCK_UNITS < target // BLOCK_UNITS)
        bound[behind] = _lookup(index.block_key, index.block_max, index.term[q[behind]] * index.n_blocks + target[behind] // BLOCK_UNITS)
        good = np.bincount(r, bound, len(lane)) >= least
        beyond = np.where(up_to, n_units, unit).min(axis=1)
        goal = np.where(good, here, np.minimum((here // BLOCK_UNITS + 1) * BLOCK_UNITS, beyond))[r]
        late = np.flatnonzero(index.unit[q] < goal)
        q[late] = _next_at(index, q[late], np.minimum(goal[late], n_units))
        scored = np.flatnonzero(good[r] & (index.unit[q] == target))
        score = np.bincount(r[scored], index.impact[q[scored]], len(lane))
        hit = np.flatnonzero(score >= index.threshold - 1e-9)
        yield lane[hit], here[hit], score[hit]
        q[scored] = _next_at(index, q[scored], target[scored] + 1)
        stand[r, c] = encode(q)


def _search(index: Index):
    n_units = len(index.item_of)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            ids, keys = batch.column("doc_id"), batch.column("key")
            for a, _, raw, at in textvec.pieces(pc.utf8_lower(batch.column("text")), TOGETHER):
                words, n = hashed_words(raw, at)
                if not len(words) or not n_units:
                    continue
                place = np.minimum(np.searchsorted(index.terms, words), len(index.terms) - 1)
                known = np.flatnonzero(index.terms[place] == words)
                begin = np.cumsum(n) - n
                in_row = np.searchsorted(begin + n, known, side="right")
                stride = (known - begin[in_row]) // STRIDE
                # a word is in the passages that begin with its stride and with the one before
                passages = np.maximum(-(-n // STRIDE) - 1, 1)
                first = np.cumsum(passages) - passages
                number = np.concatenate([first[in_row] + stride, first[in_row] + stride - 1])
                inside = np.concatenate([stride < passages[in_row], stride > 0])
                distinct = np.unique(number[inside] * len(index.terms) + np.tile(place[known], 2)[inside])
                bounds = np.searchsorted(distinct, np.arange(passages.sum() + 1) * len(index.terms))
                hits, units, scores = search_passages(index, bounds, distinct % len(index.terms))
                rows_hit = np.searchsorted(first, hits, side="right") - 1
                best: dict[tuple[int, int], float] = {}
                for key, score in zip(zip(rows_hit.tolist(), index.item_of[units].tolist(), strict=True), scores.tolist(), strict=True):
                    best[key] = max(best.get(key, 0.0), score)
                runs: dict[int, np.ndarray] = {}
                for (r, item), score in sorted(best.items()):
                    if r not in runs:
                        runs[r] = np.unique(textvec.shingle_hashes(words[begin[r] : begin[r] + n[r]], n[r : r + 1], 3)[0])
                    share = [float(np.isin(x, runs[r]).mean()) if len(x) else 1.0 for x in (index.question[item], index.answer[item], index.whole[item])]
                    rows.append((ids[a + r].as_py(), keys[a + r].as_py(), index.item_ids[item], min(score, 1.0), *share))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 7
            kinds = [pa.int64(), pa.int64(), pa.int64(), *[pa.float64()] * 4]
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["doc_id", "key", "item_id", "score", "question_overlap", "answer_overlap", "item_overlap"]
            )

    return run


def _unit_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(term, units that hold it, -) of items, and for each batch one row without a term: (-, units, words)."""
    for batch in batches:
        frequency: dict[int, int] = {}
        n_units = n_words = 0
        for text in pc.utf8_lower(batch.column("text")).to_pylist():
            for unit in _units(text) if text else []:
                n_units, n_words = n_units + 1, n_words + len(unit)
                for t in np.unique(unit).view(np.int64).tolist():
                    frequency[t] = frequency.get(t, 0) + 1
        yield pa.RecordBatch.from_arrays(
            [pa.array([None, *frequency], pa.int64()), pa.array([n_units, *frequency.values()], pa.int64()), pa.array([n_words] + [0] * len(frequency), pa.int64())],
            names=["term", "units", "words"],
        )


def _statistics(part: DataFrame, whole: DataFrame) -> Statistics:
    """The benchmark's statistics as far as a slice's terms need them; whole: (term, units, words) of all items."""
    total = whole.where("term is null").agg(F.sum("units"), F.sum("words")).first()
    mine = part.select("text").mapInArrow(_unit_terms, "term long, units long, words long").where("term is not null").select("term").distinct()
    rows = whole.where("term is not null").join(mine, "term").select("term", "units").collect()
    frequency = {r["term"] & 0xFFFFFFFFFFFFFFFF: r["units"] for r in rows}
    return Statistics(total[0] or 0, (total[1] or 0) / max(total[0] or 0, 1), frequency)


def retrieve(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, slice_bytes: int = SLICE_BYTES) -> DataFrame:
    """(doc_id, item_id, score, and the overlaps of question, answer and item) of all items above the threshold."""
    return _retrieved(docs, items, threshold, slice_bytes).drop("key")


def _retrieved(docs: DataFrame, items: DataFrame, threshold: float, slice_bytes: int = SLICE_BYTES) -> DataFrame:
    """retrieve with key, a hash of the document's text."""
    docs = docs.select("doc_id", F.xxhash64("text").alias("key"), "text")
    sized = items.select("item_id", "text", F.octet_length("text").alias("size")).where("size > 0")
    total = sized.agg(F.sum("size")).first()[0] or 0
    n_slices = -(-total // slice_bytes) or 1
    whole = None
    if n_slices > 1:
        whole = sized.select("text").mapInArrow(_unit_terms, "term long, units long, words long").groupBy("term").agg(F.sum("units").alias("units"), F.sum("words").alias("words"))
        whole = materialize(whole, "item-terms")
    out = None
    for k in range(n_slices):
        part = sized if n_slices == 1 else sized.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n_slices)) == k)
        rows = sorted(((r["item_id"], r["text"]) for r in part.collect()), key=lambda r: (r[0] is None, r))
        statistics = None if whole is None else _statistics(part, whole)
        index = build_index(rows, threshold, statistics)
        found = docs.mapInArrow(_search(index), "doc_id long, key long, item_id long, score double, question_overlap double, answer_overlap double, item_overlap double")
        out = found if out is None else out.unionByName(found)
    return out


def contaminated(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, overlap: float = OVERLAP) -> DataFrame:
    """The retrieved pairs whose question and answer both occur in the document, or the item as a whole but for a word or two."""
    return _confirmed(retrieve(docs, items, threshold), overlap)


def _confirmed(found: DataFrame, overlap: float) -> DataFrame:
    both = (F.col("question_overlap") >= overlap) & (F.col("answer_overlap") >= overlap)
    return found.where(both | (F.col("item_overlap") >= (1 + overlap) / 2))


def drop_contaminated(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, overlap: float = OVERLAP) -> DataFrame:
    """docs without the documents that hold an item; other texts under the same id, or without one, stay."""
    found = _confirmed(_retrieved(docs, items, threshold), overlap)
    bad = materialize(found.select(F.col("doc_id").alias("bad_id"), F.col("key").alias("bad_key")).distinct(), "contaminated")
    return docs.join(bad, docs["doc_id"].eqNullSafe(bad["bad_id"]) & (F.xxhash64(docs["text"]) == bad["bad_key"]), "left_anti")


def op3_decontamination(spark, sf_dir) -> DataFrame:
    docs, items = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    return contaminated(docs, items)
