"""Language identification with a linear-chain conditional random field over words.

A word's potentials are sums of learned weights of hashed features: its prefixes and suffixes of one to
three bytes, its byte bigrams and trigrams (mean over the word), the word itself, and the lexicons that it
stands in: a language's lexicon has the words that occur in two of its training texts at least; a word in none
has a feature of its own.  The weights of a chain's first language and of the transitions between the languages
of neighbouring words are learned too.  A chain is a line of text, cut every `CHAIN` words.  Forward-backward gives each word's probability
of each language; a document's language has the largest mean probability, which is its score.

Training uses at most `MAX_TRAINING_DOCS` labelled rows, those with the smallest hash of id and text, and
of each at most `MAX_TRAINING_BYTES` bytes; chains are built from pieces of documents of different
languages as well, so that transitions away from a language are seen.  Everything else covers all data.

Defined cases: a null text, or one without letters (of any alphabet), is `und` with score 0; repeated rows are scored alike;
a table without a usable label gives `und` throughout; an empty table gives an empty result; further
columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec

SPACE_BITS, CHAIN = 16, 128
MAX_TRAINING_DOCS, MAX_TRAINING_BYTES, EPOCHS = 1200, 1500, 6
_MASK = np.uint64((1 << SPACE_BITS) - 1)
_LETTER = np.array([chr(b).isalpha() if b < 128 else False for b in range(256)])


@dataclass
class Model:
    labels: list[str]
    weights: np.ndarray  # features x labels
    transitions: np.ndarray  # from x to
    first: np.ndarray
    words: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))  # hashes of the lexicons' words, sorted
    known: np.ndarray | None = None  # words x labels: whose lexicon has the word
    lexicon: np.ndarray | None = None  # (labels + 1) x labels: weights of standing in a lexicon, or in none


def _slots(h: np.ndarray, kind: int) -> np.ndarray:
    return ((textvec.mix(h + np.uint64(kind * 0x51ED270B)) >> np.uint64(20)) & _MASK).astype(np.int64)


def _grams(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    b = raw.astype(np.uint64)
    two = np.zeros(len(b), np.uint64)
    two[:-1] = b[:-1] << np.uint64(8) | b[1:]
    three = two.copy()
    three[:-2] |= b[2:] << np.uint64(16)
    return two, three


def _features(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per word: slots of the affixes and of the word (words x 7); per byte: slots of the bigram and trigram there."""
    size = ends - starts
    padded = np.concatenate([raw, np.zeros(4, np.uint8)]).astype(np.uint64)
    cols = []
    prefix = np.zeros(len(starts), np.uint64)
    suffix = np.zeros(len(starts), np.uint64)
    for k in range(3):
        has = size > k
        prefix = np.where(has, (prefix << np.uint64(8)) | padded[np.minimum(starts + k, len(raw))], prefix)
        suffix = np.where(has, (suffix << np.uint64(8)) | padded[np.maximum(ends - 1 - k, 0)], suffix)
        cols += [_slots(prefix, 1 + k), _slots(suffix, 5 + k)]
    cols.append(_slots(textvec.span_hashes(raw, starts, ends), 9))
    two, three = _grams(raw)
    return np.stack(cols, axis=1), _slots(two, 11), _slots(three, 13)


def lexicon_features(model: Model, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """words x (labels + 1): whether a word is in each language's lexicon, and whether it is in none."""
    n = len(model.labels)
    out = np.zeros((len(starts), n + 1), np.float32)
    if len(model.words) and len(starts):
        h = textvec.span_hashes(raw, starts, ends)
        at = np.minimum(np.searchsorted(model.words, h), len(model.words) - 1)
        hit = model.words[at] == h
        out[hit, :n] = model.known[at[hit]]
    out[:, n] = ~out[:, :n].any(axis=1)
    return out


def potentials(model: Model, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """words x labels."""
    weights = model.weights
    words, two, three = _features(raw, starts, ends)
    out = np.zeros((len(starts), weights.shape[1]), np.float32)
    if model.lexicon is not None:
        out += lexicon_features(model, raw, starts, ends) @ model.lexicon.astype(np.float32)
    for c in range(words.shape[1]):
        out += weights[words[:, c]]
    size = (ends - starts)[:, None].astype(np.float32)
    for slots, width in ((two, 2), (three, 3)):
        total = np.concatenate([np.zeros((1, weights.shape[1]), np.float64), np.cumsum(weights[slots], axis=0, dtype=np.float64)])
        last = np.maximum(ends - width + 1, starts)
        out += ((total[last] - total[starts]) * (4.0 / np.maximum(size - width + 1, 1))).astype(np.float32)
    return out


def lexicons(texts: list[tuple[bytes, int]], n_labels: int) -> tuple[np.ndarray, np.ndarray]:
    """(sorted word hashes, words x labels) of texts(bytes, label): the words that at least two texts of a label hold."""
    seen: list[Counter] = [Counter() for _ in range(n_labels)]
    for raw_text, label in texts:
        raw = np.frombuffer(raw_text, np.uint8)
        starts, ends, _ = textvec.word_bounds(raw, np.array([0, len(raw)]))
        seen[label].update(np.unique(textvec.span_hashes(raw, starts, ends)).tolist())
    kept = [np.array(sorted(w for w, k in c.items() if k >= 2), np.uint64) for c in seen]
    words = np.unique(np.concatenate(kept))
    return words, np.stack([np.isin(words, k) for k in kept], axis=1)


def chains(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, row of each word, chain of each word, place in the chain): lines, cut every CHAIN words."""
    starts, ends, n = textvec.word_bounds(raw, at)
    row = np.repeat(np.arange(len(n)), n)
    line = np.searchsorted(np.flatnonzero(raw == 10), starts)
    new = np.ones(len(starts), bool)
    new[1:] = (line[1:] != line[:-1]) | (row[1:] != row[:-1])
    begin = np.flatnonzero(new)
    place = np.arange(len(starts)) - np.repeat(begin, np.diff(np.append(begin, len(starts))))
    chain = np.cumsum(new | (place % CHAIN == 0)) - 1
    return starts, ends, row, chain, place % CHAIN


def forward_backward(model: Model, scores: np.ndarray, chain: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words x labels) probabilities, and the expected transitions summed over all chains."""
    n_labels = scores.shape[1]
    out = np.zeros_like(scores)
    moves = np.zeros((n_labels, n_labels))
    if not len(scores):
        return out, moves
    begin = np.flatnonzero(place == 0)
    size = np.diff(np.append(begin, len(scores)))
    order = np.argsort(-size, kind="stable")
    begin, size = begin[order], size[order]
    e = np.exp(scores - scores.max(axis=1, keepdims=True))
    step = np.exp(model.transitions - model.transitions.max()).astype(np.float32)
    longest = int(size[0])
    alive = np.searchsorted(-size, -np.arange(1, longest + 1), side="right")
    alpha = np.zeros_like(scores)
    a = np.exp(model.first - model.first.max()).astype(np.float32) * e[begin]
    a /= a.sum(axis=1, keepdims=True)
    alpha[begin] = a
    for t in range(1, longest):
        k = alive[t]
        a = (a[:k] @ step) * e[begin[:k] + t]
        a /= a.sum(axis=1, keepdims=True)
        alpha[begin[:k] + t] = a
    beta = np.ones((len(begin), n_labels), np.float32)
    for t in range(longest - 1, -1, -1):
        k = alive[t]
        p = alpha[begin[:k] + t] * beta[:k]
        out[begin[:k] + t] = p / p.sum(axis=1, keepdims=True)
        if t:
            ahead = e[begin[:k] + t] * beta[:k]
            pair = alpha[begin[:k] + t - 1][:, :, None] * step * ahead[:, None, :]
            moves += (pair / pair.sum(axis=(1, 2), keepdims=True)).sum(axis=0)
            b = ahead @ step.T
            beta[:k] = b / b.sum(axis=1, keepdims=True)
    return out, moves


def train(rows: list[tuple[str, str]], epochs: int = EPOCHS, seed: int = 11) -> Model | None:
    """rows: (text, language).  Adagrad on the chains' conditional likelihood, in batches of texts."""
    labels = sorted({lang for _, lang in rows})
    if not labels:
        return None
    n = len(labels)
    rng = np.random.Generator(np.random.PCG64(seed))
    model = Model(labels, np.zeros((1 << SPACE_BITS, n), np.float32), np.zeros((n, n)), np.zeros(n))
    cut = [(text.encode()[:MAX_TRAINING_BYTES].decode("utf-8", "ignore"), labels.index(lang)) for text, lang in rows]
    model.words, model.known = lexicons([(text.encode(), y) for text, y in cut], n)
    model.lexicon = np.zeros((n + 1, n))
    texts: list[list[tuple[bytes, int]]] = []
    for text, y in cut:
        for line in text.split("\n"):
            if words := line.split():
                texts.append([(w.encode(), y) for w in words])
    mixed = []
    for k in rng.permutation(len(texts))[: len(texts) // 4]:  # lines of two languages run together
        other = texts[int(rng.integers(len(texts)))]
        mixed.append(texts[k][:12] + other[:12])
    texts += mixed
    seen_w = np.full_like(model.weights, 1e-6)
    seen = {"transitions": np.full((n, n), 1e-6), "first": np.full(n, 1e-6), "lexicon": np.full((n + 1, n), 1e-6)}
    for _ in range(epochs):
        order = rng.permutation(len(texts))
        for lo in range(0, len(order), 256):
            lines = [texts[k] for k in order[lo : lo + 256]]
            raw = np.frombuffer(b"\n".join(b" ".join(w for w, _ in line) for line in lines), np.uint8)
            truth = np.array([y for line in lines for _, y in line])
            starts, ends, _, chain, place = chains(raw, np.array([0, len(raw)]))
            p, moves = forward_backward(model, potentials(model, raw, starts, ends), chain, place)
            want = np.zeros_like(p)
            want[np.arange(len(truth)), truth] = 1
            g = (want - p) / len(lines)
            slots, two, three = _features(raw, starts, ends)
            grad = np.zeros_like(model.weights)
            for c in range(slots.shape[1]):
                for y in range(n):
                    grad[:, y] += np.bincount(slots[:, c], g[:, y], 1 << SPACE_BITS)
            size = (ends - starts)[:, None]
            for s, width in ((two, 2), (three, 3)):
                many = np.maximum(np.maximum(ends - width + 1, starts) - starts, 0)
                at = np.repeat(starts - (np.cumsum(many) - many), many) + np.arange(many.sum())
                part = np.repeat(g * (4.0 / np.maximum(size - width + 1, 1)), many, axis=0)
                for y in range(n):
                    grad[:, y] += np.bincount(s[at], part[:, y], 1 << SPACE_BITS)
            grad -= 1e-5 * model.weights
            seen_w += grad * grad
            model.weights += (0.3 * grad / np.sqrt(seen_w)).astype(np.float32)
            true_moves = np.zeros((n, n))
            same = chain[1:] == chain[:-1]
            np.add.at(true_moves, (truth[:-1][same], truth[1:][same]), 1)
            begins = np.flatnonzero(place == 0)
            steps = {
                "transitions": (true_moves - moves) / len(lines),
                "first": (np.bincount(truth[begins], minlength=n) - p[begins].sum(axis=0)) / len(lines),
                "lexicon": lexicon_features(model, raw, starts, ends).T @ g,
            }
            for name, step in steps.items():
                seen[name] += step * step
                setattr(model, name, getattr(model, name) + 0.1 * step / np.sqrt(seen[name]))
    return model


def label_words(model: Model, text: str) -> list[tuple[str, str, float]]:
    """(word, language, probability) of each word of a text."""
    raw = np.frombuffer(text.encode(), np.uint8)
    starts, ends, _, chain, place = chains(raw, np.array([0, len(raw)]))
    p, _ = forward_backward(model, potentials(model, raw, starts, ends), chain, place)
    best = p.argmax(axis=1)
    return [(raw[a:b].tobytes().decode(), model.labels[k], float(q[k])) for a, b, k, q in zip(starts, ends, best, p, strict=True)]


def _predict(model: Model | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, raw, at in textvec.pieces(batch.column("text")):
                rows = b - a
                letters = np.diff(np.concatenate(([0], np.cumsum(_LETTER[raw])))[at]) > 0
                for k in np.flatnonzero(~letters):
                    if (raw[at[k] : at[k + 1]] > 127).any():
                        letters[k] = any(map(str.isalpha, raw[at[k] : at[k + 1]].tobytes().decode("utf-8", "ignore")))
                pred, score = np.full(rows, "und", object), np.zeros(rows)
                if model is not None:
                    starts, ends, row, chain, place = chains(raw, at)
                    p, _ = forward_backward(model, potentials(model, raw, starts, ends), chain, place)
                    total = np.stack([np.bincount(row, p[:, y], rows) for y in range(p.shape[1])], axis=1)
                    mean = total / np.maximum(np.bincount(row, minlength=rows), 1)[:, None]
                    best = mean.argmax(axis=1)
                    pred[letters] = np.array(model.labels, object)[best[letters]]
                    score[letters] = np.clip(mean[np.arange(rows), best][letters], 0, 1)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(a, rows), batch.column("held_out").slice(a, rows), pa.array(pred, pa.string()), pa.array(score)],
                    names=["doc_id", "held_out", "lang_pred", "score"],
                )

    return run


def training_rows(docs: DataFrame, max_docs: int = MAX_TRAINING_DOCS) -> list[tuple[str, str]]:
    """At most max_docs labelled rows that are not held out."""
    usable = docs.where("not held_out and lang is not null and text is not null")
    picked = usable.select(F.substr("text", F.lit(1), F.lit(MAX_TRAINING_BYTES)).alias("text"), "lang", F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 40)).alias("h"))
    # a few times as many rows as wanted come before the sort, however many there are
    share = min(1.0, 4 * max_docs / max(usable.count(), 1))
    rows = picked.where(F.col("h") < int(share * (1 << 40))).orderBy("h", "lang", "text").limit(max_docs).collect()
    return sorted((r["text"], r["lang"]) for r in rows)


def identify(docs: DataFrame, max_docs: int = MAX_TRAINING_DOCS) -> DataFrame:
    """For each row of docs(doc_id, text, lang): doc_id, held_out, lang_pred, score.  Learns from the rows not held out."""
    held = F.pmod(F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")), F.lit(4)) == 2
    docs = docs.select("doc_id", "text", "lang", F.coalesce(held, F.lit(False)).alias("held_out"))
    model = train(training_rows(docs, max_docs))
    return docs.select("doc_id", "text", "held_out").mapInArrow(_predict(model), "doc_id long, held_out boolean, lang_pred string, score double")


def op8_language_id(spark, sf_dir) -> DataFrame:
    return identify(spark.read.parquet(f"{sf_dir}/documents.parquet"))
