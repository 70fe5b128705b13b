"""Token counts under a unigram vocabulary, by dynamic programming over a trie of pre-tokens.

Pre-tokens are the words of a text, each with the word-start mark before it, as sentence-piece
vocabularies have it.  The distinct pre-tokens of a batch go into a trie.  A trie node stands for a
prefix; the best segmentation of the prefix depends on nothing else, so its score and its number of
tokens are computed once from the nodes above it, however many pre-tokens share it.  The count is stored
at the nodes where pre-tokens end.  A character that no piece covers falls back to its UTF-8 bytes.

The vocabulary is a public file, read on the driver and sent to the tasks; nothing in it is changed.  It has
no unigram probabilities, so they are estimated: a piece's is its share, plus one, of the pieces into which
the file's own merges cut all words of all texts.  Words are counted before they are cut, per task, and only
one number per piece reaches the driver.  Of equally likely segmentations the one with fewer tokens counts.

Defined cases: a null or empty text has no tokens; repeated rows give a row each; null ids are kept; an
empty table gives an empty result; further columns are ignored.  The table of counted pre-tokens of a
task is bounded; when full it starts anew.  Of a word, states are kept for the first PATH characters and for
as many as the longest piece has, whatever its length.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec

MARK = "▁"
#: Pre-tokens whose counts a task keeps.
KEPT = 400_000
#: Characters of a word whose states the next word may share.
PATH = 1024
#: The public 32,000-piece file as this environment has it; a path elsewhere is a parameter.
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"


def _processor(path: str | None = None, proto: bytes | None = None):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=path) if proto is None else sentencepiece.SentencePieceProcessor(model_proto=proto)


def _piece_uses(proto: bytes):
    """How often each piece (by its id) is used in the words of a task's rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _processor(proto=proto)
        uses = np.zeros(model.get_piece_size(), np.int64)
        words: dict[bytes, int] = {}

        def cut() -> None:
            names = list(words)
            for a in range(0, len(names), 20_000):
                some = names[a : a + 20_000]
                ids = model.encode([w.decode("utf-8", "replace") for w in some], num_threads=1)
                sizes = [len(x) for x in ids]
                flat = np.fromiter((i for x in ids for i in x), np.int64, sum(sizes))
                uses[:] += np.bincount(flat, np.repeat([words[w] for w in some], sizes), len(uses)).astype(np.int64)
            words.clear()

        for batch in batches:
            for _, _, raw, at in textvec.pieces(batch.column("text")):
                starts, ends, _ = textvec.word_bounds(raw, at)
                _, first, n = np.unique(textvec.span_hashes(raw, starts, ends), return_index=True, return_counts=True)
                text = raw.tobytes()
                for a, b, k in zip(starts[first].tolist(), ends[first].tolist(), n.tolist(), strict=True):
                    word = text[a:b]
                    words[word] = words.get(word, 0) + k
                if len(words) > KEPT:
                    cut()
        cut()
        some = np.flatnonzero(uses)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(uses[some])], names=["piece", "n"])

    return run


def estimate(docs: DataFrame, model: str = DEFAULT_MODEL) -> dict[str, float]:
    """Piece to log probability, from all texts of docs(text)."""
    file = _processor(model)
    used = docs.select("text").mapInArrow(_piece_uses(file.serialized_model_proto()), "piece long, n long").groupBy("piece").agg(F.sum("n").alias("n")).collect()
    uses = {r["piece"]: r["n"] for r in used}
    plain = [i for i in range(file.get_piece_size()) if not (file.is_control(i) or file.is_unknown(i) or file.is_byte(i))]
    total = math.log(sum(uses.get(i, 0) + 1 for i in plain))
    return {file.id_to_piece(i): math.log(uses.get(i, 0) + 1) - total for i in plain}


class Counter:
    """Counts of pre-tokens by a depth-first walk of their trie."""

    def __init__(self, vocabulary: dict[str, float]):
        self.vocabulary = vocabulary
        self.longest = max(map(len, vocabulary), default=1)
        self.fallback = min(vocabulary.values(), default=0.0) - 10.0
        # every end of a piece, with its score if it is a piece itself: longer ones are tried while there is such an end
        self.tails: dict[str, float | None] = {}
        for p in vocabulary:
            for k in range(1, len(p)):
                self.tails.setdefault(p[k:], None)
        self.tails.update(vocabulary)
        self.nodes = 0

    def count(self, words: list[str]) -> list[int]:
        """Numbers of tokens of words, which must be sorted: the path to the last one is the live part of the trie."""
        out = []
        path = ""
        scores, sizes = [0.0], [0]  # of the best segmentation of each prefix of the path
        tail, fallback, window = self.tails.get, self.fallback, self.longest
        for word in words:
            token = MARK + word
            keep = 0
            stop = min(len(path), len(token), PATH)
            while keep < stop and path[keep] == token[keep]:
                keep += 1
            del scores[keep + 1 :], sizes[keep + 1 :]
            cut = 0  # states before this place are gone
            for i in range(keep, len(token)):
                at = i - cut
                c = token[i]
                size = 1 if c == MARK else len(c.encode())
                best, n = scores[at] + fallback * size, sizes[at] + size
                begin = i
                while begin >= 0:
                    p = tail(token[begin : i + 1], 0)
                    if p is not None:
                        if p == 0:
                            break
                        other = scores[begin - cut] + p
                        if other > best or (other == best and sizes[begin - cut] + 1 < n):
                            best, n = other, sizes[begin - cut] + 1
                    begin -= 1
                scores.append(best)
                sizes.append(n)
                if at > 4 * PATH + window:
                    drop = at - PATH - window
                    del scores[:drop], sizes[:drop]
                    cut += drop
            self.nodes += len(token) - keep
            out.append(sizes[-1])
            path = token
            if cut:
                path, scores, sizes = "", [0.0], [0]
        return out


def _count(vocabulary: dict[str, float]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = Counter(vocabulary)
        known, values = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        for batch in batches:
            for a, b, raw, at in textvec.pieces(batch.column("text")):
                starts, ends, n = textvec.word_bounds(raw, at)
                words = textvec.span_hashes(raw, starts, ends)
                distinct, first, place = np.unique(words, return_index=True, return_inverse=True)
                where = np.minimum(np.searchsorted(known, distinct), max(len(known) - 1, 0))
                new = known[where] != distinct if len(known) else np.ones(len(distinct), bool)
                counts = np.zeros(len(distinct), np.int64)
                if len(known):
                    counts[~new] = values[where[~new]]
                if new.any():
                    text = raw.tobytes()
                    fresh = [(text[starts[i] : ends[i]].decode("utf-8", "replace"), j) for i, j in zip(first[new], np.flatnonzero(new), strict=True)]
                    fresh.sort()
                    counts[[j for _, j in fresh]] = counter.count([w for w, _ in fresh])
                    if len(known) + len(fresh) > KEPT:
                        known, values = distinct, counts
                    else:
                        known, values = np.concatenate([known, distinct[new]]), np.concatenate([values, counts[new]])
                        order = np.argsort(known, kind="stable")
                        known, values = known[order], values[order]
                total = np.concatenate(([0], np.cumsum(counts[place])))
                edge = np.concatenate(([0], np.cumsum(n)))
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(a, b - a), pa.array(n.astype(np.int64)), pa.array(np.diff(total[edge]))],
                    names=["doc_id", "n_pretokens", "n_tokens"],
                )

    return run


def token_counts(docs: DataFrame, model: str = DEFAULT_MODEL, vocabulary: dict[str, float] | None = None) -> DataFrame:
    """For each row of docs(doc_id, text): doc_id, n_pretokens, n_tokens; vocabulary: piece to log probability, else estimated."""
    vocabulary = estimate(docs, model) if vocabulary is None else vocabulary
    return docs.select("doc_id", "text").mapInArrow(_count(vocabulary), "doc_id long, n_pretokens long, n_tokens long")


def op10_token_counts(spark, sf_dir) -> DataFrame:
    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"))
