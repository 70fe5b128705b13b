"""Suffix array of a byte text by two-stage sorting, and common prefixes of neighbours.

A suffix is of the rising kind if it is smaller than its successor, else of the falling kind.  Only
rising suffixes are sorted directly.  One scan over the buckets of first symbols, in order, then places
the falling ones: a falling suffix starts a bucket no smaller than that of its successor, so when a
bucket is reached all its falling suffixes with a smaller second symbol are in place already, and those
that repeat the bucket's own symbol follow in waves.  Each bucket is handled with whole-array operations.

Order is exact to `depth` symbols at least; suffixes that agree further stand in an arbitrary order.
"""

from __future__ import annotations

import numpy as np

#: Symbols of 9 bits in a 64-bit word.
_IN_WORD = 7


def _words(symbols: np.ndarray) -> np.ndarray:
    n = len(symbols)
    padded = np.zeros(n + _IN_WORD, np.uint64)
    padded[:n] = symbols
    out = np.zeros(n, np.uint64)
    for k in range(_IN_WORD):
        out = (out << np.uint64(9)) | padded[k : k + n]
    return out


def _word_at(words: np.ndarray, at: np.ndarray) -> np.ndarray:
    inside = at < len(words)
    out = np.zeros(len(at), np.uint64)
    out[inside] = words[at[inside]]
    return out


def _direct(words: np.ndarray, picked: np.ndarray, depth: int) -> np.ndarray:
    """picked positions in suffix order, word by word; only ties are looked at again."""
    order = picked[np.argsort(words[picked], kind="stable")]
    key = words[order]
    group = np.concatenate(([0], np.cumsum(key[1:] != key[:-1]))) if len(order) else np.zeros(0, np.int64)
    for step in range(_IN_WORD, depth, _IN_WORD):
        same = np.zeros(len(order), bool)
        equal = group[1:] == group[:-1]
        same[1:] |= equal
        same[:-1] |= equal
        tied = np.flatnonzero(same)
        if not len(tied):
            break
        value = _word_at(words, order[tied] + step)
        by = np.lexsort((value, group[tied]))
        order[tied] = order[tied][by]
        full = np.zeros(len(order), np.uint64)
        full[tied] = value[by]
        new = np.concatenate(([False], (group[1:] != group[:-1]) | (full[1:] != full[:-1])))
        group = np.cumsum(new)
    return order


def suffix_array(text: np.ndarray, depth: int = 56) -> np.ndarray:
    """Start positions of the suffixes of text (symbols 0 to 256) in order."""
    n = len(text)
    if n == 0:
        return np.zeros(0, np.int64)
    symbols = text.astype(np.int64)
    # kind: that of the first later place where neighbours differ; the last suffix falls (its successor is empty)
    differs = np.flatnonzero(symbols[:-1] != symbols[1:])
    rising = np.zeros(n, bool)
    if len(differs):
        nearest = np.searchsorted(differs, np.arange(n))
        known = nearest < len(differs)
        at = differs[nearest[known]]
        rising[known] = symbols[at] < symbols[at + 1]
    sizes = np.bincount(symbols, minlength=257)
    bucket_end = np.cumsum(sizes)
    bucket_begin = bucket_end - sizes
    array = np.full(n, -1, np.int64)
    up = np.flatnonzero(rising)
    ordered = _direct(_words(symbols), up, depth)
    risen = np.bincount(symbols[up], minlength=257)
    at = 0
    for s in np.flatnonzero(risen):
        array[bucket_end[s] - risen[s] : bucket_end[s]] = ordered[at : at + risen[s]]
        at += risen[s]
    free = bucket_begin.copy()
    # the last suffix falls and its successor is the empty one, the smallest of all
    array[free[symbols[n - 1]]] = n - 1
    free[symbols[n - 1]] += 1

    def induce(entries: np.ndarray) -> None:
        before = entries[entries > 0] - 1
        before = before[~rising[before]]
        first = symbols[before]
        by = np.argsort(first, kind="stable")
        before, first = before[by], first[by]
        if not len(first):
            return
        cuts = np.flatnonzero(np.concatenate(([True], first[1:] != first[:-1])))
        for a, b in zip(cuts, np.append(cuts[1:], len(first)), strict=True):
            s = first[a]
            array[free[s] : free[s] + b - a] = before[a:b]
            free[s] += b - a

    for s in np.flatnonzero(sizes):
        done = bucket_begin[s]
        while done < free[s]:  # waves of the bucket's own symbol
            wave = array[done : free[s]].copy()
            done = free[s]
            induce(wave)
        if risen[s]:
            induce(array[bucket_end[s] - risen[s] : bucket_end[s]])
    return array


def neighbour_prefixes(text: np.ndarray, array: np.ndarray, cap: int = 56) -> np.ndarray:
    """For each place of the suffix array but the first, the common prefix with the place before, up to cap; 0 first."""
    n = len(array)
    out = np.zeros(n, np.int64)
    if n < 2:
        return out
    words = _words(text.astype(np.int64))
    live = np.arange(1, n)
    for step in range(0, cap, _IN_WORD):
        a, b = array[live] + step, array[live - 1] + step
        differ = _word_at(words, a) ^ _word_at(words, b)
        equal = differ == 0
        # leading symbols that agree in the first word that differs
        top = 63 - np.clip(np.floor(np.log2(np.maximum(differ[~equal], 1).astype(np.float64))), 0, 62).astype(np.int64)
        out[live[~equal]] = step + np.minimum((top - 1) // 9, _IN_WORD - 1)
        live = live[equal]
        out[live] = step + _IN_WORD
        if not len(live):
            break
    longest = n - np.maximum(array[1:], array[:-1])
    out[1:] = np.minimum(np.minimum(out[1:], longest), cap)
    return out
