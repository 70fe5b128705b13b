"""Exact substring deduplication with sorted suffixes.

A byte goes if a string of `length` (50) bytes that covers it also starts in a document with a smaller
id.  Sorting every suffix of a corpus would ship each byte many times over, so the sort is given only
places that can matter:

1. Equal texts form a class; only the document with the smallest id is looked into.
2. Every 50-byte string holds an anchor: its 24-byte gram of least hash.  Equal strings have equal
   anchors.  Anchors that occur in one text only are out.  A map task sends one packed entry per gram
   and group of texts, so a gram of a third of all documents costs one entry a task.
3. Around each anchor that is left lies a context of up to 76 bytes with all strings that it stands for.
   Equal contexts in a task are one entry, sent with the smallest id; the others are covered already.
4. Contexts with the same gram meet in one task.  Where a gram has several contexts they are laid end to
   end, their suffixes are put in order by two-stage sorting, and strings with a common prefix of 50
   bytes or more with a neighbour form a run, whose smallest id decides.

Map tasks pack what they send by bucket.  Buckets, and what a task packs at once, grow with the square root of
the input (16 MB of text at 30 GB, 1 GB at 100 TB), so packed rows are of one size and their number grows
as the input does; a worker needs some three times a bucket.  A gram that many texts have with ever other bytes
beside it has all its contexts in one bucket.

Defined cases: a null text is empty; a text of under 50 bytes loses nothing; rows with the same id never
remove each other's bytes; a null id counts as the greatest; repeated rows give a row each; an empty
table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import suffix_sort, textvec
from .shared import materialize

GRAM = 24
#: Text bytes that share one bucket of grams, and that a map task works on before it sends, at least; and what
#: the input's bytes are multiplied by before the root is taken.
BUCKET_BYTES, PACKED_BYTES = 16 << 20, 8192
_IDENT = 1 << 32
_LAST_ID = (1 << 63) - 1
_SORT_BYTES = 1 << 19


def _sliding(values: np.ndarray, width: int, least: bool) -> np.ndarray:
    pick = np.minimum if least else np.maximum
    out, have = values, 1
    while have < width:
        step = min(have, width - have)
        out = pick(out[: len(out) - step], out[step:])
        have += step
    return out


def anchors(raw: np.ndarray, at: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions, gram hashes): every string of length bytes inside a row has one of them at least."""
    n, span = len(raw), length - GRAM + 1
    if n < length:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    up, down = textvec._powers(n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[:n], out=total[1:])
    grams = textvec.mix((total[GRAM:] - total[:-GRAM]) * down[: n - GRAM + 1])
    rank = (grams >> np.uint64(32)).astype(np.uint32)
    least = _sliding(rank, span, True)
    mark = np.zeros(len(least) + 1, np.int32)
    cuts = at[1:-1]
    np.add.at(mark, np.clip(cuts - length + 1, 0, len(least)), 1)
    np.add.at(mark, np.clip(cuts, 0, len(least)), -1)
    least[np.cumsum(mark[:-1]) > 0] = 0
    rim = np.zeros(span - 1, np.uint32)
    most = _sliding(np.concatenate([rim, least, rim]), span, False)
    found = np.flatnonzero((most == rank) & (most > 0))
    return found, grams[found]


def _gram_ids(grams: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket and 32 further bits of a gram in one number, ident * buckets + bucket."""
    m = textvec.mix(grams ^ np.uint64(0x632BE59BD9B4E019))
    k = np.uint64(buckets)
    return ((m // k) % np.uint64(_IDENT)) * k + m % k


def _runs(*keys: np.ndarray) -> np.ndarray:
    """Starts of the runs of equal keys."""
    if not len(keys[0]):
        return np.zeros(0, np.int64)
    new = np.zeros(len(keys[0]), bool)
    new[0] = True
    for k in keys:
        new[1:] |= k[1:] != k[:-1]
    return np.flatnonzero(new)


def _ends(cut: np.ndarray, n: int) -> np.ndarray:
    return np.append(cut[1:], n) if len(cut) else cut


_GRAMS = "bucket int, key long, idents binary, counts binary, keys binary"


def _gram_batch(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
    return pa.RecordBatch.from_arrays(
        [pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int64()), *(pa.array(c, pa.binary()) for c in cols[2:])],
        names=["bucket", "key", "idents", "counts", "keys"],
    )


def bucket_bytes(total: int) -> int:
    return max(BUCKET_BYTES, math.isqrt(total * PACKED_BYTES))


def _grams(length: int, buckets: int, flush_bytes: int):
    """Packed entries for the buckets, and (key, grams) that are known to be shared already."""

    def flush(ids: list, keys: list) -> Iterator[pa.RecordBatch]:
        if not ids:
            return
        g, k = np.concatenate(ids), np.concatenate(keys)
        order = np.lexsort((k, g))
        g, k = g[order], k[order]
        first = _runs(g, k)
        g, k = g[first], k[first]
        first = _runs(g)
        size = np.diff(np.append(first, len(g)))
        many = np.repeat(size > 1, size)
        rows = []
        by = np.argsort(k[many], kind="stable")
        sk, sg = k[many][by], g[many][by]
        cut = _runs(sk)
        for a, b in zip(cut, _ends(cut, len(sk)), strict=True):
            rows.append((None, int(sk[a].view(np.int64)), sg[a:b].tobytes(), None, None))
        g, k = g[first], k[first]
        bucket = (g % np.uint64(buckets)).astype(np.int64)
        order = np.lexsort((k, bucket))
        g, k, bucket = g[order], k[order], bucket[order]
        cut = _runs(bucket)
        for a, b in zip(cut, _ends(cut, len(g)), strict=True):
            c = _runs(k[a:b])
            packed = (g[a:b] // np.uint64(buckets)).astype(np.uint32).tobytes()
            counts = np.diff(np.append(c, b - a))
            counts = counts.astype(np.uint16 if counts.max() < 1 << 16 else np.uint32).tobytes()
            rows.append((int(bucket[a]), None, packed, counts, k[a:b][c].tobytes()))
        yield _gram_batch(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, keys, held, seen = [], [], 0, set()
        for batch in batches:
            key = batch.column("key").to_numpy(zero_copy_only=False).view(np.uint64)
            for a, b, raw, at in textvec.pieces(batch.column("text")):
                found, grams = anchors(raw, at, length)
                row = np.searchsorted(at, found, side="right") - 1
                new = np.array([x not in seen and not seen.add(x) for x in key[a:b].tolist()], bool)
                use = new[row]
                ids.append(_gram_ids(grams[use], buckets))
                keys.append(key[a:b][row[use]])
                held += len(raw)
                if held >= flush_bytes:
                    yield from flush(ids, keys)
                    ids, keys, held, seen = [], [], 0, set()
        yield from flush(ids, keys)

    return run


_SHARED = "dest long, keys binary, counts binary, grams binary"


def _shared_batch(dest: np.ndarray, k: np.ndarray, g: np.ndarray) -> pa.RecordBatch:
    """Rows for (key, gram) pairs, sorted by dest, then key; one for each dest."""
    cut = _runs(dest)
    rows = []
    for a, b in zip(cut, _ends(cut, len(dest)), strict=True):
        c = _runs(k[a:b])
        rows.append((int(dest[a]), k[a:b][c].tobytes(), np.diff(np.append(c, b - a)).astype(np.uint32).tobytes(), g[a:b].tobytes()))
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
    return pa.RecordBatch.from_arrays(
        [pa.array(cols[0], pa.int64()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["dest", "keys", "counts", "grams"]
    )


def _shared_grams(buckets: int):
    """From all entries of a bucket: the grams that texts with different keys have, packed by groups of keys."""
    groups = np.uint64(4 * buckets)

    def packed(k: np.ndarray, g: np.ndarray) -> pa.RecordBatch:
        dest = (textvec.mix(k) % groups).astype(np.int64)
        order = np.lexsort((g, k, dest))
        return _shared_batch(dest[order], k[order], g[order])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        local: list = []
        for batch in batches:
            for bucket, key, idents, counts, keys in zip(*(batch.column(c).to_pylist() for c in ("bucket", "key", "idents", "counts", "keys")), strict=True):
                if bucket is None:
                    g = np.frombuffer(idents, np.uint64)
                    local.append((np.full(len(g), key, np.int64).view(np.uint64), g))
                    continue
                n = np.frombuffer(counts, np.uint16 if len(counts) == len(keys) // 4 else np.uint32)
                held.setdefault(bucket, []).append((np.frombuffer(idents, np.uint32).astype(np.uint64), np.repeat(np.frombuffer(keys, np.uint64), n)))
        if local:
            yield packed(np.concatenate([x[0] for x in local]), np.concatenate([x[1] for x in local]))
        for bucket in list(held):
            parts = held.pop(bucket)
            g, k = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
            del parts
            order = np.argsort(g)
            g, k = g[order], k[order]
            cut = _runs(g)
            low, high = np.minimum.reduceat(k, cut), np.maximum.reduceat(k, cut)
            use = np.repeat(low != high, np.diff(np.append(cut, len(g))))
            if use.any():
                yield packed(k[use], g[use] * np.uint64(buckets) + np.uint64(bucket))

    return run


def _by_key(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row (key, grams) for each key of the groups that meet here."""
    keys, grams = [], []
    for batch in batches:
        for k, n, g in zip(*(batch.column(c).to_pylist() for c in ("keys", "counts", "grams")), strict=True):
            keys.append(np.repeat(np.frombuffer(k, np.uint64), np.frombuffer(n, np.uint32)))
            grams.append(np.frombuffer(g, np.uint64))
    if not keys:
        return
    k, g = np.concatenate(keys), np.concatenate(grams)
    order = np.argsort(k, kind="stable")
    k, g = k[order], g[order]
    cut = _runs(k)
    ends = _ends(cut, len(k))
    for a in range(0, len(cut), 10_000):
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(k[cut[a : a + 10_000]].view(np.int64)),
                pa.array([g[x:y].tobytes() for x, y in zip(cut[a : a + 10_000], ends[a : a + 10_000], strict=True)], pa.binary()),
            ],
            names=["key", "grams"],
        )


def pack(*arrays: np.ndarray) -> bytes:
    parts = [np.ascontiguousarray(a).tobytes() for a in arrays]
    whole = np.array([len(p) for p in parts], np.int64).tobytes() + b"".join(parts)
    return np.int64(len(whole)).tobytes() + pa.compress(whole, codec="zstd", asbytes=True)


def unpack(blob: bytes, *kinds: type) -> list[np.ndarray]:
    whole = pa.decompress(blob[8:], decompressed_size=int(np.frombuffer(blob[:8], np.int64)[0]), codec="zstd", asbytes=True)
    ends = np.cumsum(np.frombuffer(whole[: 8 * len(kinds)], np.int64)) + 8 * len(kinds)
    return [np.frombuffer(whole[a:b], k) for a, b, k in zip(np.concatenate(([8 * len(kinds)], ends)), ends, kinds)]


def _spread(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin, begin + 1, ... of size places each, end to end."""
    return np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


#: Contexts (kind 0) or decisions (kind 1), packed by bucket.
_PACKED = "bucket long, kind int, payload binary"
_CONTEXT = (np.uint64, np.uint8, np.int64, np.int64, np.uint32, np.int64, np.uint8)
_DECISION = (np.int64, np.int64, np.int64, np.int64)


def _packed_batch(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 3
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int32(), pa.binary()), strict=True)], names=["bucket", "kind", "payload"])


def _windows(size: np.ndarray, length: int) -> np.ndarray:
    """Bit j: the string that starts j bytes into the context lies in it."""
    return (np.int64(1) << np.maximum(size.astype(np.int64) - length + 1, 0)) - 1


def _contexts(length: int, buckets: int, spread: int, flush_bytes: int):
    """Contexts of shared grams, dealt to `spread` parts by gram."""
    reach = length - GRAM

    def flush(held: list) -> Iterator[pa.RecordBatch]:
        if not held:
            return
        gram, size, begin, start, ord_, key, same = (np.concatenate([h[k] for h in held]) for k in range(7))
        raw = np.concatenate([h[7] for h in held])
        order = np.lexsort((start, key, ord_, same, gram))
        gram, size, begin, start, ord_, key, same = (x[order] for x in (gram, size, begin, start, ord_, key, same))
        cut = _runs(gram, same)
        least = np.repeat(ord_[cut], np.diff(np.append(cut, len(gram))))
        rows = []
        # strings of the others are those of a smaller id: decided here
        late = np.flatnonzero(ord_ > least)
        goal = (textvec.mix(key[late].view(np.uint64)) % np.uint64(spread)).astype(np.int64)
        by = np.argsort(goal, kind="stable")
        late, goal = late[by], goal[by]
        cut = _runs(goal)
        for a, b in zip(cut, _ends(cut, len(goal)), strict=True):
            at = late[a:b]
            rows.append((int(goal[a]), 1, pack(ord_[at], key[at], start[at], _windows(size[at], length))))
        first = np.flatnonzero(ord_ == least)
        goal = (gram[first] % np.uint64(spread)).astype(np.int64)
        by = np.argsort(goal, kind="stable")
        first, goal = first[by], goal[by]
        cut = _runs(goal)
        for a, b in zip(cut, _ends(cut, len(goal)), strict=True):
            at = first[a:b]
            c = _runs(gram[at], same[at], ord_[at], key[at])
            e = at[c]
            places = np.diff(np.append(c, len(at))).astype(np.uint32)
            rows.append((int(goal[a]), 0, pack(gram[e], size[e].astype(np.uint8), ord_[e], key[e], places, start[at], raw[_spread(begin[e], size[e])])))
        yield _packed_batch(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, amount, base = [], 0, 0
        for batch in batches:
            ords = batch.column("ord").to_numpy(zero_copy_only=False)
            keys = batch.column("key").to_numpy(zero_copy_only=False)
            shared, shared_at = textvec.string_parts(batch.column("grams"))
            for a, b, raw, at in textvec.pieces(batch.column("text")):
                found, grams = anchors(raw, at, length)
                row = np.searchsorted(at, found, side="right") - 1
                gram = _gram_ids(grams, buckets)
                mine = shared[shared_at[a] : shared_at[b]].copy().view(np.uint64)
                owner = np.repeat(np.arange(b - a), np.diff(shared_at[a : b + 1]) // 8).astype(np.uint64)
                tag = np.uint64(0x9E3779B97F4A7C15)
                use = np.isin(textvec.mix(gram ^ (row.astype(np.uint64) * tag)), textvec.mix(mine ^ (owner * tag)))
                found, row, gram = found[use], row[use], gram[use]
                begin = np.maximum(found - reach, at[row])
                size = np.minimum(found + GRAM + reach, at[row + 1]) - begin
                same = textvec.span_hashes(raw, begin, begin + size)
                held.append((gram, size, begin + base, begin - at[row], ords[a:b][row], keys[a:b][row], same, raw.copy()))
                base += len(raw)
                amount += len(found) * 76 + len(raw)
                if amount >= flush_bytes:
                    yield from flush(held)
                    held, amount, base = [], 0, 0
        yield from flush(held)

    return run


def _decide(text: np.ndarray, begins: np.ndarray, sizes: np.ndarray, owner: np.ndarray, length: int) -> np.ndarray:
    """Smallest owner (contexts x strings) of each string of the contexts that start at begins in text."""
    span = length - GRAM + 1
    out = np.full((len(begins), span), _LAST_ID, np.int64)
    array = suffix_sort.suffix_array(text, length)
    prefix = suffix_sort.neighbour_prefixes(text, array, cap=length)
    entry = np.searchsorted(begins, array, side="right") - 1
    offset = array - begins[entry]
    valid = offset + length <= sizes[entry]
    run = np.cumsum(prefix < length)
    run, entry, offset = run[valid], entry[valid], offset[valid]
    cut = _runs(run)
    if len(cut):
        least = np.minimum.reduceat(owner[entry], cut)
        out[entry, offset] = np.repeat(least, np.diff(np.append(cut, len(run))))
    return out


def _judged(parts: list[list[np.ndarray]], length: int) -> tuple[np.ndarray, ...]:
    """Decisions (ord, key, start, mask) from all contexts of some grams."""
    span = length - GRAM + 1
    gram, size, ord_, key, places, starts, raw = (np.concatenate([p[k] for p in parts]) for k in range(7))
    size = size.astype(np.int64)
    begin = np.cumsum(size) - size
    same = textvec.laid_hashes(raw, size)
    order = np.lexsort((same, gram))
    cut = _runs(gram[order], same[order])
    count = np.diff(np.append(cut, len(order)))
    entry = np.empty(len(order), np.int64)
    entry[order] = np.repeat(np.arange(len(cut)), count)
    owner = np.minimum.reduceat(ord_[order], cut)
    lead = order[cut]
    egram = gram[lead]
    g = _runs(egram)
    alone = np.repeat(np.diff(np.append(g, len(egram))), np.diff(np.append(g, len(egram)))) == 1
    masks = np.where(owner[entry] < ord_, _windows(size, length), 0)
    several = np.flatnonzero(~alone)
    if len(several):
        # pieces of about _SORT_BYTES that end between two grams
        total = np.cumsum(size[lead[several]] + 1)
        ends = np.append(_runs(egram[several])[1:], len(several))
        piece = total[ends - 1] // _SORT_BYTES
        stops = ends[np.append(np.flatnonzero(piece[1:] != piece[:-1]), len(ends) - 1)]
        bits = np.int64(1) << np.arange(span, dtype=np.int64)
        members = np.flatnonzero(~alone[entry])
        members = members[np.argsort(entry[members], kind="stable")]
        at = 0
        for stop in stops:
            part = several[at:stop]
            n = size[lead[part]]
            begins = np.cumsum(n + 1) - n - 1
            text = np.zeros(int((n + 1).sum()), np.uint16)
            text[_spread(begins, n)] = raw[_spread(begin[lead[part]], n)].astype(np.uint16) + 1
            least = _decide(text, begins, n, owner[part], length)
            lo, hi = np.searchsorted(entry[members], [part[0], part[-1] + 1])
            mine = members[lo:hi]
            row = np.searchsorted(part, entry[mine])
            masks[mine] = ((least[row] < ord_[mine][:, None]) * bits).sum(axis=1) & _windows(size[mine], length)
            at = stop
    hit = np.flatnonzero(masks)
    n = places[hit].astype(np.int64)
    first = np.cumsum(places.astype(np.int64)) - places
    return np.repeat(ord_[hit], n), np.repeat(key[hit], n), starts[_spread(first[hit], n)], np.repeat(masks[hit], n)


def _compare(length: int, buckets: int):
    """Contexts of the same gram against each other; all decisions, packed by groups of keys."""
    groups = np.uint64(4 * buckets)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        made: list[list[np.ndarray]] = []
        for batch in batches:
            for bucket, kind, payload in zip(*(batch.column(c).to_pylist() for c in ("bucket", "kind", "payload")), strict=True):
                if kind:
                    made.append(unpack(payload, *_DECISION))
                else:
                    held.setdefault(bucket, []).append(payload)
        for bucket in list(held):
            made.append(list(_judged([unpack(x, *_CONTEXT) for x in held.pop(bucket)], length)))
        if not made:
            return
        ord_, key, start, mask = (np.concatenate([m[k] for m in made]) for k in range(4))
        dest = (textvec.mix(key.view(np.uint64)) % groups).astype(np.int64)
        order = np.argsort(dest, kind="stable")
        cut = _runs(dest[order])
        rows = []
        for a, b in zip(cut, _ends(cut, len(order)), strict=True):
            at = order[a:b]
            rows.append((int(dest[at[0]]), 1, pack(ord_[at], key[at], start[at], mask[at])))
        yield _packed_batch(rows)

    return run


def _decided(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each text that loses something."""
    made = [unpack(x, *_DECISION) for batch in batches for x in batch.column("payload").to_pylist()]
    if not made:
        return
    ord_, key, start, mask = (np.concatenate([m[k] for m in made]) for k in range(4))
    order = np.lexsort((start, key, ord_))
    ord_, key, start, mask = (x[order] for x in (ord_, key, start, mask))
    cut = _runs(ord_, key)
    ends = _ends(cut, len(ord_))
    for a in range(0, len(cut), 10_000):
        c, e = cut[a : a + 10_000], ends[a : a + 10_000]
        yield pa.RecordBatch.from_arrays(
            [pa.array(ord_[c]), pa.array(key[c]), *(pa.array([x[i:j].tobytes() for i, j in zip(c, e, strict=True)], pa.binary()) for x in (start, mask))],
            names=["ord", "key", "starts", "masks"],
        )


_REMOVED = "ord long, key long, removed array<struct<start:long,end:long>>, kept_sha256 string"


def _cut_out(length: int):
    span = length - GRAM + 1
    kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sizes, edges, digests = [0], [], []
            raw, at = textvec.string_parts(b.column("text"))
            for i, (starts, masks) in enumerate(zip(b.column("starts").to_pylist(), b.column("masks").to_pylist(), strict=True)):
                text = raw[at[i] : at[i + 1]]
                start = np.frombuffer(starts, np.int64)
                bits = np.unpackbits(np.frombuffer(masks, np.uint8), bitorder="little").reshape(-1, 64)[:, :span]
                place, shift = np.nonzero(bits)
                begin = np.unique(start[place] + shift)
                change = np.zeros(len(text) + 1, np.int32)
                change[begin] = 1
                change[begin + length] -= 1
                gone = np.cumsum(change[:-1]) > 0
                edge = np.flatnonzero(np.diff(np.concatenate(([0], gone.view(np.int8), [0]))))
                edges.append(edge)
                sizes.append(len(edge) // 2)
                digests.append(hashlib.sha256(text[~gone].tobytes()).hexdigest())
            flat = np.concatenate(edges) if edges else np.zeros(0, np.int64)
            structs = pa.StructArray.from_arrays([pa.array(flat[::2]), pa.array(flat[1::2])], names=["start", "end"])
            spans = pa.ListArray.from_arrays(pa.array(np.cumsum(sizes).astype(np.int32)), structs).cast(kind)
            yield pa.RecordBatch.from_arrays(
                [b.column("ord"), b.column("key"), spans, pa.array(digests, pa.string())], names=["ord", "key", "removed", "kept_sha256"]
            )

    return run


def dedup_substrings(docs: DataFrame, length: int = 50) -> DataFrame:
    """For each row of docs(doc_id, text): doc_id, n_bytes, sha256 of the text, removed byte spans, kept_sha256."""
    assert GRAM < length <= GRAM + 62
    docs = docs.select(
        "doc_id", F.coalesce("text", F.lit("")).alias("text"), F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST_ID)).alias("ord")
    ).withColumn("key", F.xxhash64("text"))
    base = materialize(
        docs.select("doc_id", "ord", "key", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2(F.encode("text", "UTF-8"), 256).alias("sha256")),
        "texts",
    )
    first = base.groupBy("sha256").agg(F.min("ord").alias("first"))
    base = materialize(base.join(first, "sha256"), "text-classes")
    total = int(base.agg(F.sum("n_bytes")).first()[0] or 0)
    at_once = bucket_bytes(total)
    buckets = max(8, -(-total // at_once))
    entries = docs.where(F.octet_length("text") >= length).select("key", "text").mapInArrow(_grams(length, buckets, at_once), _GRAMS)
    spread = entries.repartition(buckets, F.coalesce(F.col("bucket").cast("long"), F.col("key")))
    packed = spread.mapInArrow(_shared_grams(buckets), _SHARED).repartition(buckets, "dest")
    grams = packed.mapInArrow(_by_key, "key long, grams binary")
    lead = base.where("ord = first").select("ord", "key").distinct()
    wanted = lead.join(grams, "key").select("ord", "key", "grams")
    # both joins with the texts use one and the same exchange of them
    texts = docs.where(F.octet_length("text") >= length).select("ord", "key", "text")
    contexts = texts.hint("merge").join(wanted, ["ord", "key"]).mapInArrow(_contexts(length, buckets, 2 * buckets, at_once), _PACKED)
    met = contexts.repartition(2 * buckets, "bucket").mapInArrow(_compare(length, 2 * buckets), _PACKED)
    decided = met.repartition(2 * buckets, "bucket").mapInArrow(_decided, "ord long, key long, starts binary, masks binary")
    removed = texts.hint("merge").join(decided, ["ord", "key"]).mapInArrow(_cut_out(length), _REMOVED)
    if not base.groupBy("ord", "key").count().where("count > 1").isEmpty():  # repeated rows
        removed = removed.dropDuplicates(["ord", "key"])
    nothing = F.array().cast("array<struct<start:long,end:long>>")
    whole = F.array(F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("end")))
    copy = (F.col("ord") > F.col("first")) & (F.col("n_bytes") >= length)
    return base.join(materialize(removed, "removed"), ["ord", "key"], "left").select(
        "doc_id",
        "n_bytes",
        "sha256",
        F.when(copy, whole).otherwise(F.coalesce("removed", nothing)).alias("removed"),
        F.when(copy, F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("kept_sha256", "sha256")).alias("kept_sha256"),
    )


def op9_substring_dedup(spark, sf_dir) -> DataFrame:
    spans = dedup_substrings(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    gone = F.aggregate("removed", F.lit(0).cast("long"), lambda s, x: s + x["end"] - x["start"])
    return spans.select(
        "doc_id", "n_bytes", gone.alias("n_removed"), F.size("removed").cast("long").alias("n_spans"), "kept_sha256"
    )


#: Every string of every text; for small tables.
OP9_SQL = """
WITH d AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
n AS (SELECT r, doc_id, h, length(h) // 2 AS n FROM d),
w AS (SELECT r, doc_id, p, substr(h, 2 * p + 1, 100) AS g FROM (SELECT *, unnest(range(0, n - 49)) AS p FROM n WHERE n >= 50)),
f AS (SELECT g, min(doc_id) AS m FROM w GROUP BY g HAVING count(*) > 1),
s AS (SELECT w.r, w.p FROM w JOIN f ON w.g = f.g WHERE f.m < w.doc_id),
i AS (SELECT r, p, CASE WHEN p <= lag(p) OVER (PARTITION BY r ORDER BY p) + 50 THEN 0 ELSE 1 END AS new FROM s),
k AS (SELECT r, p, sum(new) OVER (PARTITION BY r ORDER BY p) AS k FROM i),
a AS (SELECT r, k, min(p) AS b, max(p) + 50 AS e FROM k GROUP BY r, k),
q AS (SELECT a.r, b, e, substr(h, 2 * coalesce(lag(e) OVER (PARTITION BY a.r ORDER BY b), 0) + 1, 2 * (b - coalesce(lag(e) OVER (PARTITION BY a.r ORDER BY b), 0))) AS piece FROM a JOIN n ON a.r = n.r),
x AS (SELECT r, sum(e - b) AS n_removed, count(*) AS n_spans, string_agg(piece, '' ORDER BY b) AS head, max(e) AS e FROM q GROUP BY r)
SELECT doc_id, n AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans,
       sha256(unhex(coalesce(head, '') || substr(h, 2 * coalesce(e, 0) + 1))) AS kept_sha256
FROM n LEFT JOIN x ON n.r = x.r
"""
