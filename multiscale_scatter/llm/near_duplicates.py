"""Near-duplicate documents by an inverted join of MinHash signature coordinates.

Each document's set of word shingles gets a signature of 64 coordinates.  A coordinate and its value
form one posting key, so two documents agree in as many coordinates as they share keys.  The steps:

1. Documents with the same set form a class; one representative stands for it from here on.
2. Keys found in one class only cannot bring a pair together and go.  What is left of a signature is
   sorted by how many classes have the key, rarest first.  Two signatures that agree in at least
   `min_matches` coordinates share `PREFIX_HITS` keys among the first c - min_matches + PREFIX_HITS of
   each (c: keys kept), so only that prefix is posted, and classes with fewer keys are skipped.
3. Posting lists of at most `SHORT` classes are joined with themselves; pairs of similar size are counted,
   and those with enough common lists are compared in all coordinates.  In longer lists each class is
   paired with a few pivots of the list only.
4. Every class is confirmed on full sets against its likeliest partner first, then what still lies in
   different components.
5. Long lists that still span several components get other pivots.  What is still open then is joined by its
   rarest shingles: sets that are similar share one of them, at places that leave the threshold within reach.
   Only ids travel in that join, in shares of a hot shingle, and the pairs of different components that are
   left are confirmed.  So no link between components is lost, while a group of copies costs a few pairs a
   member, and a family with much common text but too little for a link meets in its common shingles no more.

The signature step misses a pair at exactly the threshold of 0.8 with a probability below 1e-6 (64
trials at 0.8, fewer than 32 hits); everything after it is exact.

Defined cases: a null or empty text, or one of white space only, has an empty set and is linked with
nothing; repeated rows are copies of each other and each gives a row; a row without an id shares the
component of an equal set that has one, and is compared no further (component null, kept); an empty
table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import textvec
from .shared import components, discard, materialize

#: The low six bits of a posting key hold the coordinate.
COORDINATES = 64
_RNG = np.random.Generator(np.random.PCG64(20240229))
_FLIP = _RNG.integers(0, 1 << 63, COORDINATES, dtype=np.uint64)
_TIMES = _RNG.integers(0, 1 << 63, COORDINATES, dtype=np.uint64) | np.uint64(1)

#: Keys that two prefixes must share; the longest list whose pairs are all counted; pivots of a longer one;
#: ids that are broadcast at most; links whose components one task finds at most; classes of a hot shingle's share.
PREFIX_HITS, SHORT, PIVOTS, MAX_BROADCAST, MAX_EDGES, SHARE = 4, 64, 2, 1_000_000, 1_000_000, 4096

_SIGNED = "doc_id long, key long, n_shingles long, cid long, keys array<long>, brief array<int>"


def _distinct(hashes: np.ndarray, per_row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of each row, end to end, and how many there are."""
    ends = np.cumsum(per_row)
    kept, n = [], np.zeros(len(per_row), np.int64)
    for k in np.flatnonzero(per_row):
        s = np.sort(hashes[ends[k] - per_row[k] : ends[k]])
        if len(s) > 1:
            s = s[np.concatenate(([True], s[1:] != s[:-1]))]
        kept.append(s)
        n[k] = len(s)
    return (np.concatenate(kept) if kept else np.zeros(0, np.uint64)), n


def _sets(raw: np.ndarray, at: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    starts, ends, counts = textvec.word_bounds(raw, at)
    words = textvec.span_hashes(textvec.lower_ascii(raw), starts, ends)
    return _distinct(*textvec.shingle_hashes(words, counts, width))


def _signatures(sets: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Posting keys (rows x 64) of rows with a set; n has no zero."""
    begins = np.cumsum(n) - n
    out = np.empty((len(n), COORDINATES), np.uint64)
    for c in range(COORDINATES):
        out[:, c] = np.minimum.reduceat((sets ^ _FLIP[c]) * _TIMES[c], begins)
    return (out & ~np.uint64(COORDINATES - 1)) | np.arange(COORDINATES, dtype=np.uint64)


def _class_ids(sets: np.ndarray, n: np.ndarray) -> np.ndarray:
    begins = np.cumsum(n) - n
    total = np.add.reduceat(textvec.mix(sets ^ np.uint64(0x5851F42D4C957F2D)), begins)
    return textvec.mix(total ^ textvec.mix(np.bitwise_xor.reduceat(sets, begins)) ^ n.astype(np.uint64))


def _sign(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, text_keys = batch.column("doc_id"), batch.column("key")
            for a, b, raw, at in textvec.pieces(batch.column("text")):
                sets, n = _sets(raw, at, width)
                full = n > 0
                cid, keys, size = np.zeros(b - a, np.int64), np.zeros((0, COORDINATES), np.uint64), np.zeros(b - a, np.int64)
                if full.any():
                    cid[full] = _class_ids(sets, n[full]).view(np.int64)
                    keys = _signatures(sets, n[full])
                    size[full] = COORDINATES
                # coordinate and 26 bits of its value: enough to compare two signatures
                low = np.uint64((1 << 26) - 1)
                brief = (((keys >> np.uint64(6)) & low) | (np.arange(COORDINATES, dtype=np.uint64) << np.uint64(26))).astype(np.uint32)
                offsets = pa.array(np.concatenate(([0], np.cumsum(size))).astype(np.int32))
                yield pa.RecordBatch.from_arrays(
                    [
                        ids.slice(a, b - a),
                        text_keys.slice(a, b - a),
                        pa.array(n),
                        pa.array(cid, mask=~full),
                        pa.ListArray.from_arrays(offsets, pa.array(keys.reshape(-1).view(np.int64))),
                        pa.ListArray.from_arrays(offsets, pa.array(brief.reshape(-1).view(np.int32))),
                    ],
                    names=["doc_id", "key", "n_shingles", "cid", "keys", "brief"],
                )

    return run


def _full_sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, raw, at in textvec.pieces(batch.column("text")):
                sets, n = _sets(raw, at, width)
                n = n[n > 0]
                if not len(n):
                    continue
                lists = pa.ListArray.from_arrays(
                    pa.array(np.concatenate(([0], np.cumsum(n))).astype(np.int32)), pa.array(sets.view(np.int64))
                )
                yield pa.RecordBatch.from_arrays([pa.array(_class_ids(sets, n).view(np.int64)), lists], names=["cid", "shingles"])

    return run


def _alike(pairs: DataFrame, brief: DataFrame, min_matches: int) -> DataFrame:
    """pairs(a, b) that agree in min_matches coordinates, with their number."""
    left = brief.select(F.col("cid").alias("a"), F.col("brief").alias("ka"))
    right = brief.select(F.col("cid").alias("b"), F.col("brief").alias("kb"))
    joined = pairs.join(left, "a").join(right, "b").select("a", "b", F.size(F.array_intersect("ka", "kb")).alias("matches"))
    return materialize(joined.where(F.col("matches") >= min_matches), "near-pairs")


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """pairs(a, b) whose full sets are similar."""
    sa = sets.select(F.col("cid").alias("a"), F.col("shingles").alias("sa"))
    sb = sets.select(F.col("cid").alias("b"), F.col("shingles").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    return (
        pairs.select("a", "b")
        .join(sa, "a")
        .join(sb, "b")
        .select("a", "b", both.alias("both"), (F.size("sa") + F.size("sb") - both).alias("either"))
        .where(F.col("both") * 100 >= F.col("either") * percent)
        .select("a", "b")
    )


def near_duplicates(
    docs: DataFrame, width: int = 5, percent: int = 80, min_matches: int = 32, short: int = SHORT
) -> DataFrame:
    """One row for each row of docs(doc_id, text): doc_id, n_shingles, component_id, kept.

    Linked: 100 * intersection >= percent * union of the sets of width-word shingles.
    """
    return _judged(docs, width, percent, min_matches, short).drop("key", "component")


def _judged(docs: DataFrame, width: int = 5, percent: int = 80, min_matches: int = 32, short: int = SHORT) -> DataFrame:
    """near_duplicates with key, a hash of the text, and component, which tells components apart that share their smallest id."""
    docs = docs.select("doc_id", F.xxhash64("text").alias("key"), "text")
    signed = materialize(docs.mapInArrow(_sign(width), _SIGNED), "signatures")
    classes = materialize(
        signed.where("n_shingles > 0").groupBy("cid").agg(F.min("doc_id").alias("doc_id"), F.max("n_shingles").alias("n")), "classes"
    )
    linked = _links(docs, signed, classes, width, percent, min_matches, short)
    named = (
        classes.join(linked, classes["cid"] == linked["node"], "left")
        .select("cid", "doc_id", F.coalesce("component", "cid").alias("component"))
    )
    lowest = named.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    by_class = named.join(lowest, "component").select(F.col("cid").alias("class_id"), "component", "component_id")
    return signed.join(by_class, signed["cid"] == by_class["class_id"], "left").select(
        "doc_id",
        "key",
        "n_shingles",
        "component",
        F.when(F.col("cid").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"),
    ).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _enough(left: Column, right: Column, n1: Column, n2: Column, percent: int) -> Column:
    """An intersection as large as the smaller of left and right would do for sets of n1 and n2 members."""
    return F.least(left, right) * (100 + percent) >= (n1 + n2) * percent


def _open(members: DataFrame) -> DataFrame:
    """The postings of lists that span several components."""
    spans = members.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi"))
    return members.join(spans.where("lo < hi").select("key"), "key")


def _few(df: DataFrame) -> DataFrame:
    """df(one id column) marked for broadcast if it is small."""
    return F.broadcast(df) if df.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST else df


def _with_labels(members: DataFrame, labels: DataFrame) -> DataFrame:
    named = members.drop("component").join(labels, members["cid"] == labels["node"], "left")
    return named.select("key", "cid", "n", "c", F.coalesce("component", "cid").alias("component"))


def _pivot_pairs(members: DataFrame, percent: int, first: int, count: int) -> DataFrame:
    """Each member of a list with up to `count` members of other components that could be similar by size.

    Those with the most shared keys come first: they lie in the middle of a group of near copies.
    """
    middle = -F.col("c")
    picks = [F.min_by(F.struct("cid", "component", "n"), F.struct(middle.alias("m"), F.xxhash64("cid", F.lit(k)).alias("h"))) for k in range(first, first + count)]
    pivots = members.groupBy("key").agg(F.array(*picks).alias("p")).select("key", F.explode(F.array_distinct("p")).alias("p"))
    return members.join(
        pivots, (members["key"] == pivots["key"]) & (F.col("component") != F.col("p.component"))
        & _enough(F.col("n"), F.col("p.n"), F.col("n"), F.col("p.n"), percent),
    ).select(F.least("cid", "p.cid").alias("a"), F.greatest("cid", "p.cid").alias("b")).distinct()


def _postings(signed: DataFrame, classes: DataFrame, min_matches: int, short: int) -> tuple[DataFrame, DataFrame]:
    """Representatives, and the prefix postings (key, cid, n, c: shared keys of the class, long: the list has more than short classes)."""
    chosen = signed.join(classes.select("cid", "doc_id"), ["cid", "doc_id"], "left_semi").dropDuplicates(["cid"])
    posted = chosen.select("cid", F.col("n_shingles").cast("int").alias("n"), F.explode("keys").alias("key"))
    # counts are combined before the shuffle; the join back is one that adaptive execution can split
    shared = posted.groupBy("key").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    shared = posted.join(shared, "key")
    of_class = W.partitionBy("cid")
    ranked = shared.select(
        "cid", "n", "key", F.row_number().over(of_class.orderBy("df", "key")).alias("r"), F.count("key").over(of_class).alias("c")
    )
    prefix = ranked.where(F.col("c") >= min_matches).where(F.col("r") <= F.col("c") - min_matches + PREFIX_HITS)
    prefix = materialize(prefix.select("key", "cid", "n", "c"), "prefixes")
    lists = prefix.groupBy("key").agg(F.count(F.lit(1)).alias("size")).where("size > 1")
    return chosen, materialize(prefix.join(lists, "key").select("key", "cid", "n", "c", (F.col("size") > short).alias("long")), "postings")


def _counted_pairs(postings: DataFrame, percent: int) -> DataFrame:
    """Pairs that meet in short lists often enough; a long list of both counts as a meeting."""
    in_long = postings.where("long").groupBy("cid").agg(F.count(F.lit(1)).alias("l"))
    members = postings.where("not long").join(in_long, "cid", "left").select("key", "cid", "n", F.coalesce("l", F.lit(0)).alias("l"))
    other = members.select("key", F.col("cid").alias("cid2"), F.col("n").alias("n2"), F.col("l").alias("l2"))
    met = members.join(
        other, (members["key"] == other["key"]) & (F.col("cid") < F.col("cid2")) & _enough(F.col("n"), F.col("n2"), F.col("n"), F.col("n2"), percent)
    )
    counted = met.groupBy(F.col("cid").alias("a"), F.col("cid2").alias("b")).agg(F.count(F.lit(1)).alias("k"), F.max(F.least("l", "l2")).alias("l"))
    return counted.where(F.col("k") + F.col("l") >= PREFIX_HITS).select("a", "b")


def _links(docs, signed, classes, width, percent, min_matches, short) -> DataFrame:
    """(node, component) of the classes that have a link."""
    chosen, postings = _postings(signed, classes, min_matches, short)
    brief = chosen.select("cid", "brief")
    long_lists = materialize(postings.where("long").select("key", "cid", "n", "c", F.col("cid").alias("component")), "long-lists")
    near = _alike(_counted_pairs(postings, percent).unionByName(_pivot_pairs(long_lists, percent, 0, 1)).distinct(), brief, min_matches)
    wanted = near.select(F.col("a").alias("cid")).unionByName(near.select(F.col("b").alias("cid"))).unionByName(long_lists.select("cid")).distinct()
    wanted = materialize(chosen.join(wanted, "cid", "left_semi").select("doc_id"), "wanted")
    texts = docs.join(_few(wanted), "doc_id").select("text")
    sets = texts.mapInArrow(_full_sets(width), "cid long, shingles array<long>")
    if not signed.groupBy("doc_id").count().where("count > 1").isEmpty():  # repeated rows bring a set more than once
        sets = sets.dropDuplicates(["cid"])
    sets = materialize(sets, "sets")
    # the likeliest partner of each class first
    ways = near.unionByName(near.select(F.col("b").alias("a"), F.col("a").alias("b"), "matches"))
    best = ways.groupBy("a").agg(F.max_by("b", F.struct("matches", "b")).alias("b")).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    best = materialize(best, "best-pairs")
    found = materialize(_confirmed(best, sets, percent), "links")
    labels = components(found, MAX_EDGES)
    one, two = (labels.select(F.col("node").alias(c), F.col("component").alias(f"c{c}")) for c in "ab")
    rest = near.select("a", "b").join(best, ["a", "b"], "left_anti").join(one, "a", "left").join(two, "b", "left")
    rest = rest.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b")
    before, found = found, materialize(found.unionByName(_confirmed(rest, sets, percent)), "links")
    discard(before, labels)
    labels = components(found, MAX_EDGES)
    for last in (False, True):
        members = materialize(_open(_with_labels(long_lists, labels)), "open-lists")
        if members.isEmpty():
            break
        if last:
            links = _all_links(members, sets, percent)
        else:
            links = _confirmed(_alike(_pivot_pairs(members, percent, 1, PIVOTS), brief, min_matches), sets, percent)
        before, found = found, materialize(found.unionByName(links), "links")
        discard(before, members, labels)
        labels = components(found, MAX_EDGES)
    discard(sets, postings, long_lists, near, best, wanted)
    return labels


def _all_links(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Every link (a, b) between the classes of members that lie in different components.

    The shingles of a set are put in order, rarest first.  Of two sets that are similar, the first common
    shingle is at place i of one and j of the other, counted from 0, and all that they share lies from there on;
    so n - i and m - j bound the intersection, and neither i nor j lies behind the first 1 - percent / 100 of
    its set.  Shingles that no other class here has come first and take up places without being posted.
    """
    here = members.groupBy("cid").agg(F.first("n").alias("n"), F.first("component").alias("component"))
    shingles = materialize(sets.join(here, "cid").select("cid", "n", "component", F.explode("shingles").alias("shingle")), "open-shingles")
    common = shingles.groupBy("shingle").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    of_class = W.partitionBy("cid")
    ranked = shingles.join(common, "shingle").select(
        "*", (F.col("n") - F.count(F.lit(1)).over(of_class) + F.row_number().over(of_class.orderBy("df", "shingle")) - 1).alias("place")
    )
    posted = ranked.where((F.col("n") - F.col("place")) * 100 >= F.col("n") * percent).select("shingle", "cid", "n", "component", (F.col("n") - F.col("place")).alias("left"))
    posted = materialize(posted, "rare-postings")
    shares = posted.groupBy("shingle").agg(F.count(F.lit(1)).alias("m"), F.min("component").alias("lo"), F.max("component").alias("hi"))
    shares = shares.where("lo < hi").select("shingle", F.ceil(F.col("m") / SHARE).cast("int").alias("shares"))
    dealt = posted.join(shares, "shingle")
    one = dealt.withColumn("share", F.pmod(F.xxhash64("cid"), F.col("shares")).cast("int")).drop("shares")
    two = dealt.withColumn("share", F.explode(F.sequence(F.lit(0), F.col("shares") - 1))).drop("shares")
    two = two.select(*(F.col(c).alias(c if c in ("shingle", "share") else f"{c}2") for c in two.columns))
    near = one.join(two, ["shingle", "share"]).where(
        (F.col("cid") < F.col("cid2")) & (F.col("component") != F.col("component2")) & _enough(F.col("left"), F.col("left2"), F.col("n"), F.col("n2"), percent)
    )
    pairs = materialize(near.select(F.col("cid").alias("a"), F.col("cid2").alias("b")).distinct(), "open-pairs")
    discard(shingles, posted)
    return _confirmed(pairs, sets, percent)


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """docs without near-duplicates: of each component the document with the smallest id stays, once.

    Decisions go by id and text, so other texts under the same id, or without one, are judged by themselves.
    Further rows of what stays of a component are dropped as well, and so are repeats of a text that has no
    id anywhere; documents without words all stay.
    """
    judged = _judged(docs, **options)
    gone = judged.where(~F.col("kept")).select(F.col("doc_id").alias("gone_id"), F.col("key").alias("gone_key")).distinct()
    rest = docs.join(gone, docs["doc_id"].eqNullSafe(gone["gone_id"]) & (F.xxhash64(docs["text"]) == gone["gone_key"]), "left_anti")
    stays = judged.where("kept and n_shingles > 0").select("doc_id", "key", "component")
    again = stays.groupBy("component").count().where("count > 1").select("component")
    again = stays.join(again, "component").select(F.col("doc_id").alias("again_id"), F.col("key").alias("again_key"), F.col("component").alias("again_component")).distinct()
    same = rest["doc_id"].eqNullSafe(again["again_id"]) & (F.xxhash64(rest["text"]) == again["again_key"])
    once = rest.join(again, same, "left_anti")
    twice = rest.join(again, same).dropDuplicates(["again_component"]).select(*docs.columns)
    return once.unionByName(twice)


def op6_near_duplicates(spark, sf_dir) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), width=2, percent=80)


#: All pairs by shared shingles; for small tables.
OP6_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
u AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) > 1 THEN list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) ELSE ws END) AS s FROM w),
n AS (SELECT doc_id, count(*) AS n FROM u GROUP BY doc_id),
s AS (SELECT u.doc_id, s, n FROM u JOIN n ON u.doc_id = n.doc_id WHERE s IN (SELECT s FROM u GROUP BY s HAVING count(*) > 1)),
p AS (
  SELECT a.doc_id AS x, b.doc_id AS y, any_value(a.n) AS nx, any_value(b.n) AS ny, count(*) AS c
  FROM s a JOIN s b ON a.s = b.s AND a.doc_id < b.doc_id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) GROUP BY 1, 2),
e AS (SELECT x, y FROM p WHERE 100 * c >= 80 * (nx + ny - c)),
b AS (SELECT x, y FROM e UNION SELECT y, x FROM e),
reach(x, y) AS (SELECT x, y FROM b UNION SELECT reach.x, b.y FROM reach JOIN b ON reach.y = b.x),
g AS (SELECT x, least(x, min(y)) AS component_id FROM reach GROUP BY x)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(g.component_id, w.doc_id) AS component_id, w.doc_id = coalesce(g.component_id, w.doc_id) AS kept
FROM w LEFT JOIN n ON w.doc_id = n.doc_id LEFT JOIN g ON w.doc_id = g.x
"""
