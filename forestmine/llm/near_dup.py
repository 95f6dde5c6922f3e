"""Near-duplicate classes by circulant MinHash, banding and exact verification.

Two permutations make every signature coordinate: ``sigma`` sends a shingle to a
circle of 2^32 places, coordinate k is the least image under ``pi`` of the places
turned by k steps. Bands of coordinates propose, full shingle sets decide.

Copies with equal sets collapse first: by a SHA-256 of the whole sorted set, with partial minima. In a
band's bucket every member is held against the bucket's most popular member, the
one that shares most buckets with others: of copies changed from one text that is
the text they come from, so a group of n copies costs n checks. Buckets whose
members are still in different components take their next leader.

Members of buckets that are open after that meet in a prefix join. A set's shingles are put in one
order for all, the rarest first; two sets similar enough must share one of the first
few, and texts changed apart from one source have shingles of their own there, so that
they never meet. Only members outside of a shingle's largest component look for partners.

Before sets are fetched a parity sketch rules pairs out: bits that two sketches differ in
can't be more than the shingles that the sets differ in. Both tests are exact: they lose no link.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import _text
from ._spark import discard, masked, materialize, only_ids, small_batches
from .components import components

#: Bands and rows: a pair at 0.8 is missed with (1 - 0.8^5)^36 < 1e-6.
BANDS, ROWS = 36, 5
#: Words of 64 bits in a parity sketch.
PARITY = 12
#: Leaders that an open bucket has before its other members meet in the prefix join.
ROUNDS = 2
#: Bytes of text whose words are hashed at once.
PIECE = 1 << 18

_BITS = [f"p{i}" for i in range(PARITY)]
_SKETCH = f"id long, n long, digest binary, {', '.join(f'{c} long' for c in _BITS)}, bands array<long>"


def shingle_sets(column: pa.Array, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, sorted distinct shingle hashes of all rows end to end, offsets) by piece."""
    for w in _text.words(column, lower=True, most=PIECE):
        h, first = w.windows(k)
        n = w.counts()
        sets = []
        for i in range(w.rows):
            if 0 < n[i] < k:
                sets.append(_text.span_hashes(w.hash[w.first[i] : w.first[i + 1]], np.array([0]), np.array([n[i]])))
            else:
                sets.append(np.unique(h[first[i] : first[i + 1]]))
        yield w.row, np.concatenate(sets) if sets else np.zeros(0, np.uint64), np.concatenate(([0], np.cumsum([len(s) for s in sets]))).astype(np.int64)


def _pi(x: np.ndarray) -> np.ndarray:
    """The second permutation, of the circle of 2^32 places."""
    x = x ^ (x >> np.uint32(16))
    x *= np.uint32(0x7FEB352D)
    x ^= x >> np.uint32(15)
    x *= np.uint32(0x846CA68B)
    x ^= x >> np.uint32(16)
    return x


def signatures(hashes: np.ndarray, offsets: np.ndarray, coordinates: int) -> np.ndarray:
    """Circulant MinHash of each non-empty set: (sets, coordinates) of uint32; empty sets stay zero."""
    out = np.zeros((len(offsets) - 1, coordinates), np.uint32)
    full = np.flatnonzero(np.diff(offsets))
    if len(full):
        place = (_text.mix64(hashes) >> np.uint64(32)).astype(np.uint32)  # sigma
        low, step = offsets[full], np.uint32(0x9E3779B1)
        for begin in range(0, len(full), 64):  # a cache-sized run of sets at a time
            to = min(begin + 64, len(full))
            part = place[low[begin] : offsets[full[to - 1] + 1]]
            at = low[begin:to] - low[begin]
            for c in range(coordinates):
                out[full[begin:to], c] = np.minimum.reduceat(_pi(part), at)
                part = part + step
    return out


def parity(hashes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """(sets, PARITY) of int64: each shingle turns one of 64 * PARITY bits over."""
    bits, rows = 64 * PARITY, len(offsets) - 1
    place = ((_text.mix64(hashes ^ np.uint64(0x5851F42D4C957F2D)) >> np.uint64(32)) * np.uint64(bits) >> np.uint64(32)).astype(np.int64)
    out = np.zeros((rows, PARITY), np.int64)
    for begin in range(0, rows, 256):
        to = min(begin + 256, rows)
        row = np.repeat(np.arange(to - begin), np.diff(offsets[begin : to + 1]))
        turned = np.bincount(row * bits + place[offsets[begin] : offsets[to]], minlength=(to - begin) * bits) & 1
        out[begin:to] = np.packbits(turned.astype(np.uint8).reshape(to - begin, bits), axis=1).view(np.int64)
    return out


def _longs(values: np.ndarray, offsets: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values.view(np.int64)))


def _sketch(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, hashes, offsets in shingle_sets(batch.column("text"), k):
                rows, n = len(offsets) - 1, np.diff(offsets)
                sig = signatures(hashes, offsets, BANDS * ROWS)
                digest = [hashlib.sha256(hashes[a:b].tobytes()).digest() for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
                sketch = parity(hashes, offsets)
                key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F), (rows, BANDS)).copy()
                for r in range(ROWS):
                    key = _text.mix64(key ^ sig[:, r::ROWS]) + np.uint64(r + 1)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("id").slice(row, rows), pa.array(n), pa.array(digest, "binary"), *(pa.array(np.ascontiguousarray(sketch[:, i])) for i in range(PARITY)), _longs(key.ravel(), np.arange(0, rows * BANDS + 1, BANDS))],
                    names=["id", "n", "digest", *_BITS, "bands"],
                )

    return _text.lean(run)


def _sets(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, hashes, offsets in shingle_sets(batch.column("text"), k):
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(row, len(offsets) - 1), _longs(hashes, offsets)], names=["id", "set"])

    return _text.lean(run)


def sets_of(ids: DataFrame, texts: DataFrame, k: int) -> DataFrame:
    """(id, set array<long>) of the texts (id, text) with one of the ids, written once."""
    return materialize(only_ids(texts, ids, "id").mapInArrow(_sets(k), "id long, set array<long>"), "sets")


def verify(pairs: DataFrame, texts: DataFrame, k: int, percent: int) -> DataFrame:
    """Pairs (src, dst) whose full shingle sets are similar enough, written once. texts: (id, text)."""
    ids = materialize(pairs.select(F.col("src").alias("id")).union(pairs.select("dst")).distinct(), "ids")
    sets = sets_of(ids, texts, k)
    joined = pairs.join(sets.toDF("src", "a"), "src").join(sets.toDF("dst", "b"), "dst")
    both, all_ = F.size(F.array_intersect("a", "b")), F.size("a") + F.size("b")
    links = materialize(joined.withColumn("both", both).filter((F.col("both") > 0) & (100 * F.col("both") >= percent * (all_ - F.col("both")))).select("src", "dst").distinct(), "links")
    discard(ids, sets)
    return links


def _near(a: str, b: str, percent: int) -> Column:
    """Not ruled out by sizes or by parities: sets of n and m that are similar enough differ in (n + m)(100 - percent) / (100 + percent) shingles at most."""
    differ = functools.reduce(lambda x, y: x + y, (F.bit_count(F.col(f"{a}.{c}").bitwiseXOR(F.col(f"{b}.{c}"))) for c in _BITS))
    n, m = F.col(f"{a}.n"), F.col(f"{b}.n")
    return (100 * F.least(n, m) >= percent * F.greatest(n, m)) & ((100 + percent) * differ <= (100 - percent) * (n + m))


def _equal(some: DataFrame, members: DataFrame) -> DataFrame:
    """(id, component) of ids whose set another id has too."""
    label = members.filter("id <> rep").select("id", F.col("rep").alias("component")).distinct()
    if some.groupBy("id").count().filter("count > 1").isEmpty():
        return materialize(label.union(label.select(F.col("component").alias("id"), "component").distinct()), "components")
    return materialize(components(label.toDF("src", "dst")).toDF("id", "component"), "components")  # an id of several texts joins their classes


def _relabel(label: DataFrame, links: DataFrame) -> DataFrame:
    """(id, component) after more links between ids; ids without a link so far are their own component."""
    ends = links.join(label.toDF("src", "ca"), "src", "left").join(label.toDF("dst", "cb"), "dst", "left")
    joined = components(ends.select(F.coalesce("ca", "src").alias("src"), F.coalesce("cb", "dst").alias("dst"))).toDF("component", "final")
    # Components that came in as single ids have no row yet.
    nodes = label.union(joined.join(label.select("component").distinct(), "component", "left_anti").select(F.col("component").alias("id"), "component"))
    out = materialize(nodes.join(joined, "component", "left").select("id", F.coalesce("final", "component").alias("component")), "components")
    discard(label, links)
    return out


def prefix_pairs(sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (src, dst) of sets (id, component, set) in different components that a prefix filter can't rule out; all pairs that are similar enough are among them.

    Sets are put in order by size. Of a pair the smaller has one of its first n - ceil(2 n percent / (100 + percent)) + 1
    shingles among the larger's first n - ceil(n percent / 100) + 1, in any order of all shingles; the order here is
    by how many of the sets hold a shingle, so that only shared ones need rows.
    """
    sets = sets.withColumn("n", F.size("set").cast("long")).filter("n > 0").withColumn("sid", F.xxhash64("set"))
    tokens = sets.select("id", "sid", "component", "n", F.explode("set").alias("h"))
    held = tokens.groupBy("h").agg(F.count(F.lit(1)).alias("df")).filter("df > 1")
    ranked = tokens.join(held, "h").groupBy("id", "sid", "component", "n").agg(F.sort_array(F.collect_list(F.struct("df", "h"))).alias("ranked"))
    ceil = lambda a, b: F.floor((a + b - 1) / b).cast("long")
    n = F.col("n")
    probe, own = n - ceil(percent * n, F.lit(100)) + 1, n - F.size("ranked")
    first = ranked.withColumns({"own": own, "take": F.greatest(F.lit(0), probe - own).cast("int")}).select("id", "sid", "component", "n", "own", F.posexplode(F.slice("ranked", F.lit(1), F.col("take"))).alias("at", "x"))
    first = first.select("id", "sid", "component", "n", (F.col("own") + F.col("at")).alias("at"), F.col("x.h").alias("h"))
    first = materialize(first.withColumn("short", F.col("at") <= n - ceil(2 * percent * n, F.lit(100 + percent))), "prefixes")
    # A shingle's largest component: pairs across components have a member outside of it.
    largest = first.groupBy("h", "component").agg(F.count(F.lit(1)).alias("c")).groupBy("h").agg(F.max(F.struct("c", "component"))["component"].alias("largest"), F.count(F.lit(1)).alias("k")).filter("k > 1").select("h", "largest")
    met = materialize(first.join(largest, "h"), "met")
    a, b = met.filter("component <> largest").alias("a"), met.alias("b")
    col = F.col
    smaller = F.struct(col("a.n"), col("a.sid"), col("a.id")) < F.struct(col("b.n"), col("b.sid"), col("b.id"))
    # What two sets can have in common if this shingle is the first: it, and what follows in both.
    most = F.least(col("a.n") - col("a.at"), col("b.n") - col("b.at"))
    near = (100 * F.least(col("a.n"), col("b.n")) >= percent * F.greatest(col("a.n"), col("b.n"))) & ((100 + percent) * most >= percent * (col("a.n") + col("b.n")))
    pairs = a.join(b, (col("a.h") == col("b.h")) & (col("a.component") != col("b.component")) & F.when(smaller, col("a.short")).otherwise(col("b.short")) & near)
    pairs = materialize(pairs.select(F.least("a.id", "b.id").alias("src"), F.greatest("a.id", "b.id").alias("dst")).distinct(), "across")
    discard(first, met)
    return pairs


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """Per row: doc_id, n_shingles, component_id, kept.

    A row's set is its distinct shingles of k lower-cased words (all words, if
    fewer); rows link if 100 * intersection >= percent * union.

    Defined cases: null or empty text has an empty set and links with nothing. A
    null doc_id links with nothing; its component is null and it is kept. Rows
    that share a doc_id are one node with the links of each; each is returned.
    """
    with small_batches(docs.sparkSession):
        return _near_duplicates(docs, k, percent)


def _near_duplicates(docs: DataFrame, k: int, percent: int) -> DataFrame:
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    sketch = materialize(texts.mapInArrow(_sketch(k), _SKETCH), "sketch")
    some = sketch.filter("n > 0 and id is not null")
    # Equal sets: linked to the least id that has the set.
    classes = some.groupBy("digest").agg(F.min("id").alias("rep"))
    members = materialize(some.join(classes, "digest").select("id", "rep", "n", *_BITS, F.when(F.col("id") == F.col("rep"), F.col("bands")).alias("bands")), "members")
    reps = members.filter("id = rep")
    label = _equal(some, members)
    sizes = reps.select("id", "n", *_BITS)

    bands = reps.select("id", F.explode("bands").alias("key"))
    counted = bands.groupBy("key").agg(F.count(F.lit(1)).alias("k")).filter("k > 1")
    shared = materialize(bands.join(counted, "key"), "shared")
    popular = shared.groupBy("id").agg(F.sum("k").alias("popular"))
    rows, old = shared.join(popular, "id").select("key", "id", "popular"), [shared]
    for _ in range(ROUNDS):
        marked = materialize(rows.join(label, "id", "left").select("key", "id", "popular", F.coalesce("component", "id").alias("component")), "rows")
        discard(*old)
        leader = F.max(F.struct("popular", (-F.col("id")).alias("least"), F.col("component"))).alias("leader")
        keys = marked.groupBy("key").agg(leader, F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi").select("key", (-F.col("leader.least")).alias("leader"), F.col("leader.component").alias("its"))
        met = materialize(marked.join(keys, "key").filter("id <> leader"), "met")
        stars = met.filter("component <> its").select(F.col("id").alias("src"), F.col("leader").alias("dst")).distinct()
        stars = stars.join(sizes.alias("a"), F.col("src") == F.col("a.id")).join(sizes.alias("b"), (F.col("dst") == F.col("b.id")) & _near("a", "b", percent)).select("src", "dst").distinct()
        stars = materialize(stars, "stars")
        if not stars.isEmpty():
            label = _relabel(label, verify(stars, texts, k, percent))
        rows, old = met.select("key", "id", "popular"), [met]  # a leader has met all of its bucket
        discard(marked, stars)

    marked = rows.join(label, "id", "left").select("key", "id", F.coalesce("component", "id").alias("component"))
    keys = marked.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi").select("key")
    left = materialize(marked.join(keys, "key", "left_semi").select("id", "component").distinct(), "left")
    discard(*old)
    if not left.isEmpty():
        sets = sets_of(left.select("id"), texts, k)
        pairs = prefix_pairs(sets.join(left, "id"), percent)
        across = pairs.join(sizes.alias("a"), F.col("src") == F.col("a.id")).join(sizes.alias("b"), (F.col("dst") == F.col("b.id")) & _near("a", "b", percent)).select("src", "dst").distinct()
        across = materialize(across, "pairs")
        if not across.isEmpty():
            label = _relabel(label, verify(across, texts, k, percent))
        discard(sets, pairs, across)
    discard(left, members)
    return (
        sketch.select("id", "n").join(label, "id", "left")
        .select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("component", "id").alias("component_id"))
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )


def keep_one(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs' rows, one of each group of near duplicates: that of least doc_id, of equal ids that of least row hash.

    Defined cases: rows are told apart by all of their columns, so of rows that share a doc_id each has only its own
    links; of rows equal in all columns one stays. Null or empty texts and null doc_ids resemble nothing and stay.
    """
    rows, own = masked(docs)
    doc_id = F.col(own["doc_id"])
    known = rows.filter(doc_id.isNotNull()).withColumn("__node", F.xxhash64(*own.values()))
    slim = materialize(known.select("__node", doc_id.alias("doc_id")), "nodes")
    found = near_duplicates(known.select(F.col("__node").alias("doc_id"), F.col(own["text"]).alias("text")), k, percent).select(F.col("doc_id").alias("__node"), "component_id").distinct()
    placed = materialize(found.join(slim.distinct(), "__node"), "placed")
    best = placed.groupBy("component_id").agg(F.min(F.struct("doc_id", "__node"))["__node"].alias("best"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    gone = materialize(placed.join(best, "component_id").filter("__node <> best").select("__node").distinct(), "gone")
    twice = materialize(slim.groupBy("__node").count().filter("count > 1").select("__node"), "twice")
    left = only_ids(known, gone, "__node", keep=False)
    if not twice.isEmpty():
        left = only_ids(left, twice, "__node", keep=False).unionByName(only_ids(left, twice, "__node").dropDuplicates(["__node"]))
    discard(slim, placed)
    return left.select(*own.values()).unionByName(rows.filter(doc_id.isNull())).toDF(*own)
