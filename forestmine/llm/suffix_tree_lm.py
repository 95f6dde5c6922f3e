"""A probabilistic suffix tree over words, and a unigram base, for scoring texts.

Learning: words are counted over all training documents. A context (the words
before, most recent last) is a candidate if it occurs MIN_CONTEXT times, and stays
in the tree if its next-word distribution diverges from that of the context one word
shorter. Its distribution keeps next words that follow it MIN_NEXT times,
discounts them, and gives what is left to the shorter context, down to add-one
unigrams; so each state's distribution sums to one. Both supports are absolute: what
is gathered grows with the corpus.

Runs of words are known by a 64-bit hash. Each depth's runs are counted in buckets of
keys, where they are sent as places in the list of frequent words, and joined with the depth
before; the tree is a table by key. Written as factors,
a text's log10 probability is its unigram base plus a weight for each run
in it (a run's gain as a next word, and what it leaves as a context). So runs are
looked up one by one: the HOT most frequent ones where they are read, others leave
their number of uses and meet the table in buckets of keys, as rare words meet the word counts.

A run can have a weight only if the run without its last word is a context of the tree: so longer runs
are looked up only where shorter ones were found.

Broadcast sizes are bounded whatever the data: at most WORDS words, HOT runs and
two filters of FILTER_BITS, which only spare rows.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import _text
from ._spark import discard, materialize, small_batches, sweep

#: Words at most whose root probability is broadcast, the most frequent ones.
WORDS = 1 << 18
#: Times that a context must occur, and a next word after it.
MIN_CONTEXT, MIN_NEXT = 16, 4
#: Longest context in words; nats an occurrence by which a context must differ; discount of kept counts.
DEPTH, DIVERGENCE, DISCOUNT = 4, 0.02, 0.75
#: Nats in all, besides one for each next word, by which a context must differ: less comes by chance once in about 1e5 contexts or more often.
CHANCE = 10
#: Runs broadcast at most; bits of a filter (a power of two) and parts that it is put together in; runs packed at once; runs meant for a bucket.
HOT, FILTER_BITS, FILTER_PARTS, RUNS_AT_ONCE, RUNS_IN_BUCKET = 2_000_000, 1 << 26, 64, 300_000, 1_000_000
#: Scored tokens meant for a bucket of what is looked up by joins: few buckets, as each adds to most documents.
TOKENS_IN_BUCKET = 8_000_000
#: Bytes of text whose words are hashed at once.
PIECE = 1 << 18
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: The end token: no word's hash counts as it but by a 64-bit collision.
END = np.uint64(0x1F83D9ABFB41BD6B)


def held_out(doc_id: Column, folds: int = 7, fold: int = 2) -> Column:
    """crc32 of the id's decimal text modulo folds; null counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % folds == fold


def _tokens(column: pa.Array) -> Iterator[tuple[_text.Words, np.ndarray, np.ndarray]]:
    """Pieces with their token hashes, an end after each row's words, and each row's first token."""
    for w in _text.words(column, lower=True, most=PIECE):
        n = w.counts()
        tokens = np.full(len(w.hash) + w.rows, END)
        tokens[np.arange(len(w.hash)) + np.repeat(np.arange(w.rows), n)] = w.hash
        yield w, tokens, w.first + np.arange(w.rows + 1)


def _emit(keys: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts.astype(np.int64))], names=["h", "c"])


class _Tally:
    """Counts of 64-bit keys; gives them out when a million distinct ones have gathered."""

    def __init__(self) -> None:
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.size = 0

    def add(self, keys: np.ndarray) -> Iterator[pa.RecordBatch]:
        self.parts.append(np.unique(keys, return_counts=True))
        self.size += len(self.parts[-1][0])
        if self.size > 4_000_000:
            keys, counts = self.merged()
            self.parts, self.size = [(keys, counts)], len(keys)
            if self.size > 1_000_000:
                yield from self.flush()

    def merged(self) -> tuple[np.ndarray, np.ndarray]:
        keys, at = np.unique(np.concatenate([k for k, _ in self.parts]), return_inverse=True)
        return keys, np.bincount(at, np.concatenate([c for _, c in self.parts]), len(keys)).astype(np.int64)

    def flush(self) -> Iterator[pa.RecordBatch]:
        if self.size:
            yield _emit(*self.merged())
        self.parts, self.size = [], 0


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    tally = _Tally()
    for batch in batches:
        for _, tokens, _ in _tokens(batch.column("text")):
            yield from tally.add(tokens)
    yield from tally.flush()


def _extend(key: np.ndarray, tokens: np.ndarray) -> np.ndarray:
    """Keys of runs of words that are one word longer."""
    return _text.mix64(key * _ODD + tokens)


def _runs(tokens: np.ndarray, row: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each length up to ``most``: keys of the runs that end at each token, and where they lie in one row."""
    key, inside = tokens, np.ones(len(tokens), bool)
    yield key, inside
    for d in range(1, most):
        longer = np.zeros(len(tokens), np.uint64)
        longer[1:] = _extend(key[:-1], tokens[1:])
        inside = inside.copy()
        inside[:d] = False
        inside[d:] &= row[d:] == row[:-d]
        key = longer
        yield key, inside


def _probes(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two places in a filter."""
    k = _text.mix64(keys)
    return (k & np.uint64(FILTER_BITS - 1)).astype(np.int64), ((k >> np.uint64(32)) & np.uint64(FILTER_BITS - 1)).astype(np.int64)


def _may_hold(bits: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Whether a filter may hold the keys; never false for a key that it holds."""
    a, b = _probes(keys)
    return ((bits[a >> 3] >> (a & 7).astype(np.uint8)) & (bits[b >> 3] >> (b & 7).astype(np.uint8)) & 1).astype(bool)


def _mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    bits = np.zeros(FILTER_BITS // 8, np.uint8)
    for batch in batches:
        for at in _probes(batch.column(0).to_numpy().view(np.uint64)):
            np.bitwise_or.at(bits, at >> 3, np.uint8(1) << (at & 7).astype(np.uint8))
    parts = bits.reshape(FILTER_PARTS, -1)
    some = np.flatnonzero(parts.any(1))
    yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array([pa.compress(parts[i].tobytes(), "zstd", asbytes=True) for i in some], "binary")], names=["part", "bits"])


def _merge_marks(group: pa.Table) -> pa.Table:
    bits = functools.reduce(np.bitwise_or, (np.frombuffer(pa.decompress(x, FILTER_BITS // 8 // FILTER_PARTS, "zstd", asbytes=True), np.uint8) for x in group["bits"].to_pylist()))
    return pa.table([group["part"].slice(0, 1), pa.array([pa.compress(bits.tobytes(), "zstd", asbytes=True)], "binary")], names=["part", "bits"])


def _filter(keys: DataFrame) -> np.ndarray:
    """A filter of fixed size over (key), put together by parts: it only spares rows, what it lets through by chance finds no partner."""
    bits, kind = np.zeros((FILTER_PARTS, FILTER_BITS // 8 // FILTER_PARTS), np.uint8), "part int, bits binary"
    for r in keys.mapInArrow(_mark, kind).groupBy("part").applyInArrow(_merge_marks, kind).collect():
        bits[r["part"]] = np.frombuffer(pa.decompress(bytes(r["bits"]), bits.shape[1], "zstd", asbytes=True), np.uint8)
    return bits.ravel()


def _find(keys: np.ndarray, wanted: np.ndarray, values: np.ndarray, none=-1) -> np.ndarray:
    if not len(keys):
        return np.full(len(wanted), none, values.dtype)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, values[at], none)


def _table(keys: np.ndarray) -> _text.HashTable:
    """Places of distinct keys."""
    out = _text.HashTable(max(4, len(keys).bit_length() + 1))
    out.add(keys, np.arange(len(keys)))
    return out


def _most(counts: DataFrame, room: int) -> int:
    """The least floor(4 log2(c)) from which rows (c) are ``room`` at most: so coarse steps keep the histogram small."""
    steps = {r["step"]: r["count"] for r in counts.groupBy(_step()).count().collect()}
    least = max(steps, default=0) + 1
    for step in sorted(steps, reverse=True):
        room -= steps[step]
        if room < 0:
            break
        least = step
    return least


def _step() -> Column:
    return F.floor(4 * F.log2("c")).alias("step")


class Tree:
    """The hot part of the tree, which is broadcast: frequent words, and runs of words with their weights.

    A run's weight is what each occurrence adds to a text's log10 probability: as a next word
    after a context (nexts) and as a context (lefts). State 0 is the root; contexts[depth] maps keys to states.
    """

    def __init__(self, words: np.ndarray, counts: np.ndarray, total: int, kinds: int):
        order = np.argsort(words)
        self.words, self.total, self.kinds = words[order], total, kinds
        self.root = np.log10((counts[order] + 1.0) / (total + kinds + 1.0))
        self.keys, self.nexts, self.lefts = np.zeros(0, np.uint64), np.zeros(0), np.zeros(0)
        self.contexts: list[tuple[np.ndarray, np.ndarray]] = []
        self.state_keys, self.parent, self.left = np.zeros(1, np.uint64), np.zeros(1, np.int64), np.ones(1)
        self.cold = np.zeros(FILTER_BITS // 8, np.uint8)

    def fill(self, hot: pa.Table) -> None:
        """From (key, nexts, lefts, depth, suffix); with a context all its suffixes are hot, as they are more frequent."""
        column = lambda name, kind: hot[name].to_numpy().astype(kind)
        key = column("key", np.int64).view(np.uint64)
        order = np.argsort(key)
        self.keys, self.nexts, self.lefts = key[order], column("nexts", float)[order], column("lefts", float)[order]
        depth, suffix = column("depth", np.int64)[order], column("suffix", np.int64).view(np.uint64)[order]
        stays = np.flatnonzero(self.lefts < 0)
        stays = stays[np.argsort(depth[stays], kind="stable")]
        number = np.zeros(len(self.keys), np.int64)
        number[stays] = np.arange(1, len(stays) + 1)
        above = _find(self.keys, suffix, np.arange(len(self.keys)))
        up = np.where(depth > 1, above, -1)[stays]
        for _ in range(int(depth.max(initial=0))):  # past suffixes that did not stay
            skip = (up >= 0) & (number[up] == 0)
            up[skip] = np.where(depth[up[skip]] > 1, above[up[skip]], -1)
        self.parent = np.concatenate(([0], np.where(up >= 0, number[up], 0)))
        self.state_keys, self.left = np.concatenate((self.state_keys, self.keys[stays])), np.concatenate((self.left, 10.0 ** self.lefts[stays]))
        for d in range(1, int(depth[stays].max(initial=0)) + 1):
            at = stays[depth[stays] == d]
            self.contexts.append((np.sort(self.keys[at]), number[at][np.argsort(self.keys[at])]))

    def log10(self, state: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """log10 P(word | state) for words of the table."""
        out = self.root[ids]
        while state.any():
            out = out + np.where(state > 0, np.log10(self.left[state]) + _find(self.keys, _extend(self.state_keys[state], self.words[ids]), self.nexts, 0.0), 0.0)
            state = self.parent[state]
        return out


def _planes(columns: list[np.ndarray]) -> bytes:
    """Columns of one length, each as planes of its first bytes, second bytes and so on."""
    return b"".join(np.ascontiguousarray(np.ascontiguousarray(c).view(np.uint8).reshape(len(c), -1).T).tobytes() for c in columns)


def _columns(data: np.ndarray, n: int, kinds: list) -> list[np.ndarray]:
    """The columns of planes."""
    out, x = [], 0
    for kind in map(np.dtype, kinds):
        out.append(np.ascontiguousarray(data[x : x + n * kind.itemsize].reshape(kind.itemsize, n).T).view(kind).ravel())
        x += n * kind.itemsize
    return out


def _packed(columns: list[np.ndarray]) -> bytes:
    return pa.compress(_planes(columns), "zstd", asbytes=True)


def _unpacked(payload: bytes, n: int, kinds: list) -> list[np.ndarray]:
    return _columns(np.frombuffer(pa.decompress(payload, n * sum(np.dtype(k).itemsize for k in kinds), "zstd", asbytes=True), np.uint8), n, kinds)


def _count_runs(shared, words: int, buckets: int):
    """Runs of ``words`` words, counted and packed: a row for each bucket of keys.

    Their context may be frequent, and the run without its oldest word, which is no rarer, may be a next word itself.
    A word is packed as its place among the frequent words, or past their end as its place among the others' hashes, which end a payload.
    """

    def flush(parts: list[tuple[np.ndarray, np.ndarray]], others: list[np.ndarray], known: int) -> Iterator[pa.RecordBatch]:
        key, ids = (np.concatenate(x) for x in zip(*parts))
        others = np.concatenate(others)
        order = np.argsort(key)
        new = np.concatenate(([True], np.diff(key[order]) != 0))
        count = np.diff(np.concatenate((np.flatnonzero(new), [len(key)]))).astype(np.uint32)
        at = order[new]
        bucket = key[at] >> np.uint64(64 - buckets.bit_length() + 1)
        order = np.argsort(ids[at, 0].astype(np.uint64) << np.uint64(32) | ids[at, 1].astype(np.uint64))
        order = order[np.argsort(bucket[order].astype(np.uint16 if buckets <= 1 << 16 else np.uint32), kind="stable")]
        ids, count, edges = ids[at[order]], count[order], np.searchsorted(bucket[order], np.arange(buckets + 1))
        rows = []
        for b, (x, y) in enumerate(zip(edges, edges[1:])):
            if y > x:
                own = ids[x:y]
                rare = own >= known
                used, place = np.unique(own[rare], return_inverse=True)
                own[rare] = known + place
                data = _planes([np.diff(own[:, 0], prepend=np.uint32(0)), *own[:, 1:].T, count[x:y]])
                rows.append((b, int(y - x), len(used), pa.compress(data + others[used - known].tobytes(), "zstd", asbytes=True)))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(("int32", "int32", "int32", "binary"))], names=["bucket", "n", "others", "payload"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        contexts, suffixes, frequent = shared.value
        places, known = _table(frequent), len(frequent)
        parts, others, size, rare = [], [], 0, 0
        for batch in batches:
            for w, tokens, first in _tokens(batch.column("text")):
                row = np.repeat(np.arange(w.rows), np.diff(first))
                keys = list(_runs(tokens, row, words))
                at = np.flatnonzero(keys[-1][1])
                at = at[_may_hold(contexts, keys[-2][0][at - 1])]
                at = at[_may_hold(suffixes, keys[-2][0][at])]
                ids = places.find(tokens).astype(np.int64)
                used = np.zeros(len(tokens), bool)
                for i in range(words):
                    used[at - i] = True
                used = np.flatnonzero(used & (ids < 0))
                ids[used] = known + rare + np.arange(len(used))
                parts.append((keys[-1][0][at], np.stack([ids[at - i] for i in range(words - 1, -1, -1)], 1).astype(np.uint32)))
                others.append(tokens[used])
                size, rare = size + len(at), rare + len(used)
                if size >= RUNS_AT_ONCE:
                    yield from flush(parts, others, known)
                    parts, others, size, rare = [], [], 0, 0
        if size:
            yield from flush(parts, others, known)

    return _text.lean(run)


def _sum_runs(shared, words: int):
    """A bucket's packed counts to (key, ctx, pkey, c) of runs that occur MIN_NEXT times; pkey is the run without its oldest word."""

    def chain(tokens: list[np.ndarray]) -> np.ndarray:
        return functools.reduce(_extend, tokens)

    def run(group: pa.Table) -> pa.Table:
        frequent, parts = shared.value[2], []
        for n, others, payload in zip(group["n"].to_pylist(), group["others"].to_pylist(), group["payload"].to_pylist()):
            wide = 4 * (words + 1) * n
            data = np.frombuffer(pa.decompress(payload, wide + 8 * others, "zstd", asbytes=True), np.uint8)
            *ids, count = _columns(data, n, [np.uint32] * (words + 1))
            ids[0] = np.cumsum(ids[0], dtype=np.uint32)
            hashes = np.concatenate((frequent, np.frombuffer(data[wide:].tobytes(), np.uint64)))
            tokens = [hashes[x] for x in ids]
            ctx = chain(tokens[:-1])
            parts.append((_extend(ctx, tokens[-1]), ctx, chain(tokens[1:]), count.astype(np.int64)))
        key, ctx, pkey, count = (np.concatenate(x) for x in zip(*parts))
        order = np.argsort(key)
        start = np.flatnonzero(np.concatenate(([True], np.diff(key[order]) != 0)))
        c = np.add.reduceat(count[order], start)
        at, c = order[start][c >= MIN_NEXT], c[c >= MIN_NEXT]
        return pa.Table.from_arrays([pa.array(x.view(np.int64)) for x in (key[at], ctx[at], pkey[at], c)], names=["key", "ctx", "pkey", "c"])

    return run


def _levels(docs: DataFrame, counts: DataFrame, frequent: np.ndarray, n: int, v: int, depth: int) -> tuple[DataFrame, list[DataFrame]] | None:
    """The whole tree: (key, c, nexts, lefts, depth, suffix, again), a row for each context (again: its key has another) and one for each next word; and the tables that it is read from."""
    spark, found, levels = docs.sparkSession, [], []
    # Runs of the last length: how often, their probability after their context, and the run without its oldest word.
    last = counts.select(F.col("h").alias("key"), "c", ((F.col("c") + 1) / F.lit(n + v + 1.0)).alias("p"), F.lit(0).cast("long").alias("pkey"), F.lit(0.0).alias("nexts")).filter(f"key <> {int(END.view(np.int64))}")
    end = counts.filter(f"h = {int(END.view(np.int64))}").select(F.col("h").alias("key"), "c", ((F.col("c") + 1) / F.lit(n + v + 1.0)).alias("p"))
    buckets = 1 << max(6, int(n // RUNS_IN_BUCKET).bit_length())
    by = Window.partitionBy("ctx")
    for d in range(1, depth + 1):
        contexts = last.filter(F.col("c") >= MIN_CONTEXT)
        above = (last.select("key", "c", "p") if d > 1 else last.select("key", "c", "p").union(end)).filter(F.col("c") >= MIN_NEXT)
        shared = spark.sparkContext.broadcast((_filter(contexts.select("key")), _filter(above.select("key")), frequent))
        packed = docs.select("text").mapInArrow(_count_runs(shared, d + 1, buckets), "bucket int, n int, others int, payload binary")
        runs = packed.groupBy("bucket").applyInArrow(_sum_runs(shared, d + 1), "key long, ctx long, pkey long, c long")
        counted = materialize(runs, "runs")
        shared.destroy()
        del packed, runs
        sweep(spark)
        # A run is no more frequent than its parts, so each finds both. The rows of a context come together once, for all that is asked of it.
        runs = counted.join(above.select(F.col("key").alias("pkey"), F.col("p").alias("above")), "pkey")
        runs = runs.join(contexts.select(F.col("key").alias("ctx"), F.col("c").alias("t"), F.col("pkey").alias("suffix"), (F.col("nexts") != 0).alias("again")), "ctx")
        share = F.expr(f"(c - {DISCOUNT}D) / t")
        sums = {"gain": F.sum(F.expr("c * ln(c / t / above)")), "kept": F.sum(share), "kinds": F.count("c"), "seen": F.sum("c"), "sure": F.sum("above"), "least": F.min("key")}
        runs = runs.select("*", *(x.over(by).alias(k) for k, x in sums.items()))
        # The other next words count as one. A context must differ by more than its next words could by chance.
        gain = F.col("gain") + F.expr("if(seen < t, (t - seen) * ln((t - seen) / t / greatest(1 - sure, 1e-12D)), 0D)")
        runs = runs.withColumn("stays", gain >= F.greatest(DIVERGENCE * F.col("t"), CHANCE + F.col("kinds")))
        runs = runs.withColumn("left", F.when(F.col("stays"), 1 - F.col("kept")).otherwise(1.0))
        runs = runs.withColumn("p", F.when(F.col("stays"), share + F.col("left") * F.col("above")).otherwise(F.col("above")))
        nexts = F.when(F.col("stays"), F.log10(F.col("p") / (F.col("left") * F.col("above")))).otherwise(0.0)
        head = F.col("key") == F.col("least")  # one row of a context holds what is known of it
        last = materialize(runs.select("key", "c", "p", "pkey", nexts.alias("nexts"), *(F.when(head, F.col(x)).alias(x) for x in ("ctx", "t", "suffix", "left", "again"))), "tree")
        discard(counted)
        del runs
        sweep(spark)
        levels.append(last)
        zero = F.lit(0).cast("long")
        found.append(last.filter("ctx is not null").select(F.col("ctx").alias("key"), F.col("t").alias("c"), F.lit(0.0).alias("nexts"), F.log10("left").alias("lefts"), F.lit(d).cast("long").alias("depth"), "suffix", "again"))
        found.append(last.filter("nexts <> 0").select("key", "c", "nexts", F.lit(0.0).alias("lefts"), zero.alias("depth"), zero.alias("suffix"), F.lit(False).alias("again")))
        if last.isEmpty():
            break
    return (functools.reduce(DataFrame.union, found), levels) if found else None


def _grow(docs: DataFrame, depth: int, states: bool) -> tuple[Tree, DataFrame, DataFrame | None]:
    """The hot part (with its states, if asked), the word counts (h, c), and the weights (h, weight) of the rest, whose rows add up; None if there is no rest."""
    spark = docs.sparkSession
    sum_up = lambda df: df.groupBy("h").agg(F.sum("c").alias("c"))
    counts = materialize(sum_up(docs.select("text").mapInArrow(_count_words, "h long, c long")), "words")
    sweep(spark)
    size = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count("c").alias("v")).first()
    frequent = counts.filter(_step() >= _most(counts, WORDS)).toArrow()
    words, often = frequent["h"].to_numpy().astype(np.int64).view(np.uint64), frequent["c"].to_numpy().astype(np.int64)
    tree = Tree(words, often, size.n, size.v)
    grown = _levels(docs, counts, words[np.argsort(-often, kind="stable")], size.n, size.v, depth) if size.n else None
    if grown is None:
        return tree, counts, None
    weights, levels = grown
    # Both rows of a key hold the same count, so they are hot or not together.
    hot = _step() >= _most(weights.filter("not again"), HOT)
    if states:
        tree.fill(_once(weights.filter(hot).select("key", "nexts", "lefts", "depth", "suffix").toArrow()))
    else:
        got = _once(weights.filter(hot).select("key", (F.col("nexts") + F.col("lefts")).alias("weight")).toArrow())
        tree.keys, tree.nexts, tree.lefts = got["key"].to_numpy().astype(np.int64).view(np.uint64), got["weight"].to_numpy().astype(float), 0.0
    rest = materialize(weights.filter(~hot).select(F.col("key").alias("h"), (F.col("nexts") + F.col("lefts")).alias("weight")), "weights")
    discard(*levels)
    if rest.filter("weight <> 0").isEmpty():
        return tree, counts, None
    tree.cold = _filter(rest.select("h"))  # a context of no weight leads on to longer ones
    return tree, counts, rest.filter("weight <> 0")


def _once(rows: pa.Table) -> pa.Table:
    """One row for each key, the other columns summed."""
    key = rows["key"].to_numpy()
    order = np.argsort(key)
    start = np.flatnonzero(np.concatenate(([True], np.diff(key[order]) != 0))) if len(key) else order
    return pa.table({"key": key[order[start]], **{x: np.add.reduceat(rows[x].to_numpy()[order], start) if len(key) else rows[x] for x in rows.column_names[1:]}})


def learn(docs: DataFrame, depth: int = DEPTH) -> tuple[Tree, DataFrame]:
    """From (text) of all training documents: the tree's hot part, and the table of word counts (h, c)."""
    with small_batches(docs.sparkSession):
        return _grow(docs, depth, states=True)[:2]


def _uses(row: np.ndarray, keys: np.ndarray, rows: int) -> pa.ListArray:
    """(row, key) pairs as a list of (h, uses) for each row."""
    order = np.argsort(keys)
    order = order[np.argsort(row[order].astype(np.uint16 if rows <= 1 << 16 else np.uint32), kind="stable")]
    row, keys = row[order], keys[order]
    new = np.concatenate(([True], (row[1:] != row[:-1]) | (keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, bool)
    uses = np.diff(np.concatenate((np.flatnonzero(new), [len(new)]))) if len(new) else np.zeros(0, np.int64)
    bound = np.searchsorted(row[new], np.arange(rows + 1)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(bound), pa.StructArray.from_arrays([pa.array(keys[new].view(np.int64)), pa.array(uses.astype(np.int64))], names=["h", "uses"]))


class _Hot:
    """What scoring needs of a tree: tables of words and runs, and a filter of the runs that aren't broadcast."""

    def __init__(self, tree: Tree, cold: bool):
        self.words, self.root = _table(tree.words), tree.root
        self.runs, self.weights = _table(tree.keys), tree.nexts + tree.lefts
        self.cold = tree.cold if cold else None


def _score(shared, depth: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree: _Hot = shared.value
        for batch in batches:
            doc = batch.column("doc_id").to_pylist()
            for w, tokens, first in _tokens(batch.column("text")):
                ids = tree.words.find(tokens)
                row = np.repeat(np.arange(w.rows), np.diff(first))
                base = np.where(ids >= 0, tree.root[np.maximum(ids, 0)] if len(tree.root) else 0.0, 0.0)
                logs, rest = base.copy(), [(row[:0], tokens[:0])]
                at, key = np.arange(len(tokens)), tokens
                for _ in range(depth + 1):
                    found = tree.runs.find(key)
                    hit = found >= 0
                    logs[at[hit]] += tree.weights[found[hit]]
                    if tree.cold is not None:
                        more = np.flatnonzero(~hit)
                        more = more[_may_hold(tree.cold, key[more])]
                        rest.append((row[at[more]], key[more]))
                        hit[more] = True
                    hit &= at + 1 < len(tokens)
                    hit[hit] = row[at[hit]] == row[at[hit] + 1]
                    at, key = at[hit] + 1, _extend(key[hit], tokens[at[hit] + 1])
                at, rare = first[:-1], ids < 0
                yield pa.RecordBatch.from_arrays(
                    [pa.array(doc[w.row : w.row + w.rows], "int64"), pa.array(np.diff(first).astype(np.int64)), pa.array(np.add.reduceat((ids >= 0).astype(np.int64), at)), pa.array(np.add.reduceat(base, at)), pa.array(np.add.reduceat(logs, at)), _uses(row[rare], tokens[rare], w.rows), _uses(*(np.concatenate(x) for x in zip(*rest)), w.rows)],
                    names=["doc_id", "n_tokens", "n_known", "base_score", "score", "misses", "runs"],
                )

    return _text.lean(run)


def score_texts(docs: DataFrame, training: Column | None = None, depth: int = DEPTH) -> DataFrame:
    """Per row: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Tokens are words of the lower-cased text and one end. base_score sums
    log10((c + 1) / (N + V + 1)) over tokens; score is the tree's log10
    probability. Training rows are those that aren't held out, or ``training``.

    Defined cases: null or empty text has one token, the end. A null doc_id counts
    as the empty text for the fold. Rows that share a doc_id are scored (and
    learnt from) each by itself. Without training rows N = V = 0. An empty table gives no rows.
    """
    with small_batches(docs.sparkSession):  # throughout: workers of either setting would stay beside each other
        return _score_texts(docs, training, depth)


#: Kinds of packed rows: uses of rare words and of runs by documents, and the tables that hold their counts and weights.
MISSES, RUNS, COUNTS, WEIGHTS = range(4)
_PACKED = "bucket int, kind int, chunk long, n int, payload binary"


def _by_bucket(kind: int, chunk: int, buckets: int, keys: np.ndarray, *columns: np.ndarray) -> Iterator[tuple]:
    """Packed rows of keys and columns, one for each bucket of keys."""
    order = np.argsort(keys)
    keys = keys[order]
    edges = np.append(np.searchsorted(keys, np.arange(buckets, dtype=np.uint64) << np.uint64(64 - buckets.bit_length() + 1)), len(keys))
    for b, (x, y) in enumerate(zip(edges, edges[1:])):
        if y > x:
            yield b, kind, chunk, int(y - x), _packed([np.diff(keys[x:y], prepend=np.uint64(0)), *(c[order[x:y]] for c in columns)])


def _packed_batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(("int32", "int32", "int64", "int32", "binary"))], names=["bucket", "kind", "chunk", "n", "payload"])


def _pack_uses(buckets: int):
    """(rid, misses, runs) to packed rows. A chunk is the documents whose rids differ in the last 16 bits only."""

    def flush(chunk: int, parts: list[tuple]) -> Iterator[pa.RecordBatch]:
        rows = []
        for kind in (MISSES, RUNS):
            rows += _by_bucket(kind, chunk, buckets, *(np.concatenate(x) for x in zip(*(own for k, *own in parts if k == kind))))
        if rows:
            yield _packed_batch(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk, parts, size = None, [], 0
        for batch in batches:
            rid = batch.column("rid").to_numpy()
            for x, y in zip(cuts := [0, *(np.flatnonzero(np.diff(rid >> 16)) + 1).tolist()], [*cuts[1:], len(rid)]):
                if y > x and (chunk != rid[x] >> 16 or size >= RUNS_AT_ONCE):
                    if parts:
                        yield from flush(chunk, parts)
                    chunk, parts, size = int(rid[x] >> 16), [], 0
                for kind, name in ((MISSES, "misses"), (RUNS, "runs")):
                    lists = batch.column(name).slice(x, y - x)
                    uses = lists.flatten()
                    doc = np.repeat((rid[x:y] & 0xFFFF).astype(np.uint16), lists.value_lengths().to_numpy())
                    parts.append((kind, uses.field(0).to_numpy().view(np.uint64), doc, uses.field(1).to_numpy().astype(np.uint32)))
                    size += len(doc)
        if parts:
            yield from flush(chunk, parts)

    return _text.lean(run)


def _pack_table(kind: int, buckets: int):
    """(h, value) to packed rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, size = [], 0
        for batch in batches:
            parts.append((batch.column(0).to_numpy().view(np.uint64), batch.column(1).to_numpy()))
            size += len(batch)
            if size >= RUNS_AT_ONCE:
                yield _packed_batch(list(_by_bucket(kind, 0, buckets, *(np.concatenate(x) for x in zip(*parts)))))
                parts, size = [], 0
        if size:
            yield _packed_batch(list(_by_bucket(kind, 0, buckets, *(np.concatenate(x) for x in zip(*parts)))))

    return run


def _look_up(total: int, kinds: int):
    """A bucket's uses and tables to what they add to each document of a chunk."""

    def run(group: pa.Table) -> pa.Table:
        kind, chunk, n = (group[x].to_numpy() for x in ("kind", "chunk", "n"))

        def columns(i: int, *own) -> list[np.ndarray]:
            out = _unpacked(group["payload"][i].as_py(), n[i], [np.uint64, *own])
            return [np.cumsum(out[0], dtype=np.uint64), *out[1:]]

        def table(wanted: int, value) -> tuple[np.ndarray, np.ndarray]:
            parts = [columns(i, value) for i in np.flatnonzero(kind == wanted)] or [[np.zeros(0, np.uint64), np.zeros(0, value)]]
            keys, at = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
            sums = np.zeros(len(keys), value)
            np.add.at(sums, at, np.concatenate([v for _, v in parts]))
            return keys, sums

        counts, weights, rows = table(COUNTS, np.int64), table(WEIGHTS, float), []
        for i in np.flatnonzero(kind <= RUNS):
            keys, doc, uses = columns(i, np.uint16, np.uint32)
            if kind[i] == MISSES:
                c = _find(counts[0], keys, counts[1], 0)
                used = np.flatnonzero(np.bincount(doc))
                more, add = np.bincount(doc, uses * (c > 0))[used], np.bincount(doc, uses * np.log10((c + 1) / float(total + kinds + 1)))[used]
                own = [used.astype(np.uint16), more.astype(np.uint32), add]
            else:
                w = _find(weights[0], keys, weights[1], 0.0)
                hit = w != 0
                used = np.flatnonzero(np.bincount(doc[hit]))
                own = [used.astype(np.uint16), np.bincount(doc[hit], uses[hit] * w[hit])[used]]
            if len(used):
                rows.append((int(kind[i]), int(chunk[i]), len(used), _packed(own)))
        return pa.table([pa.array([r[i] for r in rows], t) for i, t in enumerate(("int32", "int64", "int32", "binary"))], names=["kind", "chunk", "n", "payload"])

    return run


def _add_up(group: pa.Table) -> pa.Table:
    """What all buckets add to the documents of a chunk: (rid, more, add, runs_add)."""
    used, more, add, runs = np.zeros(1 << 16, bool), np.zeros(1 << 16, np.int64), np.zeros(1 << 16), np.zeros(1 << 16)
    for kind, n, payload in zip(group["kind"].to_pylist(), group["n"].to_pylist(), group["payload"]):
        if kind == MISSES:
            doc, m, a = _unpacked(payload.as_py(), n, [np.uint16, np.uint32, float])
            more[doc] += m
            add[doc] += a
        else:
            doc, a = _unpacked(payload.as_py(), n, [np.uint16, float])
            runs[doc] += a
        used[doc] = True
    at = np.flatnonzero(used)
    return pa.table({"rid": (group["chunk"][0].as_py() << 16) + at, "more": more[at], "add": add[at], "runs_add": runs[at]})


def _score_texts(docs: DataFrame, training: Column | None, depth: int) -> DataFrame:
    out = held_out(F.col("doc_id"))
    learnt = docs.filter(~out if training is None else training).select("text")
    tree, counts, cold = _grow(learnt, depth, states=False)
    total, kinds = int(tree.total), int(tree.kinds)
    shared = docs.sparkSession.sparkContext.broadcast(_Hot(tree, cold is not None))
    del tree
    schema = "doc_id long, n_tokens long, n_known long, base_score double, score double, misses array<struct<h long, uses long>>, runs array<struct<h long, uses long>>"
    scored = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_score(shared, depth), schema)
    scored = materialize(scored.withColumn("rid", F.monotonically_increasing_id()), "scored")
    shared.destroy()
    sweep(docs.sparkSession)
    tokens = scored.agg(F.coalesce(F.sum("n_tokens"), F.lit(0))).first()[0]
    buckets = 1 << max(2, int(tokens // TOKENS_IN_BUCKET).bit_length())
    packed = scored.select("rid", "misses", "runs").mapInArrow(_pack_uses(buckets), _PACKED)
    packed = packed.union(counts.select("h", "c").mapInArrow(_pack_table(COUNTS, buckets), _PACKED))
    if cold is not None:
        packed = packed.union(cold.select("h", "weight").mapInArrow(_pack_table(WEIGHTS, buckets), _PACKED))
    sums = packed.groupBy("bucket").applyInArrow(_look_up(total, kinds), "kind int, chunk long, n int, payload binary")
    sums = sums.groupBy("chunk").applyInArrow(_add_up, "rid long, more long, add double, runs_add double")
    scored = scored.drop("misses", "runs").join(sums, "rid", "left")
    add = F.coalesce("add", F.lit(0.0))
    return scored.select(
        "doc_id", out.alias("held_out"), "n_tokens", (F.col("n_known") + F.coalesce("more", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (F.col("base_score") + add).alias("base_score"), (F.col("score") + add + F.coalesce("runs_add", F.lit(0.0))).alias("score"),
    )
