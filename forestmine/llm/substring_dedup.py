"""Removal of repeated passages with a log-structured index of window fingerprints.

Batches arrive in order of doc_id. A batch's windows of 13 words are hashed,
dealt to buckets by hash and packed as sorted blocks; only this is shuffled. The index is a
list of immutable sorted runs, tables bucketed like the batch, so that a bucket's
task reads its part of a run where it lies and merge-joins it with the batch. A window is
repeated if a smaller doc_id holds it: in the batch, or in any run, as all that came before is smaller.
The batch's distinct windows become a run of their own; once FANOUT runs stand side by side they
are compacted into one, bucket by bucket and without a shuffle, into more buckets if these have grown.

A fingerprint is 64 bits and is verified by a second, independent hash of the same words (16 bits): windows
count as equal only if both are. Two different windows of N
are taken for one with N^2 / 2^81; the words themselves are not compared.
Inside a block repeats are settled where they are met, so a passage that a third
of all documents hold reaches its bucket once for each block, not document.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import _text
from ._spark import discard, fresh_path, materialize, only_ids, remove_path, small_batches

WINDOW = 13
#: Bytes of text in a block, windows meant for a bucket, bytes of text whose words are hashed at once.
BLOCK_BYTES, BUCKET_WINDOWS, PIECE = 4 << 20, 1_000_000, 1 << 18
#: Runs that are compacted into one; ranges of doc_id that a whole table is indexed in.
FANOUT, BATCHES = 2, 3
#: Buckets of an index at least; a whole table gets one for each BUCKET_WINDOWS windows.
LEAST_BUCKETS = 256

#: Mixed into words' hashes for the second hash.
_OTHER = np.uint64(0xA24BAED4963EE407)
#: A repeated window as a document gets it.
_PAIR = np.dtype([("h", np.uint64), ("s", np.uint16)])

_ROWS = "kind string, bucket int, doc_id long, payload binary, docs binary"


def _second(w: _text.Words, window: int) -> np.ndarray:
    """A second hash of each window."""
    other, _ = replace(w, hash=_text.mix64(w.hash + _OTHER)).windows(window)
    return (other >> np.uint64(48)).astype(np.uint16)


def _pack(values: np.ndarray) -> bytes:
    """Sorted 64-bit values as differences, byte plane by byte plane: the high planes are zeros and compress away."""
    return np.ascontiguousarray(np.diff(values, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T).tobytes()


def _unpack(data: bytes) -> np.ndarray:
    return np.cumsum(np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(8, -1).T).view(np.uint64).ravel(), dtype=np.uint64)


def _unpack_both(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Packed values and the second hashes behind them."""
    n = len(data) // 10
    return _unpack(data[: 8 * n]), np.frombuffer(data[8 * n :], np.uint16)


def _pack_ids(ids: np.ndarray) -> bytes:
    """Ids as a sorted dictionary and planes of places in it."""
    known, at = np.unique(ids, return_inverse=True)
    width = 2 if len(known) <= 1 << 16 else 4
    planes = np.ascontiguousarray(at.astype(np.uint32).view(np.uint8).reshape(-1, 4)[:, :width].T)
    return len(known).to_bytes(8, "little") + known.astype(np.int64).tobytes() + planes.tobytes()


def _unpack_ids(data: bytes) -> np.ndarray:
    n = int.from_bytes(data[:8], "little")
    known, planes = np.frombuffer(data[8 : 8 + 8 * n], np.int64), np.frombuffer(data[8 + 8 * n :], np.uint8)
    if not len(planes):
        return known[:0]
    width = 2 if n <= 1 << 16 else 4
    at = np.zeros((len(planes) // width, 4), np.uint8)
    at[:, :width] = planes.reshape(width, -1).T
    return known[at.view(np.uint32).ravel()]


def _sorted(h: np.ndarray, s: np.ndarray, *more: np.ndarray, blocks: bool = True) -> tuple[np.ndarray, ...]:
    """All arrays in order of both hashes. blocks: they are sorted blocks end to end, which are merged."""
    order = np.argsort(h, kind="stable" if blocks else None)
    h, s = h[order], s[order]
    if ((h[1:] == h[:-1]) & (s[1:] != s[:-1])).any():  # one hash of two windows
        by = np.lexsort((s, h))
        h, s, order = h[by], s[by], order[by]
    return h, s, *(x[order] for x in more)


def _starts(h: np.ndarray, s: np.ndarray) -> np.ndarray:
    """Where another window begins, in order of both hashes."""
    return np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (s[1:] != s[:-1]))))


def _settled(h: np.ndarray, s: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where windows begin, the least id that holds each, and which places are of larger ids."""
    start = _starts(h, s)
    least = np.minimum.reduceat(d, start)
    return start, least, d > np.repeat(least, np.diff(np.append(start, len(h))))


def _held(h: np.ndarray, s: np.ndarray, run_h: np.ndarray, run_s: np.ndarray) -> np.ndarray:
    """Which windows a sorted run holds."""
    out = np.zeros(len(h), bool)
    if len(run_h):
        at, open_ = np.searchsorted(run_h, h), np.arange(len(h))
        while len(open_):
            place = np.minimum(at, len(run_h) - 1)
            same = (run_h[place] == h[open_]) & (at < len(run_h))
            hit = same & (run_s[place] == s[open_])
            out[open_[hit]] = True
            more = same & ~hit
            open_, at = open_[more], at[more] + 1
    return out


def _by_doc(ids: np.ndarray, hashes: np.ndarray, second: np.ndarray) -> Iterator[tuple[int, bytes]]:
    order = np.argsort(ids, kind="stable")
    ids, pairs = ids[order], np.empty(len(order), _PAIR)
    pairs["h"], pairs["s"] = hashes[order], second[order]
    cuts = np.flatnonzero(np.diff(ids)) + 1
    for a, b in zip(np.concatenate(([0], cuts)), np.concatenate((cuts, [len(ids)]))):
        if b > a:
            yield int(ids[a]), pairs[a:b].tobytes()


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    kinds = ("string", "int32", "int64", "binary", "binary")
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kinds[i]) for i in range(5)], names=["kind", "bucket", "doc_id", "payload", "docs"])


def _edges(h: np.ndarray, buckets: int, low: int = 0, of: int = 1) -> list[int]:
    """Places that part sorted hashes into buckets, ranges of equal width; here those of range ``low`` of ``of``."""
    width = (1 << 64) // (buckets * of)
    inner = [(low * buckets + b) * width for b in range(1, buckets)]
    return [0, *np.searchsorted(h, np.array(inner, np.uint64)).tolist(), len(h)]


def _blocks(window: int, buckets: int):
    """Text rows to blocks (one for each bucket and some MB of text) and to repeats that the block itself shows."""

    def flush(hashes: list[np.ndarray], second: list[np.ndarray], ids: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        h, s, d = _sorted(np.concatenate(hashes), np.concatenate(second), np.concatenate(ids), blocks=False)
        start, least, late = _settled(h, s, d)
        h_new, s_new = h[start], s[start]
        edges = _edges(h_new, buckets)
        rows = [("block", b, None, _pack(h_new[x:y]) + s_new[x:y].tobytes(), _pack_ids(least[x:y])) for b, (x, y) in enumerate(zip(edges, edges[1:])) if y > x]
        rows += [("repeat", doc % buckets, doc, got, None) for doc, got in _by_doc(d[late], h[late], s[late])]
        yield _rows(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes: list[np.ndarray] = []
        second: list[np.ndarray] = []
        ids: list[np.ndarray] = []
        size = 0
        for batch in batches:
            doc = batch.column("doc_id").to_numpy(zero_copy_only=False)
            for w in _text.words(batch.column("text"), lower=False, most=PIECE):
                h, first = w.windows(window)
                hashes.append(h)
                second.append(_second(w, window))
                ids.append(np.repeat(doc[w.row : w.row + w.rows].astype(np.int64), np.diff(first)))
                size += len(w.raw)
                if size >= BLOCK_BYTES:
                    if sum(map(len, hashes)):
                        yield from flush(hashes, second, ids)
                    hashes, second, ids, size = [], [], [], 0
        if sum(map(len, hashes)):
            yield from flush(hashes, second, ids)

    return _text.lean(run)


def _run_of(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Both hashes of a bucket's part of a run."""
    got = [_unpack_both(x) for x in table.column("payload").to_pylist()]
    if len(got) < 2:
        return got[0] if got else (np.zeros(0, np.uint64), np.zeros(0, np.uint16))
    return _sorted(*(np.concatenate(x) for x in zip(*got)))


def _settle(keep: bool, ids: bool):
    """A bucket's blocks, merge-joined with a run's part: repeats, and (keep) the batch's own run with (ids) the least id that holds each window."""

    def run(group: pa.Table, old: pa.Table | None = None) -> pa.Table:
        out, hashes, second, docs = [], [], [], []
        bucket = group.column("bucket")[0].as_py() if len(group) else None
        for kind, doc, payload, owners in zip(*(group.column(c).to_pylist() for c in ("kind", "doc_id", "payload", "docs"))):
            if kind == "repeat":
                out.append(("repeat", bucket, doc, payload, None))
            else:
                for part, got in zip((hashes, second), _unpack_both(payload)):
                    part.append(got)
                docs.append(_unpack_ids(owners))
        if hashes:
            h, s, d = _sorted(np.concatenate(hashes), np.concatenate(second), np.concatenate(docs))
            start, least, late = _settled(h, s, d)
            if old is not None:
                # All of a held window's places, as blocks come in any order: the first needn't be the least id's.
                late |= np.repeat(_held(h[start], s[start], *_run_of(old)), np.diff(np.append(start, len(h))))
            out += [("repeat", bucket, doc, got, None) for doc, got in _by_doc(d[late], h[late], s[late])]
            if keep:
                out.append(("run", bucket, None, _pack(h[start]) + s[start].tobytes(), _pack_ids(least) if ids else None))
        return pa.Table.from_batches([_rows(out)])

    return run


def _probe(new: pa.Table, old: pa.Table) -> pa.Table:
    """Windows of a batch's run that an older run holds, as repeats of the least id that has each."""
    out = []
    for bucket, payload, owners in zip(*(new.column(c).to_pylist() for c in ("bucket", "payload", "docs"))):
        h, s = _unpack_both(payload)
        found = _held(h, s, *_run_of(old))
        out += [("repeat", bucket, doc, got, None) for doc, got in _by_doc(_unpack_ids(owners)[found], h[found], s[found])]
    return pa.Table.from_batches([_rows(out)])


def _compact(buckets: int, split: int):
    """A bucket of two runs as one, in ``split`` buckets."""

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        bucket = (a if len(a) else b).column("bucket")[0].as_py()
        h, s = _sorted(*(np.concatenate(x) for x in zip(_run_of(a), _run_of(b))))
        start = _starts(h, s) if len(h) else []
        h, s = h[start], s[start]
        edges = _edges(h, split, bucket, buckets)
        return pa.Table.from_batches([_rows([("run", bucket * split + i, None, _pack(h[x:y]) + s[x:y].tobytes(), None) for i, (x, y) in enumerate(zip(edges, edges[1:])) if y > x])])

    return run


class FingerprintIndex:
    """Sorted immutable runs on shared storage; each batch adds one, and FANOUT of them become one."""

    def __init__(self, spark: SparkSession, path: str | None = None, buckets: int = 256, window: int = WINDOW):
        self.spark, self.buckets, self.window = spark, 1 << (max(1, buckets) - 1).bit_length(), window
        self.path = path or fresh_path(spark, "fingerprints")
        self.runs: list[str] = []

    def _write(self, rows: DataFrame, buckets: int) -> str:
        """A table bucketed like all runs: a run's bucket is read by one task, without a shuffle."""
        name = f"fingerprints_{uuid.uuid4().hex}"
        rows.write.partitionBy("kind").bucketBy(buckets, "bucket").option("path", f"{self.path}/{name}").option("compression", "zstd").saveAsTable(name)
        return name

    def _run(self, name: str, *more: str) -> DataFrame:
        return self.spark.table(name).filter("kind = 'run'").select("bucket", "payload", *more)

    def _remove(self, names: list[str]) -> None:
        for name in names:
            self.spark.sql(f"DROP TABLE IF EXISTS {name}")
            remove_path(self.spark, f"{self.path}/{name}")

    def add(self, batch: DataFrame, keep: bool = True) -> DataFrame:
        """Index (doc_id, text), later than all before it. Returns (doc_id, payload): both hashes of the doc's repeated windows."""
        with small_batches(self.spark):
            return self._add(batch, keep)

    def _add(self, batch: DataFrame, keep: bool) -> DataFrame:
        blocks = batch.select(F.col("doc_id").cast("long"), "text").filter("doc_id is not null").mapInArrow(_blocks(self.window, self.buckets), _ROWS).groupBy("bucket")
        older = self.runs[:-1]
        settle = _settle(keep or bool(older), bool(older))
        rows = blocks.cogroup(self._run(self.runs[-1]).groupBy("bucket")).applyInArrow(settle, _ROWS) if self.runs else blocks.applyInArrow(lambda group: settle(group), _ROWS)
        name = self._write(rows, self.buckets)
        repeats = [self.spark.table(name).filter("kind = 'repeat'").select("doc_id", "payload")]
        repeats += [self._run(name, "docs").groupBy("bucket").cogroup(self._run(run).groupBy("bucket")).applyInArrow(_probe, _ROWS).select("doc_id", "payload") for run in older]
        found = repeats[0]
        for more in repeats[1:]:
            found = found.union(more)
        found = materialize(found, "repeats")
        del blocks, rows
        self.spark._jvm.System.gc()  # lets Spark remove the batch's shuffle files
        if keep:
            self.runs.append(name)
            if len(self.runs) >= FANOUT:
                self.compact()
        else:
            self._remove([name])
        return found

    def compact(self) -> None:
        """All runs become one; buckets are split while they are larger than meant."""
        while len(self.runs) > 1:
            a, b = self.runs[:2]
            split = 1
            if len(self.runs) == 2:
                windows = self._run(a).union(self._run(b)).agg(F.max(F.length("payload"))).first()[0] or 0
                while windows * 2 > 10 * split * BUCKET_WINDOWS:
                    split *= 2
            both = self._run(a).groupBy("bucket").cogroup(self._run(b).groupBy("bucket")).applyInArrow(_compact(self.buckets, split), _ROWS)
            name = self._write(both, self.buckets * split)
            self._remove([a, b])
            self.runs, self.buckets = [name, *self.runs[2:]], self.buckets * split

    def drop(self) -> None:
        self._remove(self.runs)
        self.runs = []
        remove_path(self.spark, self.path)


def _remove(window: int):
    """(doc_id, text, payloads) to the contract's columns; payloads null: nothing repeats."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = batch.column("payloads")
            for w in _text.words(batch.column("text"), lower=False, most=PIECE):
                h, first = w.windows(window)
                second = None
                counts, raw = w.counts(), w.raw.tobytes()
                removed, digest, texts = [], [], []
                for i in range(w.rows):
                    kept = raw[w.offsets[i] : w.offsets[i + 1]].split()
                    gone, got = 0, found[w.row + i].as_py()
                    if got:
                        second = _second(w, window) if second is None else second
                        own, pairs = slice(first[i], first[i + 1]), np.frombuffer(b"".join(got), _PAIR)
                        at = np.flatnonzero(np.isin(h[own], pairs["h"]))
                        known = set(pairs.tolist())
                        at = at[np.array([p in known for p in zip(h[own][at].tolist(), second[own][at].tolist())], bool)]
                        step = np.zeros(counts[i] + 1, np.int64)
                        np.add.at(step, at, 1)
                        np.add.at(step, at + window, -1)
                        covered = np.cumsum(step)[:-1] > 0
                        gone = int(covered.sum())
                        kept = [x for x, c in zip(kept, covered.tolist()) if not c]
                    removed.append(gone)
                    texts.append(b" ".join(kept))
                    digest.append(hashlib.sha256(texts[-1]).hexdigest())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(w.row, w.rows), pa.array(counts.astype(np.int64)), pa.array(removed, "int64"), pa.array(digest, "string"), pa.array(texts, "binary").cast("string")], names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"])

    return _text.lean(run)


def dedup_substrings(docs: DataFrame, window: int = WINDOW, batches: int = BATCHES, index: FingerprintIndex | None = None) -> DataFrame:
    """Per row: doc_id, n_words, n_removed, kept_sha256, kept_text.

    A word goes if a window that covers it has its word sequence also in a
    document with a smaller doc_id. The table is indexed in ``batches`` ranges of
    doc_id; a given index must hold smaller ids only, and is kept for later batches.

    Defined cases: null or empty text has no words. A row with null doc_id is
    neither indexed nor changed. Rows that share a doc_id aren't repeats of each
    other; each loses what smaller ids hold. kept_text joins words by one space. An empty table gives no rows.
    """
    texts = docs.select(F.col("doc_id").cast("long"), "text")
    known = texts.filter("doc_id is not null")
    seen = known.agg(F.sum(F.length("text")).alias("chars"), F.percentile_approx("doc_id", [i / batches for i in range(1, batches)] or [0.5], 10_000).alias("cuts")).first()
    held = index or FingerprintIndex(docs.sparkSession, buckets=max(LEAST_BUCKETS, (seen.chars or 0) // (6 * BUCKET_WINDOWS)), window=window)
    cuts = sorted(set(seen.cuts or [])) if batches > 1 else []
    parts = []
    for i in range(len(cuts) + 1):
        part = known
        if i:
            part = part.filter(F.col("doc_id") > cuts[i - 1])
        if i < len(cuts):
            part = part.filter(F.col("doc_id") <= cuts[i])
        parts.append(held.add(part, keep=index is not None or i < len(cuts)))
    if index is None:
        held.drop()
    repeats = parts[0]
    for more in parts[1:]:
        repeats = repeats.union(more)
    lists = materialize(repeats.groupBy("doc_id").agg(F.collect_list("payload").alias("payloads")), "payloads")
    discard(*parts)
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string"
    touched = lists.select("doc_id")
    whole = only_ids(texts, touched, "doc_id", keep=False).withColumn("payloads", F.lit(None).cast("array<binary>"))
    cut = only_ids(texts, touched, "doc_id").join(lists, "doc_id")
    return whole.union(cut).mapInArrow(_remove(window), schema)
