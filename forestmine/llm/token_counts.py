"""Token counts by a two-tier lookup on the map side.

A text falls apart where white space follows another character: no pre-token of the
byte-level pattern reaches over such a place, and none there looks further ahead than
the next character after its white space. So a text's count is the sum over these groups, white
space and what follows it. Tier one is a compact hash table of frequent groups' numbers of tokens,
broadcast; tier two a table in each worker that the tokenizer itself fills. Nothing is shuffled.

Groups are known by a 64-bit hash of their bytes; both tables are looked up for whole arrays. Tier
one comes from a bounded sample and only saves time: a group that it lacks is encoded, so counts never depend on it.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import _text

#: Rows, and characters of each, from which frequent groups are taken; groups in the broadcast table at most (12 bytes for each of 4 times as many slots).
SAMPLE_ROWS, SAMPLE_CHARS, FREQUENT = 2000, 10_000, 1 << 16
#: Slots of a worker's table, as a power of two; bytes of text counted at once.
SLOTS, PIECE = 20, 1 << 18

#: White space of one byte.
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
#: Last two bytes of Unicode's white space of two bytes, last three of that of three.
_WIDE2, _WIDE3 = [0xC285, 0xC2A0], [0xE19A80, *range(0xE28080, 0xE2808B), 0xE280A8, 0xE280A9, 0xE280AF, 0xE2819F, 0xE38080]


class PreTokens:
    """A tokenizer file, and whether its texts fall apart as above."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pre = spec["pre_tokenizer"] or {}
        self.plain = not spec["normalizer"] and pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space")
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.own = _text.HashTable(SLOTS)

    def lengths(self, texts: list[str]) -> list[int]:
        return [len(e.ids) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def counts(self, keys: np.ndarray, table: _text.HashTable, raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Tokens of each group."""
        out = table.find(keys)
        rare = np.flatnonzero(out < 0)
        if len(rare):
            out[rare] = self.own.find(keys[rare])
            new, at = np.unique(keys[rare[out[rare] < 0]], return_index=True)
            if len(new):
                at = rare[out[rare] < 0][at]
                if self.own.size + len(new) > self.own.most:
                    self.own.clear()
                got = np.array(self.lengths([raw[start[j] : end[j]].tobytes().decode() for j in at.tolist()]), np.int32)
                if len(new) <= self.own.most:
                    self.own.add(new, got)
                left = rare[out[rare] < 0]
                out[left] = got[np.searchsorted(new, keys[left])]
        return out


_pre: dict[str, PreTokens] = {}


def pre_tokens(path: str) -> PreTokens:
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    if path not in _pre:
        _pre[path] = PreTokens(path)
    return _pre[path]


def groups(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where groups begin and end: at a row's beginning, and at white space after another character."""
    space = _SPACE[raw]
    begins = np.zeros(len(raw), bool)
    begins[1:] = space[1:] & ~space[:-1]
    wide = np.flatnonzero(begins & (np.concatenate(([0], raw[:-1])) >= 0x80))  # the character before may be white space, too
    if len(wide):
        at = lambda k: raw[np.maximum(wide - k, 0)].astype(np.int64)
        two = at(2) << 8 | at(1)
        begins[wide[np.isin(two, _WIDE2) | np.isin(at(3) << 16 | two, _WIDE3)]] = False
    begins[offsets[:-1][np.diff(offsets) > 0]] = True
    start = np.flatnonzero(begins)
    return start, np.append(start[1:], len(raw)) if len(start) else start


def _keyed(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    start, end = groups(raw, offsets)
    return start, end, _text.span_hashes(raw.astype(np.uint64) + np.uint64(1), start, end)


def frequent_groups(docs: DataFrame, path: str) -> _text.HashTable:
    """The broadcast table: of groups found twice or more in a sample, the FREQUENT most frequent ones."""
    pre, table = pre_tokens(path), _text.HashTable((FREQUENT - 1).bit_length() + 2)
    sample = pa.array([r[0] for r in docs.select(F.left("text", F.lit(SAMPLE_CHARS))).limit(SAMPLE_ROWS).collect()], pa.string())
    known: dict[int, list] = {}
    for _, raw, offsets in _text.pieces(sample, PIECE):
        start, end, keys = _keyed(raw, offsets)
        new, at, n = np.unique(keys, return_index=True, return_counts=True)
        for key, i, c in zip(new.tolist(), at.tolist(), n.tolist()):
            if key in known:
                known[key][0] += c
            else:
                known[key] = [c, raw[start[i] : end[i]].tobytes()]
    most = sorted(((c, key, text) for key, (c, text) in known.items() if c > 1), reverse=True)[:FREQUENT]
    if most:
        table.add(np.array([key for _, key, _ in most], np.uint64), np.array(pre.lengths([text.decode() for *_, text in most]), np.int32))
    return table


def _count(path: str, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pre = pre_tokens(path)
        for batch in batches:
            column = batch.column("text")
            whole = np.full(len(batch), not pre.plain)
            for s in pre.special:
                whole |= pc.fill_null(pc.match_substring(column, s), False).to_numpy(zero_copy_only=False)
            for row, raw, offsets in _text.pieces(column, PIECE):
                n = np.zeros(len(offsets) - 1, np.int64)
                if pre.plain:
                    start, end, keys = _keyed(raw, offsets)
                    total = np.concatenate(([0], np.cumsum(pre.counts(keys, shared.value, raw, start, end))))
                    n = np.diff(total[np.searchsorted(start, offsets)])
                for i in np.flatnonzero(whole[row : row + len(n)]):
                    n[i] = pre.lengths([raw[offsets[i] : offsets[i + 1]].tobytes().decode()])[0]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(row, len(n)), pa.array(np.diff(offsets)), pa.array(n)], names=["doc_id", "n_bytes", "n_tokens"])

    return _text.lean(run)


def count_tokens(docs: DataFrame, path: str, limit: int = 1024) -> DataFrame:
    """Per row: doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit).

    Counts are those of the tokenizer file at ``path``, without added tokens, whole
    texts. Defined cases: null or empty text counts 0; a text with a special
    string, and any text of a tokenizer that isn't plain byte-level, is encoded
    whole; doc_id may be null or repeat, each row is counted by itself; an empty table gives no rows.
    """
    table = frequent_groups(docs, path) if pre_tokens(path).plain else None
    shared = docs.sparkSession.sparkContext.broadcast(table)
    counted = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_count(path, shared), "doc_id long, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
