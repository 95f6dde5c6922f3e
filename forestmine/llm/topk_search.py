"""Exact top-k by inner product with MaxScore over packed shards of postings.

Dimensions are the terms. A shard holds its rows by dimension, a posting list of components in order of rows, in
integers as small as they allow, with the least and largest of each list: so each query knows what a dimension can add at most.
Dimensions are sorted by what they can add; the leading, essential lists are traversed for all
rows, and the rest is probed only for rows whose bound still reaches the query's
k-th score so far. Where most rows stay competitive the probe is one dense product.

Queries go in packed blocks. A task meets its shards with each block, one pair after the other, and keeps
one list for each query, whose k-th score bounds the next shard; what leaves a task is merged by rank. Neither
rows nor queries are shuffled but once, when they are packed, as long as the blocks are few enough to be broadcast.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import _text
from ._spark import discard, materialize, small_batches

#: Rows of a shard, queries of a block, rows scored at once; share of rows up to which the rest is probed row by row.
SHARD, BLOCK, STRIP, SPARSE = 8192, 2048, 2048, 0.1
#: Bytes of packed queries that are broadcast at most; beyond that shards are dealt to them by a shuffle.
BROADCAST_BYTES = 64 << 20


def _matrix(column: pa.ChunkedArray, width: int) -> np.ndarray:
    """Rows of integers, short ones filled with zeros."""
    column = column.combine_chunks()
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    size = np.diff(column.offsets.to_numpy())
    out = np.zeros((len(size), width), np.int64)
    out[np.arange(width)[None, :] < size[:, None]] = values
    return out


def _best(score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k largest of each column, ties to the smaller place, as (k, columns); scores are integers below 2^50."""
    n = len(score)
    key = score.astype(np.int64) * n + np.arange(n - 1, -1, -1)[:, None]
    top = np.argpartition(-key, min(k, n) - 1, axis=0)[: min(k, n)] if n > k else np.tile(np.arange(n)[:, None], (1, score.shape[1]))
    return np.take_along_axis(top, np.argsort(-np.take_along_axis(key, top, 0), axis=0), 0)


def max_score(ids: np.ndarray, rows: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, k: int, floor: np.ndarray | None = None, seen: dict | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query place, row id, score) of each query's k best rows of a shard, rows of its own id left out.

    floor: scores that a row must reach to matter to each query. seen: gets the numbers of components that were looked at, and of all.
    """
    order = np.argsort(ids, kind="stable")
    ids, rows = ids[order], rows[order]
    limit = float(np.abs(rows).max(initial=0)) * float(np.abs(queries).max(initial=0)) * max(1, rows.shape[1])
    kind = np.float64 if limit < 2.0**50 else object
    low, high = rows.min(0), rows.max(0)
    bound = np.maximum(queries.astype(kind) * high.astype(kind), queries.astype(kind) * low.astype(kind))  # what a dimension adds at most
    terms = np.argsort(-np.abs(bound).sum(0).astype(float), kind="stable")
    rows, queries, bound = rows[:, terms].astype(kind), queries[:, terms].astype(kind), bound[:, terms]
    nothing = np.float64(-(2.0**51)) if kind is np.float64 else -(1 << 200)
    reach = np.full(len(query_ids), nothing, kind) if floor is None else np.where(floor == LEAST, nothing, floor.astype(kind))
    best_row = np.full((0, len(query_ids)), 0, np.int64)
    best_score = np.full((0, len(query_ids)), nothing, kind)
    for begin in range(0, len(ids), STRIP):
        strip = rows[begin : begin + STRIP]
        rest = bound.sum(1)
        essential = 0
        while essential < rows.shape[1] and np.mean((rest >= reach).astype(float)) > SPARSE:
            rest = rest - bound[:, essential]  # the suffix that alone may still reach the k-th score is traversed
            essential += 1
        score = strip[:, :essential] @ queries[:, :essential].T
        looked = essential * score.size
        if essential < rows.shape[1]:
            alive = score + rest >= reach
            looked += (rows.shape[1] - essential) * int(alive.sum())
            if alive.mean() > SPARSE:
                score = score + strip[:, essential:] @ queries[:, essential:].T
                looked = score.size * rows.shape[1]
            else:
                at, of = np.nonzero(alive)
                full = score[at, of] + (strip[at, essential:] * queries[of, essential:]).sum(1)
                score = np.full(score.shape, nothing, kind)
                score[at, of] = full
        score = np.where(ids[begin : begin + STRIP, None] == query_ids[None, :], nothing, score)
        if kind is np.float64:
            top = _best(score, k)
        else:
            top = np.stack([np.array(sorted(range(len(score)), key=lambda i: (-score[i, q], i))[:k]) for q in range(len(query_ids))], 1)
        best_row = np.concatenate((best_row, begin + top))
        best_score = np.concatenate((best_score, np.take_along_axis(score, top, 0)))
        keep = np.stack([np.lexsort((best_row[:, q], -best_score[:, q]))[:k] for q in range(len(query_ids))], 1) if kind is np.float64 else np.stack([np.array(sorted(range(len(best_row)), key=lambda i: (-best_score[i, q], best_row[i, q]))[:k]) for q in range(len(query_ids))], 1)
        best_row, best_score = np.take_along_axis(best_row, keep, 0), np.take_along_axis(best_score, keep, 0)
        if len(best_row) == k:
            reach = np.maximum(reach, best_score[-1])
        if seen is not None:
            seen["looked"], seen["all"] = seen.get("looked", 0) + looked, seen.get("all", 0) + score.size * rows.shape[1]
    at, of = np.nonzero(best_score > nothing)
    return of, ids[best_row[at, of]], best_score[at, of]


#: Stands for no score.
LEAST = np.int64(-(1 << 63))
_PACKED = "part int, n int, width int, ids binary, v binary"


def _pack(group: pa.Table) -> pa.Table:
    """Rows (part, id, v) as one: ids in order, and components by dimension, in the smallest integers that hold them."""
    column = group.column("v").combine_chunks()
    width = int(np.diff(column.offsets.to_numpy()).max(initial=0))
    ids, rows = group.column("id").to_numpy(), _matrix(group.column("v"), width)
    order = np.argsort(ids, kind="stable")
    small = np.result_type(np.min_scalar_type(rows.min(initial=0)), np.int8, np.min_scalar_type(-int(rows.max(initial=0)) - 1))
    return pa.table([pa.array(x, t) for x, t in ((group.column("part").to_pylist()[:1], "int32"), ([len(ids)], "int32"), ([width], "int32"), ([ids[order].tobytes()], "binary"), ([bytes([small.itemsize]) + rows[order].T.astype(small).tobytes()], "binary"))], names=["part", "n", "width", "ids", "v"])


def _unpack(n: int, width: int, ids: bytes, v: bytes) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(ids, np.int64), np.frombuffer(v, f"i{v[0]}", offset=1).reshape(width, n).T.astype(np.int64)


def _wider(rows: np.ndarray, width: int) -> np.ndarray:
    return np.pad(rows, ((0, 0), (0, width - rows.shape[1]))) if rows.shape[1] < width else rows


def _search(k: int):
    """Pairs of a shard and a block of queries to each query's k best rows of all shards of a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[int, list[np.ndarray]] = {}
        asked: dict[int, np.ndarray] = {}
        for batch in batches:
            for r in batch.to_pylist():
                ids, rows = _unpack(r["n"], r["width"], r["ids"], r["v"])
                query_ids, queries = _unpack(r["q_n"], r["q_width"], r["q_ids"], r["q_v"])
                width = max(r["width"], r["q_width"])
                if r["block"] not in best:
                    asked[r["block"]], best[r["block"]] = query_ids, [np.full((len(query_ids), k), LEAST), np.zeros((len(query_ids), k), np.int64)]
                score, found = best[r["block"]]
                of, row, got = max_score(ids, _wider(rows, width), query_ids, _wider(queries, width), k, score[:, -1])
                place = np.arange(len(of)) - np.searchsorted(np.sort(of), np.sort(of))
                order = np.argsort(of, kind="stable")
                new_score, new_found = np.full((len(query_ids), k), LEAST), np.zeros((len(query_ids), k), np.int64)
                new_score[of[order], place], new_found[of[order], place] = got[order].astype(np.int64), row[order]
                score, found = np.concatenate((score, new_score), 1), np.concatenate((found, new_found), 1)
                keep = np.lexsort((found, -np.maximum(score, LEAST + 1)), axis=1)[:, :k]
                best[r["block"]] = [np.take_along_axis(score, keep, 1), np.take_along_axis(found, keep, 1)]
        for block, (score, found) in best.items():
            of, at = np.nonzero(score > LEAST)
            yield pa.RecordBatch.from_arrays([pa.array(asked[block][of]), pa.array(found[of, at]), pa.array(score[of, at])], names=["query_id", "vec_id", "score"])

    return _text.lean(run)


def top_k(vectors: DataFrame, is_query: Column, k: int = 20) -> DataFrame:
    """(vec_id, v array<long>), and which ``id`` asks, to query_id, rank, vec_id, score: each query's k best by integer inner product.

    Defined cases: null vectors, vectors with a null and null ids take no part. All
    rows of the query's own id are left out. A repeated query id is asked once, with
    its least vector; repeated candidate rows each count. Shorter vectors are filled
    with zeros. Ties go to the smaller id. An empty table gives no rows.
    """
    rows = vectors.select(F.col("vec_id").cast("long").alias("id"), "v").filter(F.col("id").isNotNull() & F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull()))
    asked = rows.filter(is_query).groupBy("id").agg(F.min("v").alias("v"))
    with small_batches(vectors.sparkSession, rows=8, size="16m"):
        n, q = rows.count(), asked.count()
        shards, blocks = max(1, -(-n // SHARD)), max(1, -(-q // BLOCK))
        part = lambda of, *by: F.pmod(F.xxhash64(*by), F.lit(of)).cast("int").alias("part")
        packed = materialize(rows.select(part(shards, "id", "v"), "id", "v").groupBy("part").applyInArrow(_pack, _PACKED), "shards")
        queries = materialize(asked.select(part(blocks, "id"), "id", "v").groupBy("part").applyInArrow(_pack, _PACKED).toDF("block", "q_n", "q_width", "q_ids", "q_v"), "queries")
        size = queries.agg(F.sum(F.length("q_ids") + F.length("q_v"))).first()[0] or 0
        each = packed.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
        pairs = each.join(F.broadcast(queries) if size <= BROADCAST_BYTES else queries, "block")
        found = materialize(pairs.mapInArrow(_search(k), "query_id long, vec_id long, score long"), "found")
        discard(packed, queries)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")


def scaled_embeddings(df: DataFrame, by: int = 64) -> DataFrame:
    """(vec_id, embedding) to (vec_id, v): floor(by * x) of finite vectors, null for others."""
    bad = F.col("embedding").isNull() | F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return df.select("vec_id", F.when(~bad, F.transform("embedding", lambda x: F.floor(F.lit(float(by)) * x.cast("double")))).alias("v"))
