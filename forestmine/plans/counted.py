"""Mining that keeps vertices only: a task makes the records of its whole trees anew at each level.

Kept states grow with the occurrences, and joins by tree meet every pair of a tree's vertices. Here a
task reads its trees in order, some ten thousand vertices at a time. Their vertices are numbered end to end, so that a
scope is a slice: a record meets just the vertices that it can be extended by. Frequent patterns of the levels before
steer the way to the last but one level; candidates of the last are counted where they are met. Only counts leave the task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import pattern as pt

#: Vertices that are worked on at a time (more, if one tree has more); pairs at a time; places of a table that is held densely.
CHUNK, PAIRS, DENSE = 1 << 15, 1 << 20, 1 << 23
_COUNTS = "code long, tree long, support long, trees long, n long"


@dataclass
class Records:
    """Rows: pattern, last vertex, ends of the rightmost path (-1 below the last vertex), multiplicity; whole: all matched vertices."""

    pattern: np.ndarray
    last: np.ndarray
    path: list[np.ndarray]
    mult: np.ndarray
    matched: list[np.ndarray] | None


class Trees:
    """Whole trees, their vertices end to end: the descendants of i are i + 1 to end[i]."""

    def __init__(self, tree: np.ndarray, lo: np.ndarray, hi: np.ndarray, label: np.ndarray):
        new = np.concatenate(([True], tree[1:] != tree[:-1])) if len(tree) else np.zeros(0, bool)
        self.tree, self.lo, self.label, self.rank, self.ids = tree, lo, label, np.cumsum(new) - 1, tree[new]
        width = int(max(hi.max(initial=0), lo.max(initial=0))) + 1
        self.end = np.searchsorted(self.rank * width + lo, self.rank * width + hi, "right") - 1


class Lookup:
    """Values by code, -1 for codes that are not there: a table if that is small, else by search."""

    def __init__(self, codes: np.ndarray, values: np.ndarray, size: int):
        order = np.argsort(codes)
        self.codes, self.values, self.size, self.table = codes[order], values[order], size, None

    def find(self, codes: np.ndarray) -> np.ndarray:
        if not len(self.codes):
            return np.full(len(codes), -1)
        if self.size <= DENSE:
            if self.table is None:
                self.table = np.full(self.size, -1, np.int32)
                self.table[self.codes] = self.values
            return self.table[codes]
        at = np.minimum(np.searchsorted(self.codes, codes), len(self.codes) - 1)
        return np.where(self.codes[at] == codes, self.values[at], -1)


def _safe(mult: np.ndarray) -> np.ndarray:
    """Multiplicities whose sum fits 64 bits; else this raises."""
    if len(mult) and float(mult.sum(dtype=np.float64)) > 9e18:
        raise ArithmeticError("a count passes 64 bits; count as decimal")
    return mult


def _pairs(r: Records, labels: int, label: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Blocks of (record, vertex, depth of attachment, candidate's code): every vertex after a record's last one in its root's scope."""
    some = np.flatnonzero(r.path[0] > r.last)
    size = r.path[0][some] - r.last[some]
    ends, depths = np.cumsum(size), len(r.path)
    at = 0
    while at < len(some):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + PAIRS, "right")))
        rows, n = some[at:to], size[at:to]
        x = np.arange(n.sum()) + np.repeat(r.last[rows] + 1 - (np.cumsum(n) - n), n)
        c = np.zeros(len(x), np.int64)
        for bound in r.path[1:]:
            c += np.repeat(bound[rows], n) >= x
        yield np.repeat(rows, n), x, c, np.repeat(r.pattern[rows] * (depths * labels), n) + c * labels + label[x]
        at = to


def _merged(r: Records, patterns: int, vertices: int) -> Records:
    """Records of equal pattern, last vertex and path become one."""
    keys: list[np.ndarray] = []
    room = 0
    for column, top in [(r.pattern, patterns), (r.last, vertices), *((p + 1, vertices + 1) for p in r.path)]:
        need = int(top).bit_length()
        if need <= room:
            keys[-1], room = keys[-1] << need | column, room - need
        else:
            keys.append(column.astype(np.int64))
            room = 63 - need
    order = np.argsort(keys[0]) if len(keys) == 1 else np.lexsort(keys)
    other = np.zeros(max(len(order) - 1, 0), bool)
    for k in keys:
        other |= k[order[1:]] != k[order[:-1]]
    start = np.flatnonzero(np.concatenate(([True], other))) if len(order) else order
    own = order[start]
    mult = np.add.reduceat(_safe(r.mult)[order], start) if len(order) else r.mult
    return Records(r.pattern[own], r.last[own], [p[own] for p in r.path], mult, None)


def _grown(r: Records, t: Trees, labels: int, found: Lookup, patterns: int, whole: bool) -> Records:
    """Records of the next level's frequent patterns."""
    parts = []
    for row, x, c, code in _pairs(r, labels, t.label):
        new = found.find(code)
        keep = np.flatnonzero(new >= 0)
        row, x, c = row[keep], x[keep], c[keep]
        path = [p[row] for p in r.path] + [np.full(len(row), -1)]
        for j in range(1, len(path)):
            path[j] = np.where(c + 1 == j, t.end[x], np.where(c + 1 > j, path[j], -1))
        part = Records(new[keep].astype(np.int64), x, path, r.mult[row], [*(m[row] for m in r.matched), x] if whole else None)
        parts.append(part if whole else _merged(part, patterns, len(t.lo)))
    if not parts:
        none = np.zeros(0, np.int64)
        return Records(none, none, [none] * (len(r.path) + 1), none, [none] * (len(r.path) + 1) if whole else None)
    joined = lambda columns: [np.concatenate(x) for x in zip(*columns)]
    out = Records(*(np.concatenate([getattr(p, f) for p in parts]) for f in ("pattern", "last")), joined(p.path for p in parts), np.concatenate([p.mult for p in parts]), joined(p.matched for p in parts) if whole else None)
    return out if whole or len(parts) == 1 else _merged(out, patterns, len(t.lo))


def _tallied(r: Records, t: Trees, labels: int, patterns: int, allowed: Lookup | None, by_tree: bool) -> list[np.ndarray]:
    """(code, tree, support, trees, n) of the candidates that the trees hold; by_tree: for each tree, else for all of them."""
    size = patterns * len(r.path) * labels
    ones = bool((_safe(r.mult) == 1).all())
    dense = not by_tree and size * len(t.ids) <= DENSE
    total, pairs, held = (np.zeros(size, np.int64), np.zeros(size, np.int64), np.zeros(size * len(t.ids), bool)) if dense else ([], [], [])
    for row, x, _, code in _pairs(r, labels, t.label):
        if allowed is not None:
            keep = np.flatnonzero(allowed.find(code) >= 0)
            row, x, code = row[keep], x[keep], code[keep]
        where = t.rank[x] * size + code
        if dense:
            n = np.bincount(code, minlength=size)
            pairs += n
            held[where] = True
            if ones:
                total += n
            else:
                np.add.at(total, code, _safe(r.mult[row]))
        else:
            order = np.argsort(where)
            where = where[order]
            start = np.flatnonzero(np.concatenate(([True], where[1:] != where[:-1]))) if len(where) else order
            held.append(where[start])
            total.append(np.add.reduceat(_safe(r.mult[row])[order], start) if len(where) else order)
            pairs.append(np.diff(np.append(start, len(where))))
    if dense:
        code = np.flatnonzero(pairs)
        return [code, np.full(len(code), -1), total[code], held.reshape(len(t.ids), size).sum(0)[code], pairs[code]]
    none = [np.zeros(0, np.int64)]
    where, total, pairs = (np.concatenate(none + x) for x in (held, total, pairs))
    code, tree = where % max(size, 1), where // max(size, 1)
    # A tree's candidate may be met in several blocks: it counts as one tree at its first place only.
    first = np.zeros(len(where), np.int64)
    first[np.unique(where, return_index=True)[1]] = 1
    return [code, t.ids[tree] if by_tree else np.full(len(code), -1), total, first, pairs]


def _kernel(roots: np.ndarray, steps: list[Lookup], sizes: list[int], labels: int, allowed: Lookup | None, whole: bool, spread: int):
    """Vertices in order of tree and lo to counts of the candidates one vertex larger than the last of ``sizes``."""

    def count(columns: list[np.ndarray]) -> pa.RecordBatch:
        t = Trees(*columns)
        pattern, at = roots[t.label], np.arange(len(t.lo))
        mine = pattern >= 0
        if spread > 1:  # a copy of a tree has its share of the roots
            mine &= (t.lo * 2654435761 >> 16) % spread == t.tree % spread
        at = at[mine]
        r = Records(pattern[at], at, [t.end[at]], np.ones(len(at), np.int64), [at] if whole else None)
        for step, size in zip(steps, sizes[1:]):
            r = _grown(r, t, labels, step, size, whole)
        out = _tallied(r, t, labels, sizes[-1], allowed, spread > 1)
        return pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in out], names=["code", "tree", "support", "trees", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        size = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append([batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(4)])
            size += batch.num_rows
            if size >= CHUNK and held[-1][0][-1] != held[0][0][0]:
                columns = [np.concatenate(x) for x in zip(*held)]
                cut = int(np.flatnonzero(columns[0][1:] != columns[0][:-1])[-1]) + 1
                yield count([x[:cut] for x in columns])
                held, size = [[x[cut:] for x in columns]], size - cut
        if size:
            yield count([np.concatenate(x) for x in zip(*held)])

    return run


def mine(v: DataFrame, minsup: int, max_size: int | None, labels: DataFrame, rule: str = "prefix", support: str = "occurrence", whole: bool = False, guided: bool = False, spread: int = 1) -> DataFrame:
    """As mine.levelwise: the PATTERNS columns. whole: every occurrence is a record with all its matched vertices, nothing is merged.

    labels: mine.frequent_labels of v. n_records is null from size 2 on, as merged records of the largest patterns are never made; with ``whole`` it is
    the number of occurrences. spread: tasks that a tree's root occurrences are dealt to, each with a copy of its vertices.
    """
    from ..operators.mine import _allowed, _result, hinted

    spark = v.sparkSession
    measure, n_labels = ("tree_support" if support == "tree" else "support"), 0
    rows, level = [], {}
    for r in labels.orderBy("label").collect():
        level[len(rows)] = ((pt.escape(r["label"]), 0),)
        rows.append((len(rows), pt.code(level[len(rows)]), 1, None, None, r["label"], int(r["support"]), r["tree_support"], int(r["support"])))
    names = [r[5] for r in rows]
    number, n_labels = {x: i for i, x in enumerate(names)}, len(names)
    if not rows:
        return _result(spark, rows, minsup, measure, "long")
    ids = hinted(spark.createDataFrame([(x, i) for x, i in number.items()], "label string, label_id int"), n_labels)
    own = v.filter("tree_id is not null").join(ids, "label").select("tree_id", "lo", "hi", "label_id")
    tree = F.col("tree")
    if spread > 1:
        own = own.withColumn("tree_id", F.explode(F.transform(F.sequence(F.lit(0), F.lit(spread - 1)), lambda i: F.col("tree_id") * spread + i)))
        tree = F.expr(f"(tree - pmod(tree, {spread}L)) div {spread}L")
    own = own.repartition("tree_id").sortWithinPartitions("tree_id", "lo").persist()
    known, size, first = set(level.values()), 1, list(level)
    roots, steps, sizes = np.arange(n_labels), [], [n_labels]
    try:
        while level and (max_size is None or size < max_size):
            size += 1
            width = (size - 1) * n_labels
            place = {at: i for i, at in enumerate(first)}
            allowed = None
            if rule in ("class", "all") and size > 2 and not guided:
                let = np.array([place[r["prefix_id"]] * width + r["c"] * n_labels + number[r["label"]] for r in _allowed(spark, rows, level, known, rule)[0].toLocalIterator()], np.int64)
                allowed = Lookup(let, np.zeros(len(let), np.int64), len(first) * width)
            counts = own.mapInArrow(_kernel(roots, steps, sizes, n_labels, allowed, whole, spread), _COUNTS)
            if spread > 1:
                counts = counts.groupBy("code", tree.alias("tree")).agg(F.sum("support").alias("support"), F.lit(1).cast("long").alias("trees"), F.sum("n").alias("n"))
            counts = counts.groupBy("code").agg(F.sum("support").alias("support"), F.sum("trees").alias("tree_support"), F.sum("n").alias("n"))
            good = counts.filter(F.col(measure) >= minsup).orderBy("code").collect()
            level_next, codes = {}, []
            for r in good:
                prefix, c, label = first[r["code"] // width], r["code"] % width // n_labels, names[r["code"] % n_labels]
                nodes = pt.extend(level[prefix], pt.escape(label), c)
                if rule == "all" and guided and size > 2 and not all(p in known for p in pt.one_removed(nodes)):
                    continue
                level_next[len(rows)] = nodes
                codes.append(r["code"])
                rows.append((len(rows), pt.code(nodes), size, prefix, c, label, int(r["support"]), r["tree_support"], r["n"] if whole else None))
            steps.append(Lookup(np.array(codes, np.int64), np.arange(len(codes)), len(first) * width))
            level, first = level_next, list(level_next)
            known = set(level.values())
            sizes.append(len(first))
    finally:
        own.unpersist()
    return _result(spark, rows, minsup, measure, "long")
