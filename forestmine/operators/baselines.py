"""The miners that the compact one is compared with."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import pattern as pt
from ..functions.relations import extend_path
from . import joins
from .encode import pack
from .mine import Kernel, Trace, frequent_labels, levelwise, shrink


def _full_kernel(v: DataFrame) -> Kernel:
    """Every occurrence is a row with all its matched vertices; nothing is merged."""

    def start(v: DataFrame, ids: DataFrame) -> DataFrame:
        return joins.singletons(v, ids).withColumn("matched", F.array(F.struct("lo", "hi")))

    def finish(j: DataFrame) -> DataFrame:
        whole = F.concat("matched", F.array(F.struct(F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"))))
        return j.select(F.col("pattern_id").alias("prefix_id"), "c", "label", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), extend_path(F.col("rp"), F.col("c"), F.col("x_hi")).alias("rp"), "mult", whole.alias("matched"))

    return Kernel(start, lambda r: joins.pairs_by_join(r, v), finish, ["tree_id", "lo", "hi", "rp", "mult", "matched"], "full match")


def full_match(v: DataFrame, minsup: int, max_size: int | None = None, rule: str = "prefix", support: str = "occurrence", trace: Trace | None = None, guided: bool = False, plan: str = "join") -> DataFrame:
    """Full-match miner: the same patterns as the compact one under the same rule, with a row for each occurrence.

    plan 'join' keeps a level's occurrences; 'counted' makes them anew from whole trees, level by level, and keeps none (no trace then).
    """
    if plan not in ("join", "counted") or (plan == "counted" and (trace is not None or rule == "none")):
        raise ValueError(f"plan {plan} is unknown, or takes no trace and no rule 'none'")
    keep = frequent_labels(v, minsup, support).persist()
    if plan == "counted":
        from ..plans import counted

        try:
            return counted.mine(v, minsup, max_size, keep, rule, support, whole=True, guided=guided)
        finally:
            keep.unpersist()
    v = shrink(v, keep).repartition("tree_id").persist()
    try:
        return levelwise(v, minsup, _full_kernel(v), max_size, rule, support, trace=trace, labels=keep, guided=guided)
    finally:
        v.unpersist()
        keep.unpersist()


def model_guided(v: DataFrame, minsup: int, max_size: int | None = None, support: str = "occurrence", trace: Trace | None = None, plan: str = "join") -> DataFrame:
    """Model-guided miner: breadth first with full occurrences; extensions are taken from the data, and of those
    that occur and are frequent the ones stay all of whose sub-patterns are. So occurrences of extensions that the rule throws out are made, too."""
    return full_match(v, minsup, max_size, "all", support, trace, guided=True, plan=plan)


def rightmost_set(v: DataFrame, minsup: int, max_size: int | None = None, trace: Trace | None = None) -> DataFrame:
    """Rightmost-set miner: per-tree support, records without counts. support here is the number of trees too."""
    v = shrink(v, frequent_labels(v, minsup, "tree")).repartition("tree_id").persist()

    def finish(j: DataFrame) -> DataFrame:
        keys = j.select(F.col("pattern_id").alias("prefix_id"), "c", "label", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), extend_path(F.col("rp"), F.col("c"), F.col("x_hi")).alias("rp"))
        return keys.dropDuplicates().withColumn("mult", F.lit(1).cast("long"))

    try:
        found = levelwise(v, minsup, Kernel(joins.singletons, lambda r: joins.pairs_by_join(r, v), finish, name="rightmost set"), max_size, "prefix", "tree", trace=trace)
        return found.withColumn("support", F.col("tree_support"))
    finally:
        v.unpersist()


def count_in_tree(nodes: list[tuple[int, int, str]], pattern: pt.Nodes) -> int:
    """Occurrences of a pattern in one tree of (lo, hi, label), matched from scratch vertex by vertex."""
    state = {(lo, (hi,)): 1 for lo, hi, label in nodes if label == pt.unescape(pattern[0][0])}
    for label, depth in pattern[1:]:
        wanted, grown = pt.unescape(label), {}
        for (last, path), n in state.items():
            for lo, hi, own in nodes:
                if own == wanted and last < lo <= path[depth - 1] and (depth == len(path) or lo > path[depth]):
                    key = (lo, (*path[:depth], hi))
                    grown[key] = grown.get(key, 0) + n
        state = grown
    return sum(state.values())


def _count_all(patterns: list[pt.Nodes]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, counts = [], []
            for nodes in batch.column("nodes").to_pylist():
                tree = [(x["lo"], x["hi"], x["label"]) for x in nodes]
                for i, p in enumerate(patterns):
                    n = count_in_tree(tree, p)
                    if n:
                        at.append(i)
                        counts.append(n)
            yield pa.RecordBatch.from_arrays([pa.array(at, "int64"), pa.array(counts, "int64")], names=["i", "n"])

    return run


def horizontal(v: DataFrame, minsup: int, max_size: int, support: str = "occurrence") -> DataFrame:
    """Horizontal miner: no stored occurrences; a level's candidates are matched against every tree from scratch."""
    spark = v.sparkSession
    packed = pack(v).persist()
    measure = "tree_support" if support == "tree" else "support"
    labels = [r["label"] for r in frequent_labels(v, minsup, support).orderBy("label").collect()]
    rows: list[tuple] = []
    candidates: list[tuple] = [(((pt.escape(x), 0),), None, None, x) for x in labels]
    size = 1
    while candidates and size <= max_size:
        counts = packed.select("nodes").mapInArrow(_count_all([c[0] for c in candidates]), "i long, n long").groupBy("i").agg(F.sum("n").alias("support"), F.count(F.lit(1)).alias("tree_support"))
        new = []
        for r in counts.filter(F.col(measure) >= minsup).orderBy("i").collect():
            nodes, prefix, c, label = candidates[r["i"]]
            new.append((len(rows), nodes))
            rows.append((len(rows), pt.code(nodes), size, prefix, c, label, r["support"], r["tree_support"], 0))
        candidates = [(pt.extend(nodes, pt.escape(x), c), at, c, x) for at, nodes in new for x in labels for c in range(nodes[-1][1] + 1)]
        size += 1
    packed.unpersist()
    return spark.createDataFrame(rows, "pattern_id long, code string, size int, prefix_id long, attach_depth int, label string, support long, tree_support long, n_records long")
