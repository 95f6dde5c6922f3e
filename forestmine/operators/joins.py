"""Compact records and their joins.

A record stands for all occurrences of a pattern in a tree that share the scope
of the last vertex and the upper bounds ``rp`` of the rightmost path; ``mult``
counts them. Columns: pattern_id, tree_id, lo, hi, rp, mult. All joins are equi
joins on tree_id, and merging groups by keys that include tree_id, so a table
dealt by tree_id is never shuffled again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.relations import attach_depth, extend_path, inner_ok, leaf_ok

KEYS = ["pattern_id", "tree_id", "lo", "hi", "rp"]
#: A candidate: which pattern was extended, at which depth, by which label.
CANDIDATE = ["prefix_id", "c", "label"]


def singletons(v: DataFrame, ids: DataFrame | None = None) -> DataFrame:
    """Records of one-vertex patterns. ids: (label, pattern_id) of those wanted, broadcast if the caller says so; else all get pattern 0."""
    rows = v.join(ids, "label") if ids is not None else v.withColumn("pattern_id", F.lit(0).cast("long"))
    return rows.select("pattern_id", "tree_id", "lo", "hi", F.array("hi").alias("rp"), F.lit(1).cast("long").alias("mult"))


def _side(v: DataFrame) -> DataFrame:
    return v.select(F.col("tree_id").alias("x_tree"), F.col("lo").alias("x_lo"), F.col("hi").alias("x_hi"), F.col("depth").alias("x_depth"), "label")


def merge(r: DataFrame, keys: list[str] = KEYS) -> DataFrame:
    """Equal keys become one record. Counts past the long range raise an arithmetic error."""
    return r.groupBy(*keys).agg(F.sum("mult").alias("mult"))


def leaf(r: DataFrame, v: DataFrame, merged: bool = True) -> DataFrame:
    """Attach each vertex of v under the last vertex. merged: equal records are added up (else one record for each pair)."""
    x = _side(v)
    j = r.join(x, (F.col("tree_id") == F.col("x_tree")) & leaf_ok(F.col("lo"), F.col("hi"), F.col("x_lo"), F.col("x_hi")))
    j = j.select("pattern_id", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), F.concat("rp", F.array("x_hi")).alias("rp"), "mult")
    return merge(j) if merged else j


def inner(r: DataFrame, v: DataFrame, c: int) -> DataFrame:
    """Attach each vertex of v at depth c, right of the path's next vertex; records with one path up to c add up."""
    x = _side(v)
    cut = r.filter(F.size("rp") > c + 1)
    j = cut.join(x, (F.col("tree_id") == F.col("x_tree")) & inner_ok(F.col("rp")[c], F.col("rp")[c + 1], F.col("x_lo")))
    return merge(j.select("pattern_id", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), extend_path(F.col("rp"), F.lit(c), F.col("x_hi")).alias("rp"), "mult"))


def inner_sorted(r: DataFrame, v: DataFrame, c: int) -> DataFrame:
    """inner by one scan of records sorted by path: runs of one path prefix are numbered, then added up by run."""
    x = _side(v)
    order = Window.partitionBy("tree_id", "pattern_id").orderBy("rp")
    head = F.slice("rp", 1, c + 1)
    cut = r.filter(F.size("rp") > c + 1).withColumn("head", head)
    new = F.when(F.lag("head").over(order).isNull() | (F.lag("head").over(order) != F.col("head")), 1).otherwise(0)
    runs = cut.withColumn("new", new).withColumn("run", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    j = runs.join(x, (F.col("tree_id") == F.col("x_tree")) & inner_ok(F.col("rp")[c], F.col("rp")[c + 1], F.col("x_lo")))
    g = j.groupBy("tree_id", "pattern_id", "run", "x_lo", "x_hi").agg(F.first("head").alias("head"), F.sum("mult").alias("mult"))
    return g.select("pattern_id", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), F.concat("head", F.array("x_hi")).alias("rp"), "mult")


def inner_cumulative(r: DataFrame, v: DataFrame, c: int, by: list[str] | None = None) -> DataFrame:
    """inner as a running total: no record meets a vertex.

    Inside a group (one path up to c) the records that x may join are those whose
    next bound lies before x; so x's multiplicity is the total of multiplicities up to x.lo - 1.
    by: extra columns of v to keep (then they are in the result).
    """
    by = by or []
    x = v.select(F.col("tree_id").alias("x_tree"), F.col("lo").alias("x_lo"), F.col("hi").alias("x_hi"), *by)
    cut = r.filter(F.size("rp") > c + 1).select("pattern_id", "tree_id", F.slice("rp", 1, c + 1).alias("head"), F.col("rp")[c + 1].alias("at"), "mult")
    steps = cut.groupBy("tree_id", "pattern_id", "head", "at").agg(F.sum("mult").alias("mult"))
    groups = steps.groupBy("tree_id", "pattern_id", "head").agg(F.min("at").alias("least"))
    asks = groups.join(x, (F.col("tree_id") == F.col("x_tree")) & (F.col("x_lo") > F.col("least")) & (F.col("x_lo") <= F.element_at("head", -1)))
    asks = asks.select("tree_id", "pattern_id", "head", F.col("x_lo").alias("at"), F.lit(0).cast("long").alias("mult"), "x_hi", *by)
    rows = steps.unionByName(asks, allowMissingColumns=True)
    before = Window.partitionBy("tree_id", "pattern_id", "head").orderBy("at").rangeBetween(Window.unboundedPreceding, -1)
    total = rows.withColumn("total", F.sum("mult").over(before)).filter("x_hi is not null and total > 0")
    return total.select("pattern_id", "tree_id", F.col("at").alias("lo"), F.col("x_hi").alias("hi"), F.concat("head", F.array("x_hi")).alias("rp"), F.col("total").alias("mult"), *by)


def pairs_by_join(r: DataFrame, v: DataFrame) -> DataFrame:
    """Records with each vertex after the last one inside the root's scope; c is the only depth it can be attached at."""
    x = _side(v)
    j = r.join(x, (F.col("tree_id") == F.col("x_tree")) & (F.col("x_lo") > F.col("lo")) & (F.col("x_lo") <= F.col("rp")[0])).drop("x_tree")
    return j.withColumn("c", attach_depth(F.col("rp"), F.col("x_lo")))


def pairs_by_slice(r: DataFrame, packed: DataFrame) -> DataFrame:
    """As pairs_by_join from packed trees. Preorder is dense, so the vertices are a slice; no range is compared."""
    j = r.join(packed.select("tree_id", "nodes"), "tree_id")
    j = j.select(*r.columns, F.explode(F.slice("nodes", F.col("lo") + 2, F.col("rp")[0] - F.col("lo"))).alias("x"))
    j = j.select(*r.columns, F.col("x.lo").alias("x_lo"), F.col("x.hi").alias("x_hi"), F.col("x.depth").alias("x_depth"), F.col("x.label").alias("label"))
    return j.withColumn("c", attach_depth(F.col("rp"), F.col("x_lo")))


def pairs_binned(r: DataFrame, v: DataFrame, width: int) -> DataFrame:
    """As pairs_by_join for forests of a few giant trees: both sides are dealt by (tree, bin of preorder numbers), so one tree spreads over many tasks."""
    x = _side(v).withColumn("x_bin", F.floor(F.col("x_lo") / width))
    first, last = F.floor((F.col("lo") + 1) / width), F.floor(F.col("rp")[0] / width)
    spread = r.filter(F.col("lo") < F.col("rp")[0]).withColumn("bin", F.explode(F.sequence(first, last)))
    j = spread.join(x, (F.col("tree_id") == F.col("x_tree")) & (F.col("bin") == F.col("x_bin")) & (F.col("x_lo") > F.col("lo")) & (F.col("x_lo") <= F.col("rp")[0])).drop("x_tree", "x_bin", "bin")
    return j.withColumn("c", attach_depth(F.col("rp"), F.col("x_lo")))


def attach(pairs: DataFrame, merge_mode: str = "canonical") -> DataFrame:
    """Pairs to records of candidates: (prefix_id, c, label, tree_id, lo, hi, rp, mult).

    canonical: equal keys add up. literal: a leaf attachment keeps one record for each pair, as the record definition is printed.
    """
    j = pairs.select(F.col("pattern_id").alias("prefix_id"), "c", "label", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), extend_path(F.col("rp"), F.col("c"), F.col("x_hi")).alias("rp"), "mult", (F.size("rp") - 1 == F.col("c")).alias("is_leaf"))
    keys = [*CANDIDATE, "tree_id", "lo", "hi", "rp"]
    if merge_mode == "literal":
        j = j.withColumn("own", F.when(F.col("is_leaf"), F.monotonically_increasing_id()))
        return j.groupBy(*keys, "own").agg(F.sum("mult").alias("mult")).drop("own")
    return j.groupBy(*keys).agg(F.sum("mult").alias("mult"))
