"""Numbering: rows with a total order and a rank to vertices with scopes.

A vertex's descendants are the rows after it up to the next row of a rank not
above its own. So ``hi`` is a running minimum from the back, one per rank; the
whole encoding is one shuffle by tree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Columns of the vertex table.
VERTICES = ["tree_id", "lo", "hi", "depth", "label"]


def number(rows: DataFrame, order: list[str], rank: str, ranks: list[int], depth_is_rank: bool = True) -> DataFrame:
    """(tree_id, label, rank, order columns) to vertices.

    ``ranks`` lists the values that rank takes. With depth_is_rank false (ranked
    sequences, in which levels may be skipped) depth is the number of ancestors.
    """
    tree = Window.partitionBy("tree_id")
    v = rows.withColumn("lo", F.row_number().over(tree.orderBy(*order)) - 1)
    v = v.withColumn("last", F.count(F.lit(1)).over(tree) - 1)
    later = tree.orderBy(F.desc("lo")).rowsBetween(Window.unboundedPreceding, -1)
    end: Column = F.lit(None).cast("int")
    for r in ranks:
        end = F.when(F.col(rank) == r, F.min(F.when(F.col(rank) <= r, F.col("lo"))).over(later)).otherwise(end)
    v = v.withColumn("hi", F.coalesce(end - 1, F.col("last")).cast("int"))
    v = v.withColumn("depth", F.col(rank).cast("int")) if depth_is_rank else with_depth(v)
    return v.select(F.col("tree_id").cast("long"), F.col("lo").cast("int"), "hi", "depth", "label")


def number_by_value(rows: DataFrame, order: list[str], value: str) -> DataFrame:
    """As number, for ranks from any domain: a row's parent is the nearest earlier row of larger value.

    The scope ends before the next row of no smaller value; found by a join inside the tree.
    """
    tree = Window.partitionBy("tree_id")
    v = rows.withColumn("lo", F.row_number().over(tree.orderBy(*order)) - 1).withColumn("last", F.count(F.lit(1)).over(tree) - 1)
    a, b = v.alias("a"), v.select("tree_id", "lo", value).alias("b")
    ends = a.join(b, (F.col("a.tree_id") == F.col("b.tree_id")) & (F.col("b.lo") > F.col("a.lo")) & (F.col(f"b.{value}") >= F.col(f"a.{value}"))).groupBy(F.col("a.tree_id").alias("tree_id"), F.col("a.lo").alias("lo")).agg(F.min("b.lo").alias("end"))
    v = v.join(ends, ["tree_id", "lo"], "left").withColumn("hi", F.coalesce(F.col("end") - 1, F.col("last")).cast("int"))
    return with_depth(v).select(F.col("tree_id").cast("long"), F.col("lo").cast("int"), "hi", "depth", "label")


def with_depth(v: DataFrame) -> DataFrame:
    """Adds depth = number of ancestors = lo - number of scopes that ended before: a running sum."""
    keep = v.columns
    ends = v.groupBy("tree_id", (F.col("hi") + 1).alias("at")).agg(F.count(F.lit(1)).alias("ended"))
    rows = v.select("*", F.col("lo").alias("at"), F.lit(0).cast("long").alias("ended"), F.lit(True).alias("vertex")).unionByName(ends.withColumn("vertex", F.lit(False)), allowMissingColumns=True)
    run = Window.partitionBy("tree_id").orderBy("at").rangeBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("depth", (F.col("lo") - F.sum("ended").over(run)).cast("int")).filter("vertex").select(*keep, "depth")


def from_adjacency(nodes: DataFrame) -> DataFrame:
    """(tree_id, id, parent, ordinal, label), parent null for roots, to vertices: paths of ordinals by level, then numbering."""
    level = nodes.filter("parent is null").select("tree_id", "id", "label", F.array("ordinal").alias("path"))
    found, depth = level, 0
    while not level.isEmpty():
        depth += 1
        level = nodes.alias("n").join(level.select(F.col("tree_id").alias("t"), F.col("id").alias("p"), "path"), (F.col("n.tree_id") == F.col("t")) & (F.col("n.parent") == F.col("p"))).select("n.tree_id", "n.id", "n.label", F.concat("path", F.array("n.ordinal")).alias("path"))
        level = level.persist()
        found = found.union(level)
    return number(found.withColumn("level", F.size("path") - 1), ["path"], "level", list(range(depth)))


def from_tokens(tokens: DataFrame) -> DataFrame:
    """(tree_id, pos, label, kind), kind 'open', 'close' or 'leaf', to vertices.

    A close ends the innermost open element; elements that are never closed reach the tree's end.
    """
    up = Window.partitionBy("tree_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    step = F.when(F.col("kind") == "open", 1).when(F.col("kind") == "close", -1).otherwise(0)
    t = tokens.withColumn("nest", F.sum(step).over(up)).withColumn("seen", F.sum(F.when(F.col("kind") != "close", 1).otherwise(0)).over(up))
    t = t.withColumn("n", F.sum(F.when(F.col("kind") != "close", 1).otherwise(0)).over(Window.partitionBy("tree_id")))
    t = t.withColumn("level", F.when(F.col("kind") == "close", F.col("nest") + 1).when(F.col("kind") == "open", F.col("nest")).otherwise(-F.col("pos") - 1))
    close = F.lead("seen").over(Window.partitionBy("tree_id", "level").orderBy("pos"))
    t = t.withColumn("hi", F.when(F.col("kind") == "leaf", F.col("seen") - 1).otherwise(F.coalesce(close - 1, F.col("n") - 1)))
    depth = F.when(F.col("kind") == "leaf", F.col("nest")).otherwise(F.col("nest") - 1)
    return t.filter("kind <> 'close'").select(F.col("tree_id").cast("long"), (F.col("seen") - 1).cast("int").alias("lo"), F.col("hi").cast("int"), depth.cast("int").alias("depth"), "label")


def pack(v: DataFrame) -> DataFrame:
    """One row a tree: tree_id, n, nodes (lo, hi, depth, label) sorted by lo."""
    return v.groupBy("tree_id").agg(F.count(F.lit(1)).cast("int").alias("n"), F.array_sort(F.collect_list(F.struct("lo", "hi", "depth", "label"))).alias("nodes"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("tree_id", F.inline("nodes")).select(*VERTICES)
