"""Relations between vertices of one tree, as column expressions over their scopes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def is_ancestor(a_lo: Column, a_hi: Column, b_lo: Column, b_hi: Column) -> Column:
    """a is a proper ancestor of b."""
    return (a_lo < b_lo) & (b_hi <= a_hi)


def is_right_relative(a_hi: Column, b_lo: Column) -> Column:
    """b lies to the right of a, and neither is an ancestor of the other."""
    return a_hi < b_lo


def leaf_ok(y_lo: Column, y_hi: Column, x_lo: Column, x_hi: Column) -> Column:
    """x may be attached under the last vertex y."""
    return (y_lo < x_lo) & (x_hi <= y_hi)


def inner_ok(y_hi: Column, z_hi: Column, x_lo: Column) -> Column:
    """x may be attached under y, right of y's rightmost child z."""
    return (z_hi < x_lo) & (x_lo <= y_hi)


def attach_depth(rp: Column, lo: Column) -> Column:
    """Depth of the deepest rightmost-path vertex whose scope reaches ``lo``: bounds never increase along a path."""
    return F.size(F.filter(rp, lambda u: u >= lo)) - 1


def extend_path(rp: Column, c: Column, hi: Column) -> Column:
    """Upper bounds of the path after attaching a vertex at depth c."""
    return F.concat(F.slice(rp, 1, c + 1), F.array(hi))


def extension_faults(matched: Column, y: Column, x_lo: Column, x_hi: Column) -> Column:
    """Names what keeps x from extending an occurrence at its y-th vertex; null if nothing does.

    matched: array of (lo, hi) in pattern preorder. x must lie inside y's scope, after
    all matched vertices, and outside every matched vertex that isn't an ancestor-or-self of y.
    """
    at = F.element_at(matched, y + 1)
    inside = (at["lo"] < x_lo) & (x_hi <= at["hi"])
    after = F.forall(matched, lambda m: m["lo"] < x_lo)
    apart = F.forall(matched, lambda m: ((m["lo"] <= at["lo"]) & (at["hi"] <= m["hi"])) | (m["hi"] < x_lo))
    return F.when(~inside, "outside").when(~after, "order").when(~apart, "relative")


def ancestor_pairs(v: DataFrame) -> DataFrame:
    """(tree_id, a_lo, b_lo) of all proper ancestor pairs."""
    a, b = v.alias("a"), v.alias("b")
    return a.join(b, (F.col("a.tree_id") == F.col("b.tree_id")) & is_ancestor(F.col("a.lo"), F.col("a.hi"), F.col("b.lo"), F.col("b.hi"))).select("a.tree_id", F.col("a.lo").alias("a_lo"), F.col("b.lo").alias("b_lo"))


def right_relative_pairs(v: DataFrame) -> DataFrame:
    """(tree_id, a_lo, b_lo) where b is right of a."""
    a, b = v.alias("a"), v.alias("b")
    return a.join(b, (F.col("a.tree_id") == F.col("b.tree_id")) & is_right_relative(F.col("a.hi"), F.col("b.lo"))).select("a.tree_id", F.col("a.lo").alias("a_lo"), F.col("b.lo").alias("b_lo"))


def parents(v: DataFrame) -> DataFrame:
    """v with parent_lo (null for roots): the last earlier vertex one level up. A window, no join."""
    own = Window.partitionBy("tree_id", "level").orderBy("lo", "side").rowsBetween(Window.unboundedPreceding, -1)
    both = v.select("*", F.explode(F.array(F.struct((F.col("depth")).alias("level"), F.lit(1).alias("side")), F.struct((F.col("depth") - 1).alias("level"), F.lit(0).alias("side")))).alias("e")).select("*", "e.level", "e.side").drop("e")
    # side 1: as a possible parent on its own level; side 0: as a child that asks the level above.
    asked = both.withColumn("parent_lo", F.last(F.when(F.col("side") == 1, F.col("lo")), ignorenulls=True).over(own))
    return asked.filter("side = 0").drop("level", "side")


def rightmost_paths(v: DataFrame) -> DataFrame:
    """Vertices of each tree's rightmost path (whose scope reaches the tree's end) with their depth along it."""
    tree = Window.partitionBy("tree_id")
    return v.withColumn("end", F.max("hi").over(tree)).filter("hi = end").drop("end").withColumn("rdepth", F.row_number().over(tree.orderBy("lo")) - 1)
