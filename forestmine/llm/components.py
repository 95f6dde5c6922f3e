"""Connected components of an edge table by repeated contraction.

Each round every node points at the neighbour (or itself) of least random
priority, and the edges are rewritten to the nodes pointed at. Priorities are
drawn anew each round, so chains shrink geometrically as stars do. No node's
neighbours are ever gathered: a round is two equi joins and three partial sums.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import materialize


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(src long, dst long) to (node, component): component is the least node reachable.

    Only nodes with an edge appear. Null ends and self loops are dropped, repeats
    merged; an empty table gives an empty result.
    """
    e = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).filter("src <> dst").distinct()
    e = materialize(e, "edges")
    nodes = e.select(F.col("src").alias("node")).union(e.select("dst")).distinct()
    steps: list[DataFrame] = []
    for turn in range(max_rounds):
        if e.isEmpty():
            break
        rank = lambda c: F.struct(F.xxhash64(c, F.lit(turn)).alias("p"), c.alias("to"))
        both = e.union(e.select("dst", "src"))
        step = both.groupBy(F.col("src").alias("node")).agg(F.least(F.min(rank(F.col("dst"))), rank(F.first("src")))["to"].alias("to"))
        step = materialize(step, "step")
        steps.append(step)
        a, b = step.toDF("src", "a"), step.toDF("dst", "b")
        e = materialize(e.join(a, "src").join(b, "dst").filter("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct(), "edges")
    else:
        raise RuntimeError("components did not settle")
    found = nodes.withColumn("root", F.col("node"))
    for step in steps:
        found = found.join(step.toDF("root", "to"), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
    least = found.groupBy("root").agg(F.min("node").alias("component"))
    return found.join(least, "root").select("node", "component")
