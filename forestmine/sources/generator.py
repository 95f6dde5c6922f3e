"""Synthetic forests: stars, chains, literal micro forests, and browsing trees from a master tree."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.encode import number

SCHEMA = "tree_id long, lo int, hi int, depth int, label string"
#: Multiplier, increment and modulus of the portable integer hash (BIGINT arithmetic only).
MULTIPLIER, INCREMENT, MODULUS = 1103515245, 12345, 2147483648


def hashed(*values: Column) -> Column:
    """A portable integer hash in [0, 2^31) of integers: rounds of one linear congruence."""
    h = F.lit(17).cast("long")
    for v in values:
        for _ in range(2):
            h = ((h + v.cast("long")) * MULTIPLIER + INCREMENT) % MODULUS
        h = F.shiftright(h, 3) + (h % 8) * (MODULUS // 8)
    return h


def star(spark: SparkSession, n: int) -> DataFrame:
    """A root a with n - 1 leaves b."""
    i = F.col("id").cast("int")
    return spark.range(n).select(F.lit(0).cast("long").alias("tree_id"), i.alias("lo"), F.when(i == 0, n - 1).otherwise(i).cast("int").alias("hi"), (i > 0).cast("int").alias("depth"), F.when(i == 0, "a").otherwise("b").alias("label"))


def chain(spark: SparkSession, n: int) -> DataFrame:
    """n vertices a, each the child of the one before."""
    i = F.col("id").cast("int")
    return spark.range(n).select(F.lit(0).cast("long").alias("tree_id"), i.alias("lo"), F.lit(n - 1).cast("int").alias("hi"), i.alias("depth"), F.lit("a").alias("label"))


def _copies(v: DataFrame, trees: int) -> DataFrame:
    return v.withColumn("tree_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(trees - 1).cast("long"))))


def stars(spark: SparkSession, trees: int, n: int) -> DataFrame:
    """So many stars of n vertices."""
    return _copies(star(spark, n), trees).select("tree_id", "lo", "hi", "depth", "label")


def chains(spark: SparkSession, trees: int, n: int) -> DataFrame:
    """So many chains of n vertices."""
    return _copies(chain(spark, n), trees).select("tree_id", "lo", "hi", "depth", "label")


def parse_tree(text: str) -> list[tuple[int, int, int, str]]:
    """label(child,child) to (lo, hi, depth, label) in preorder."""
    import re

    rows: list[list] = []
    path: list[int] = []
    for token in re.findall(r"[(),]|[^(),\s]+", text):
        if token == "(":
            path.append(len(rows) - 1)
        elif token == ")":
            rows[path.pop()][1] = len(rows) - 1
        elif token != ",":
            rows.append([len(rows), len(rows), len(path), token])
    return [tuple(r) for r in rows]


def literal_forest(spark: SparkSession, trees: list[str]) -> DataFrame:
    """Trees written as label(child,child)."""
    return spark.createDataFrame([(i, *row) for i, t in enumerate(trees) for row in parse_tree(t)], SCHEMA)


def level_sizes(vertices: int, depth: int, fan_out: int) -> list[int]:
    """Vertices at each depth from 0 to ``depth``, ``vertices`` in all: they grow by one ratio, fan_out at most, which the numbers fix."""
    low, high = 0.0, float(fan_out)
    for _ in range(60):
        ratio = (low + high) / 2
        low, high = (ratio, high) if sum(ratio**d for d in range(depth + 1)) < vertices else (low, ratio)
    sizes = [1]
    for d in range(1, depth + 1):
        sizes.append(max(1, min(round(high**d), sizes[-1] * fan_out)))
    sizes[-1] = max(1, min(sizes[-1] + vertices - sum(sizes), sizes[-2] * fan_out)) if depth else 1
    return sizes


def master(spark: SparkSession, n_labels: int = 100, vertices: int = 10_000, depth: int = 10, fan_out: int = 10, seed: int = 1) -> DataFrame:
    """The master tree: (id, parent, slot, depth, label). It has ``vertices`` vertices on all depths to ``depth``, where fan_out allows, and at most fan_out children each.

    A level's vertices take hashed places among the slots of the level before, in order, so that each knows its parent from its number.
    """
    sizes = level_sizes(vertices, depth, fan_out)
    first = [sum(sizes[:d]) for d in range(depth + 1)]
    levels = spark.createDataFrame([(d, first[d], sizes[d], first[d - 1] if d else 0, (sizes[d - 1] if d else 1) * fan_out) for d in range(depth + 1)], "depth int, first long, size long, above long, slots long")
    rows = levels.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1)).alias("i")).withColumn("id", F.col("first") + F.col("i"))
    draw = hashed(F.lit(seed), F.col("id")) % 1024
    rows = rows.withColumn("draw", draw).withColumn("at", F.expr("(i * slots * 1024 + draw * (slots - size)) div (size * 1024)"))
    label = F.concat(F.lit("s"), (hashed(F.lit(seed + 1), F.col("id")) % n_labels).cast("string"))
    return rows.select("id", F.when(F.col("depth") > 0, F.col("above") + F.expr(f"at div {fan_out}")).alias("parent"), F.when(F.col("depth") > 0, F.expr(f"at % {fan_out}")).otherwise(0).cast("int").alias("slot"), "depth", label.alias("label"))


def ratio_of(vertices: int, depth: int, fan_out: int) -> float:
    """The ratio by which levels from 0 to ``depth`` must grow to hold so many vertices."""
    low, high = 0.0, float(max(vertices, fan_out))
    for _ in range(80):
        ratio = (low + high) / 2
        low, high = (ratio, high) if sum(ratio**d for d in range(depth + 1)) < vertices else (low, ratio)
    return high


def master_of(keys: DataFrame, n_labels: int = 100, depth: int = 10, fan_out: int = 10, seed: int = 1) -> DataFrame:
    """A master tree of a table's rows, columns as for master. keys: one column, ``key``; each row with a key is a vertex, in order of keys.

    Levels grow by one ratio and the last one takes the rest. A vertex has at most fan_out children, or more where a level's rows would not find room
    else; labels and slots are drawn by key, so rows of one key may change places.
    """
    spark = keys.sparkSession
    keys = keys.select(F.col("key").cast("long").alias("key")).filter("key is not null").withColumn("block", F.floor(F.col("key") / 65536))
    blocks = keys.groupBy("block").agg(F.count(F.lit(1)).alias("n")).withColumn("before", F.sum("n").over(Window.orderBy("block")) - F.col("n"))
    ids = keys.join(blocks.select("block", "before"), "block").withColumn("id", F.col("before") + F.row_number().over(Window.partitionBy("block").orderBy("key")) - 1).select("key", "id")
    vertices = keys.count()
    high = ratio_of(vertices, depth, fan_out)
    sizes = [max(1, math.floor(high**d + 0.5)) for d in range(depth)] if depth else []
    sizes.append(max(1, vertices - sum(sizes)))
    first = [sum(sizes[:d]) for d in range(depth + 1)]
    fan = [max(fan_out, -(-n // (sizes[d - 1] if d else 1))) for d, n in enumerate(sizes)]
    levels = spark.createDataFrame([(d, first[d], sizes[d], first[d - 1] if d else 0, (sizes[d - 1] if d else 1) * fan[d], fan[d]) for d in range(depth + 1)], "depth int, first long, size long, above long, slots long, fan long")
    level = sum((F.col("id") >= n).cast("int") for n in first[1:]) if depth else F.lit(0)
    rows = ids.withColumn("depth", level).join(F.broadcast(levels), "depth").withColumn("i", F.col("id") - F.col("first"))
    drawn = F.col("key") % MODULUS
    rows = rows.withColumn("draw", F.pmod(hashed(F.lit(seed), drawn), F.lit(1024))).withColumn("at", F.expr("(i * slots * 1024 + draw * (slots - size)) div (size * 1024)"))
    label = F.concat(F.lit("s"), F.pmod(hashed(F.lit(seed + 1), drawn), F.lit(n_labels)).cast("string"))
    return rows.select("id", F.when(F.col("depth") > 0, F.col("above") + F.expr("at div fan")).alias("parent"), F.when(F.col("depth") > 0, F.expr("at % fan")).otherwise(0).cast("int").alias("slot"), "depth", label.alias("label"))


def browsing_trees(tree: DataFrame, n_trees: int, keep_percent: int = 70, seed: int = 7, small: bool = True) -> DataFrame:
    """n_trees subtrees of the master: each starts at the root; a vertex stays if its own draw says so and its parent stays. small: the master's levels may be broadcast."""
    spark = tree.sparkSession
    draw = hashed(F.lit(seed), F.col("tree_id"), F.col("id")) % 100 < keep_percent
    depths = tree.agg(F.max("depth")).first()[0] or 0
    level = spark.range(n_trees).select(F.col("id").alias("tree_id")).join(F.broadcast(tree.filter("depth = 0")), F.lit(True)).select("tree_id", "id", "label", F.array("slot").alias("path"), "depth")
    out = level
    for d in range(1, depths + 1):
        kids = tree.filter(F.col("depth") == d).select(F.col("id").alias("kid"), F.col("parent").alias("up"), "slot", F.col("label").alias("kid_label"))
        kids = F.broadcast(kids) if small else kids
        level = level.join(kids, F.col("id") == F.col("up")).select("tree_id", F.col("kid").alias("id"), F.col("kid_label").alias("label"), F.concat("path", F.array("slot")).alias("path"), F.lit(d).alias("depth")).filter(draw)
        out = out.union(level)
    return number(out, ["path"], "depth", list(range(depths + 1)))
