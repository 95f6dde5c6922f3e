"""Trees as text: one tree a line, labels in preorder with -1 for a step up."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.encode import from_tokens

#: Fixed value: the mark of a step up.
UP = "-1"


def decode_lines(lines: DataFrame) -> DataFrame:
    """(tree_id, line) to vertices. Steps up at the end of a line may be left out; blank lines give no tree."""
    t = lines.select("tree_id", F.posexplode(F.filter(F.split("line", r"\s+"), lambda x: x != "")).alias("pos", "label"))
    return from_tokens(t.withColumn("kind", F.when(F.col("label") == UP, "close").otherwise("open")))


def read_trees(spark: SparkSession, path: str) -> DataFrame:
    """Vertices of text files; tree_id tells lines apart (it is not a line number)."""
    return decode_lines(spark.read.text(path).select(F.monotonically_increasing_id().alias("tree_id"), F.col("value").alias("line")))


def encode_lines(v: DataFrame) -> DataFrame:
    """Vertices to (tree_id, line). After a vertex the line steps up by how much the next one is less deep, plus one; nothing follows the last."""
    nodes = F.array_sort(F.collect_list(F.struct("lo", "depth", "label")))
    packed = v.groupBy("tree_id").agg(nodes.alias("nodes"))
    ups = lambda x, i: F.get(F.col("nodes"), i + 1)["depth"]
    token = F.transform("nodes", lambda x, i: F.concat(x["label"], F.coalesce(F.repeat(F.lit(f" {UP}"), x["depth"] - ups(x, i) + 1), F.lit(""))))
    return packed.select("tree_id", F.array_join(token, " ").alias("line"))


def write_trees(v: DataFrame, path: str) -> None:
    encode_lines(v).select(F.col("line").alias("value")).write.text(path)
