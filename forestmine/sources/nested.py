"""Trees from nested columns and from tag soup."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.encode import number
from .tables import VOID

_TAG = r"</?[a-z][a-z0-9]*"


def from_nested(df: DataFrame, key: str, column: str) -> DataFrame:
    """A struct or array column to vertices: one per field and element that isn't null; a label is the field's name (elements: 'item'). Values are no vertices."""
    rows: list[DataFrame] = []
    deepest = 0

    def walk(d: DataFrame, kind: T.DataType, label: str, level: int) -> None:
        nonlocal deepest
        deepest = max(deepest, level)
        rows.append(d.select("tree_id", "path", F.lit(label).alias("label")))
        if isinstance(kind, T.StructType):
            for i, f in enumerate(kind.fields):
                walk(d.select("tree_id", F.concat("path", F.array(F.lit(i))).alias("path"), F.col("cur")[f.name].alias("cur")).filter("cur is not null"), f.dataType, f.name, level + 1)
        elif isinstance(kind, T.ArrayType):
            inner = d.select("tree_id", "path", F.posexplode("cur").alias("i", "cur")).filter("cur is not null")
            walk(inner.select("tree_id", F.concat("path", F.array("i")).alias("path"), "cur"), kind.elementType, "item", level + 1)

    start = df.select(F.col(key).cast("long").alias("tree_id"), F.array().cast("array<int>").alias("path"), F.col(column).alias("cur")).filter("cur is not null")
    walk(start, df.schema[column].dataType, column, 0)
    out = rows[0]
    for r in rows[1:]:
        out = out.union(r)
    return number(out.withColumn("level", F.size("path")), ["path"], "level", list(range(deepest + 1)))


def _parse(policy: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for tree, tags in zip(batch.column("tree_id").to_pylist(), batch.column("tags").to_pylist()):
                rows: list[list] = []
                open_tags: list[int] = []
                for tag in tags or []:
                    name = tag.strip("</")
                    if tag.startswith("</"):
                        at = next((i for i in range(len(open_tags) - 1, -1, -1) if rows[open_tags[i]][4] == name), None)
                        if at is not None:
                            for i in open_tags[at:]:
                                rows[i][2] = len(rows) - 1
                            del open_tags[at:]
                        continue
                    if policy == "implied" and name == "p":
                        at = next((i for i in range(len(open_tags) - 1, -1, -1) if rows[open_tags[i]][4] == "p"), None)
                        if at is not None:
                            for i in open_tags[at:]:
                                rows[i][2] = len(rows) - 1
                            del open_tags[at:]
                    rows.append([tree, len(rows), len(rows), len(open_tags), name])
                    if name not in VOID:
                        open_tags.append(len(rows) - 1)
                for i in open_tags:
                    rows[i][2] = len(rows) - 1
                out += map(tuple, rows)
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(("int64", "int32", "int32", "int32", "string"))], names=["tree_id", "lo", "hi", "depth", "label"])

    return run


def pages_nested(spark: SparkSession, sf_dir: str, policy: str = "raw") -> DataFrame:
    """DOM trees by a stack. raw: nothing is implied, an end tag closes all up to its own; implied: a new p closes an open one. End tags without a start are dropped."""
    html = F.regexp_replace(F.lower("html"), r"(?s)<!--.*?-->", "")
    html = F.regexp_replace(html, r"(?s)(<script[^>]*>).*?(</script>)", "$1$2")
    html = F.regexp_replace(html, r"(?s)(<style[^>]*>).*?(</style>)", "$1$2")
    tags = spark.read.parquet(f"{sf_dir}/pages.parquet").select(F.col("page_id").alias("tree_id"), F.regexp_extract_all(html, F.lit(_TAG), F.lit(0)).alias("tags"))
    return tags.mapInArrow(_parse(policy), "tree_id long, lo int, hi int, depth int, label string")
