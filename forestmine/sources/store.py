"""Encoded forests on storage: dealt by tree_id and sorted by (tree_id, lo), so scans skip by both."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def save(v: DataFrame, path: str, files: int) -> None:
    """Vertices with dictionary-coded labels, and the dictionary beside them."""
    labels = v.groupBy("label").agg(F.count(F.lit(1)).alias("support")).withColumn("label_id", F.xxhash64("label"))
    labels.write.mode("overwrite").parquet(f"{path}/labels")
    coded = v.withColumn("label_id", F.xxhash64("label")).drop("label")
    coded.repartition(files, "tree_id").sortWithinPartitions("tree_id", "lo").write.mode("overwrite").parquet(f"{path}/vertices")


def load(spark: SparkSession, path: str, labels: list[str] | None = None) -> DataFrame:
    """Vertices, of some labels only if asked (pushed to the scan as ids)."""
    known, v = spark.read.parquet(f"{path}/labels"), spark.read.parquet(f"{path}/vertices")
    if labels is not None:
        known = known.filter(F.col("label").isin(labels))
        v = v.filter(F.col("label_id").isin([r["label_id"] for r in known.select("label_id").collect()]))
    return v.join(known.select("label_id", "label"), "label_id").select("tree_id", "lo", "hi", "depth", "label")


def save_bucketed(v: DataFrame, table: str, buckets: int) -> None:
    """A catalog table bucketed by tree_id: joins on tree_id read it without a shuffle."""
    v.write.mode("overwrite").bucketBy(buckets, "tree_id").sortBy("tree_id", "lo").saveAsTable(table)


def save_patterns(patterns: DataFrame, path: str, kind: str = "parquet") -> None:
    """Patterns by size, as 'parquet', 'orc', 'json' or 'csv'. The columns are all of plain types."""
    writer = patterns.write.partitionBy("size").mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)


def load_patterns(spark: SparkSession, path: str, kind: str, schema) -> DataFrame:
    """What save_patterns wrote; sizes asked for are read only from their folders."""
    reader = spark.read.schema(schema).format(kind)
    return (reader.option("header", True) if kind == "csv" else reader).load(path)


def save_records(records: DataFrame, path: str, kind: str = "parquet") -> None:
    """Records of patterns; in csv the path's bounds are joined by commas."""
    flat = records.withColumn("rp", F.array_join("rp", ",")) if kind == "csv" else records
    writer = flat.write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)
