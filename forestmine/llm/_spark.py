"""Shared-storage materialisation and small Spark helpers."""

from __future__ import annotations

import contextlib
import gc
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Ids broadcast at most (8 bytes each); above that the plan shuffles instead.
BROADCAST_IDS = 1_000_000


def shared_folder(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir. Where that is unset, the context's own, or, with a local master only, a temporary one."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not known.isDefined():
            if not spark.sparkContext.master.startswith("local["):
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
            spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="forestmine-"))
            known = spark.sparkContext._jsc.sc().getCheckpointDir()
        where = known.get()
    return where.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str, by: str | None = None) -> DataFrame:
    """Write a table to shared storage and read it again: one evaluation, no lineage."""
    path, schema = fresh_path(df.sparkSession, name), df.schema
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(by) if by else writer).parquet(path)
    out = df.sparkSession.read.schema(schema).parquet(path)
    out._written = path
    return out


def discard(*tables: DataFrame | None) -> None:
    """Delete tables that materialize wrote and nothing reads any more."""
    for df in tables:
        path = getattr(df, "_written", None)
        if path:
            remove_path(df.sparkSession, path)


def sweep(spark: SparkSession) -> None:
    """Lets Spark remove the shuffle files of tables that nothing refers to any more, which else stay until the driver happens to collect its garbage."""
    gc.collect()
    spark._jvm.System.gc()


def remove_path(spark: SparkSession, path: str) -> None:
    """Delete a folder of shared storage through Hadoop's own file system."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 512, size: str = "4m") -> Iterator[None]:
    """Within, tables are handed to Python in batches of so many rows and bytes: workers and the buffers beside the heap stay small.

    Executors keep Python workers apart by such settings, so an operator stays within for all of its steps.
    """
    own = {"spark.sql.execution.arrow.maxRecordsPerBatch": str(rows), "spark.sql.execution.arrow.maxBytesPerBatch": size}
    before = {k: spark.conf.get(k, None) for k in own}
    for k, v in own.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def table(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def masked(df: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """df with names of our own for its columns, so that no caller's name clashes with one that an operator adds, and these names by the caller's."""
    own = {c: f"own_{i}" for i, c in enumerate(df.columns)}
    return df.toDF(*own.values()), own


def only_ids(df: DataFrame, ids: DataFrame, key: str, keep: bool = True) -> DataFrame:
    """Rows of df whose key is (or is not) in ids (one column, ``key``).

    The ids are counted first: broadcast if they are few, else the join shuffles.
    """
    few = ids.count() <= BROADCAST_IDS
    return df.join(F.broadcast(ids) if few else ids, key, "left_semi" if keep else "left_anti")
