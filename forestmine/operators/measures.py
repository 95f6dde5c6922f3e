"""Cost and shape measures."""

from __future__ import annotations

import math
import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.relations import is_ancestor
from .match import full_matches, records


def forest_stats(v: DataFrame) -> DataFrame:
    """One row: trees, vertices, labels, largest and summed size in vertices and in tokens of the encoded string (2n - 1)."""
    trees = v.groupBy("tree_id").agg(F.count(F.lit(1)).alias("n"), F.max("depth").alias("d"))
    shape = trees.agg(F.count(F.lit(1)).alias("n_trees"), F.sum("n").alias("n_vertices"), F.max("n").alias("max_size"), F.max("d").cast("long").alias("max_depth"), (F.max("n") * 2 - 1).alias("max_encoded"), F.sum(F.col("n") * 2 - 1).alias("sum_encoded"))
    return shape.crossJoin(v.agg(F.countDistinct("label").alias("n_labels")))  # two one-row tables


def record_stats(r: DataFrame) -> DataFrame:
    """One row for a record set: records, occurrences, b (most records of a tree), e (most occurrences of a tree), longest path."""
    per_tree = r.groupBy("tree_id").agg(F.count(F.lit(1)).alias("b"), F.sum("mult").alias("e"), F.max(F.size("rp")).alias("d"))
    return per_tree.agg(F.coalesce(F.sum("b"), F.lit(0)).alias("n_records"), F.coalesce(F.sum("e"), F.lit(0)).alias("n_occurrences"), F.max("b").alias("b"), F.max("e").alias("e"), (F.max("d") - 1).cast("long").alias("d"))


def structure_size(v: DataFrame, code: str) -> DataFrame:
    """record_stats of a pattern with the rows and vertices that full matches would take."""
    k = len(code.split(" "))
    return record_stats(records(v, code)).withColumn("full_match_cells", F.col("n_occurrences") * k)


def logical_bytes(r: DataFrame) -> int:
    """Bytes of a record set at eight a field: tree, scope, count and path."""
    width = 4 + F.size("rp") + (2 * F.size("matched") if "matched" in r.columns else F.lit(0))
    return int(r.agg(F.sum(8 * width)).first()[0] or 0)


def pattern_counts(patterns: DataFrame) -> DataFrame:
    """(size, n_patterns)."""
    return patterns.groupBy(F.col("size").cast("long").alias("size")).agg(F.count(F.lit(1)).alias("n_patterns"))


def path_label_repeats(v: DataFrame) -> DataFrame:
    """tree_id of trees with a label twice on a root-to-leaf path; the others have records linear in their size."""
    a, b = v.alias("a"), v.alias("b")
    same = (F.col("a.tree_id") == F.col("b.tree_id")) & (F.col("a.label") == F.col("b.label"))
    return a.join(b, same & is_ancestor(F.col("a.lo"), F.col("a.hi"), F.col("b.lo"), F.col("b.hi")), "left_semi").select("tree_id").distinct()


def star_size(n: int, k: int) -> tuple[int, int]:
    """(occurrences, records) of a root with k - 1 leaves in a root with n - 1 equal leaves."""
    return math.comb(n - 1, k - 1), n - k + 1


def chain_size(n: int, k: int, merge: str = "canonical") -> tuple[int, int]:
    """(occurrences, records) of a chain of k in a chain of n, one label."""
    return math.comb(n, k), n - k + 1 if merge == "canonical" else math.comb(n, k)


def timed(run: Callable[[], DataFrame], repeat: int = 1, cap: float | None = None, spark: SparkSession | None = None) -> dict:
    """Median seconds of collecting run()'s rows, their number, and a status: 'ok', 'cap' or the error's name.

    With spark, a run is stopped once it takes more than ``cap`` seconds: its jobs are in a group that a timer cancels.
    """
    seconds, rows = [], 0
    for _ in range(repeat):
        began, stopped, timer = time.time(), threading.Event(), None
        if spark is not None and cap:
            group = f"timed-{uuid.uuid4().hex}"
            spark.sparkContext.setJobGroup(group, "timed", interruptOnCancel=True)

            def stop(group: str = group, stopped: threading.Event = stopped) -> None:
                stopped.set()
                while stopped.is_set():  # a run starts one job after the other
                    spark.sparkContext.cancelJobGroup(group)
                    time.sleep(0.5)

            timer = threading.Timer(cap, stop)
            timer.daemon = True
            timer.start()
        try:
            rows = len(run().collect())
        except Exception as e:  # a failure is a measured outcome here
            return {"seconds": round(time.time() - began, 3), "patterns": None, "status": "cap" if stopped.is_set() else type(e).__name__}
        finally:
            if timer:
                timer.cancel()
                stopped.clear()
                spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        seconds.append(time.time() - began)
    middle = sorted(seconds)[len(seconds) // 2]
    return {"seconds": round(middle, 3), "patterns": rows, "status": "cap" if cap and middle > cap else "ok"}


def compare_sizes(v: DataFrame, code: str) -> DataFrame:
    """One row: records, rows of full matches."""
    r, f = records(v, code), full_matches(v, code)
    return r.agg(F.count(F.lit(1)).alias("n_records"), F.coalesce(F.sum("mult"), F.lit(0)).alias("n_occurrences")).crossJoin(f.agg(F.count(F.lit(1)).alias("n_full")))  # two one-row tables
