"""Session trees and watched supports from an event stream.

Support is a sum over trees, so windows of it are sums of per-session counts.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import pattern as pt
from ..operators.baselines import count_in_tree
from ..sources.tables import EVENT_RANKS

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files: str = "events*.parquet", per_trigger: int | None = None) -> DataFrame:
    """A stream of event files; ts as a zoned timestamp (read as the session's zone if it has none)."""
    schema = spark.read.option("pathGlobFilter", files).parquet(folder).schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", files)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def _rank(label):
    out = F.lit(max(EVENT_RANKS.values()) + 1)
    for name, r in EVENT_RANKS.items():
        out = F.when(label == name, r).otherwise(out)
    return out


def session_trees(events: DataFrame, gap: str = "24 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, start, end, nodes): closed sessions as trees, nodes (lo, hi, label), the parent rule of ranked sessions.

    Events later than the watermark are dropped; repeated event_ids inside it are too.
    """
    fresh = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    s = fresh.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.col("event_type").alias("label"), _rank(F.col("event_type")).alias("rank")))).alias("e"))
    n = F.size("e")
    # The next event of no larger rank ends a scope; places are one up, as the session itself is place 0.
    ends = lambda x, i: F.array_min(F.transform(F.filter(F.sequence(F.lit(0), n - 1), lambda j: (j > i) & (F.col("e")[j]["rank"] <= x["rank"])), lambda j: j))
    nodes = F.transform("e", lambda x, i: F.struct((i + 1).alias("lo"), F.coalesce(ends(x, i), n).alias("hi"), x["label"].alias("label")))
    root = F.array(F.struct(F.lit(0).alias("lo"), n.alias("hi"), F.lit("session").alias("label")))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.concat(root, nodes).alias("nodes"))


def session_trees_stateful(events: DataFrame, gap_hours: int = 24, late: str = "1 hour") -> DataFrame:
    """session_trees by state of our own: a user's open events are kept, and go out as a tree once the watermark is a gap past the last one.

    An event that comes late but within the watermark may join two sessions that are still kept. Repeated event_ids inside the watermark are dropped.
    """
    import pandas as pd

    gap = gap_hours * 3_600_000_000
    ranks, other = dict(EVENT_RANKS), max(EVENT_RANKS.values()) + 1
    micros = lambda ts: int(ts.timestamp() * 1_000_000 + 0.5)

    def closed(kept: list[tuple[int, int, str]], now: int) -> tuple[list[list], list, int]:
        """Sessions that are over at ``now``, the events of the others, and when the first of these ends."""
        sessions: list[list] = []
        for e in sorted(kept):
            if sessions and e[0] - sessions[-1][-1][0] <= gap:
                sessions[-1].append(e)
            else:
                sessions.append([e])
        left = [s for s in sessions if s[-1][0] + gap > now]
        return [s for s in sessions if s[-1][0] + gap <= now], [e for s in left for e in s], min((s[-1][0] + gap for s in left), default=0)

    def tree(session: list) -> list[dict]:
        level = [ranks.get(label, other) for _, _, label in session]
        nodes, open_ = [{"lo": 0, "hi": len(session), "label": "session"}], []
        for i, (_, _, label) in enumerate(session):
            while open_ and level[open_[-1]] >= level[i]:
                nodes[open_.pop() + 1]["hi"] = i
            nodes.append({"lo": i + 1, "hi": len(session), "label": label})
            open_.append(i)
        return nodes

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        kept = [(t, i, label) for t, i, label in zip(*(list(x) for x in state.get))] if state.exists else []
        for frame in frames:
            kept += [(micros(t), int(i), str(label)) for t, i, label in zip(frame["ts"], frame["event_id"], frame["event_type"])]
        now = state.getCurrentWatermarkMs() * 1000
        done, kept, due = closed(kept, now)
        if kept:
            state.update(tuple(list(x) for x in zip(*kept)))
            state.setTimeoutTimestamp(max(now, due) // 1000 + 1)
        elif state.exists:
            state.remove()
        if done:
            at = lambda us: pd.Timestamp(us, unit="us")
            yield pd.DataFrame({"user_id": [key[0]] * len(done), "start": [at(s[0][0]) for s in done], "end": [at(s[-1][0] + gap) for s in done], "nodes": [tree(s) for s in done]})

    fresh = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]).select("user_id", "ts", "event_id", "event_type")
    out, kept = "user_id long, start timestamp, end timestamp, nodes array<struct<lo int, hi int, label string>>", "ts array<long>, event_id array<long>, label array<string>"
    return fresh.groupBy("user_id").applyInPandasWithState(step, out, kept, "append", "EventTimeTimeout")


def watched_counts(trees: DataFrame, codes: list[str]) -> DataFrame:
    """(user_id, end, code, n_occ) of watched patterns in each session."""
    patterns = [pt.parse(c) for c in codes]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, which, counts = [], [], []
            for i, nodes in enumerate(batch.column("nodes").to_pylist()):
                tree = [(x["lo"], x["hi"], x["label"]) for x in nodes]
                for code, p in zip(codes, patterns):
                    n = count_in_tree(tree, p)
                    if n:
                        at.append(i)
                        which.append(code)
                        counts.append(n)
            rows = pa.array(at, "int64")
            yield pa.RecordBatch.from_arrays([batch.column("user_id").take(rows), batch.column("end").take(rows), pa.array(which, "string"), pa.array(counts, "int64")], names=["user_id", "end", "code", "n_occ"])

    return trees.select("user_id", "end", "nodes").mapInArrow(run, "user_id long, end timestamp, code string, n_occ long")


def windowed_support(counts: DataFrame, size: str = "7 days", slide: str | None = None) -> DataFrame:
    """Support of watched patterns by windows of session ends."""
    w = F.window("end", size, slide) if slide else F.window("end", size)
    return counts.groupBy(w.alias("w"), "code").agg(F.sum("n_occ").alias("support"), F.count(F.lit(1)).alias("tree_support")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "code", "support", "tree_support")


def merge_support(folder: str):
    """A foreachBatch sink that appends each batch's supports by batch_id; sum them to read. A replayed batch overwrites its own folder."""

    def sink(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy("code").agg(F.sum("n_occ").alias("support"), F.count(F.lit(1)).alias("tree_support")).write.mode("overwrite").parquet(f"{folder}/batch={batch_id}")

    return sink


def read_support(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.parquet(folder).groupBy("code").agg(F.sum("support").alias("support"), F.sum("tree_support").alias("tree_support"))
