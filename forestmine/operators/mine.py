"""Level-wise mining of frequent embedded patterns.

One loop serves the compact miner and the baselines that keep state: they differ
in the kernel that turns the state of a level and the vertices into candidates'
state, in the candidate rule and in the support. A level costs one pass of the
kernel (inside the partitions of tree_id) and one small shuffle of counts; only
frequent candidates come to the driver. States are persisted, so no plan grows; with a
checkpoint folder they are written there, and a lost executor costs a read.
"""

from __future__ import annotations

from collections.abc import Callable
import json
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import pattern as pt
from . import joins
from .encode import pack

PATTERNS = "pattern_id long, code string, size int, prefix_id long, attach_depth int, label string, support decimal(38,0), tree_support long, n_records long"
CANDIDATE = joins.CANDIDATE
#: Rows of a level's allowed or frequent list that are broadcast; longer lists are joined by shuffle.
BROADCAST_ROWS = 2_000_000
#: Preorder numbers in a bin of the binned plan.
BIN = 4096


@dataclass
class Kernel:
    """start(vertices, ids) gives the state of single vertices; grow(state, vertices) adds prefix_id, c, label, mult and the new state."""

    start: Callable[[DataFrame, DataFrame], DataFrame]
    grow: Callable[[DataFrame], DataFrame]
    finish: Callable[[DataFrame], DataFrame] = lambda df: df
    state: list[str] = field(default_factory=lambda: ["tree_id", "lo", "hi", "rp", "mult"])
    name: str = "compact"


def compact_kernel(v: DataFrame, plan: str, merge: str) -> Kernel:
    """The record joins. plan: 'join' (range), 'packed' (slices), 'binned' (giant trees), 'cumulative' (running totals) or 'local' (a tree's work in Python)."""
    if plan == "join":
        return Kernel(joins.singletons, lambda r: joins.pairs_by_join(r, v), lambda j: joins.attach(j, merge))
    if plan == "binned":
        return Kernel(joins.singletons, lambda r: joins.pairs_binned(r, v, BIN), lambda j: joins.attach(j, merge))
    if plan == "packed":
        packed = pack(v).persist()
        return Kernel(joins.singletons, lambda r: joins.pairs_by_slice(r, packed), lambda j: joins.attach(j, merge))
    if plan == "local":
        from ..plans.local import pairs_by_kernel

        return Kernel(joins.singletons, lambda r: pairs_by_kernel(r, pack(v)), lambda j: joins.attach(j, merge))
    if plan != "cumulative":
        raise ValueError(f"unknown plan {plan}")
    if merge != "canonical":
        raise ValueError("running totals need merged records")

    def grow(r: DataFrame) -> DataFrame:
        deepest = r.agg(F.max(F.size("rp"))).first()[0] or 1
        under = r.join(v.select(F.col("tree_id").alias("x_tree"), F.col("lo").alias("x_lo"), F.col("hi").alias("x_hi"), "label"), (F.col("tree_id") == F.col("x_tree")) & (F.col("x_lo") > F.col("lo")) & (F.col("x_hi") <= F.col("hi")))
        out = under.groupBy(F.col("pattern_id").alias("prefix_id"), (F.size("rp") - 1).alias("c"), "label", "tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), F.concat("rp", F.array("x_hi")).alias("rp")).agg(F.sum("mult").alias("mult"))
        for c in range(deepest - 1):
            out = out.unionByName(joins.inner_cumulative(r, v, c, by=["label"]).withColumnRenamed("pattern_id", "prefix_id").withColumn("c", F.lit(c)))
        return out

    return Kernel(joins.singletons, grow)


def frequent_labels(v: DataFrame, minsup: int, support: str = "occurrence", spread: int = 1) -> DataFrame:
    """(label, support, tree_support) of labels that are frequent, in one scan. spread: v has each tree so many times."""
    counts = v.filter("label is not null and tree_id is not null").groupBy("label").agg((F.count(F.lit(1)) / spread).cast("long").alias("support"), F.countDistinct(F.col("tree_id") if spread == 1 else F.expr(f"(tree_id - pmod(tree_id, {spread}L)) div {spread}L")).alias("tree_support"))
    return counts.filter(F.col("tree_support" if support == "tree" else "support") >= minsup)


def hinted(df: DataFrame, n: int) -> DataFrame:
    """df of n rows, to be broadcast if these are few."""
    return F.broadcast(df) if n <= BROADCAST_ROWS else df


def shrink(v: DataFrame, labels: DataFrame) -> DataFrame:
    """Vertices with one of the labels, scopes unchanged: occurrences need ancestor relations only. The labels are counted first."""
    return v.join(hinted(labels.select("label"), labels.count()), "label", "left_semi").select(*v.columns)


def threshold(v: DataFrame, num: int, den: int) -> int:
    """A threshold relative to the number of trees, as an integer of at least 1."""
    return max(1, v.select("tree_id").distinct().count() * num // den)


@dataclass
class Trace:
    """What a mining call did, by level: candidates generated, met in the data, frequent; records, occurrences and bytes of the state; seconds of generating and of counting."""

    levels: list[dict] = field(default_factory=list)


def levelwise(v: DataFrame, minsup: int, kernel: Kernel, max_size: int | None = None, rule: str = "prefix", support: str = "occurrence", roots: list[str] | None = None, trace: Trace | None = None, exact_counts: str = "long", checkpoint: str | None = None, labels: DataFrame | None = None, spread: int = 1, guided: bool = False) -> DataFrame:
    """All frequent patterns: the PATTERNS columns.

    checkpoint: a folder that gets each level's patterns and state; a later call with it goes on after the
    last whole level. It belongs to one input and one set of arguments; another call with it raises.

    rule: 'prefix' (the prefix is frequent), 'class' (a sibling is too), 'all' (every
    one-vertex-removed pattern is) or 'none' (support only; needs max_size). guided: rule 'all' is held
    against extensions that occur and are frequent, instead of deciding before the data are read.
    roots: only patterns with these root labels. Threshold by occurrences or trees.
    labels: frequent_labels(v, minsup, support), if it is there already. spread: copies of each tree (see embedded).

    Defined cases: vertices without a label or tree_id are in no pattern. An empty forest gives no patterns.
    """
    from .measures import logical_bytes

    spark = v.sparkSession
    if rule == "none" and not max_size:
        raise ValueError("without a rule a largest size is needed")
    measure = "tree_support" if support == "tree" else "support"
    least = minsup if rule != "none" else 1
    found = (labels if labels is not None and rule != "none" else frequent_labels(v, least, support, spread)).orderBy("label").collect()
    names = {r["label"] for r in found}
    rows, level = [], {}
    for r in found:
        if roots is None or r["label"] in roots:
            nodes = ((pt.escape(r["label"]), 0),)
            level[len(rows)] = nodes
            rows.append((len(rows), pt.code(nodes), 1, None, None, r["label"], int(r["support"]), r["tree_support"], int(r["support"])))
    if not rows:
        return _result(spark, rows, minsup, measure, exact_counts)
    ids = spark.createDataFrame([(r[5], r[0]) for r in rows], "label string, pattern_id long")
    state = kernel.start(v, hinted(ids, len(rows))).persist()
    # What the rules look up: frequent patterns of the last level, whatever their root.
    known = {nodes for nodes in level.values()} | {((pt.escape(x), 0),) for x in names}
    size, used = 1, []
    if checkpoint:
        _claim(checkpoint, v, {"minsup": minsup, "rule": rule, "support": support, "roots": roots, "exact_counts": exact_counts, "spread": spread, "kernel": kernel.name, "state": kernel.state})
        done = _restore(spark, checkpoint, state)
        if done:
            size, rows, level, state = done
            known = set(level.values())
    tree = F.col("tree_id") if spread == 1 else F.expr(f"(tree_id - pmod(tree_id, {spread}L)) div {spread}L")
    while level and (max_size is None or size < max_size):
        size += 1
        began = time.time()
        pairs = kernel.grow(state)
        generated = None
        if rule in ("class", "all") and size > 2 and not guided:
            allowed, generated = _allowed(spark, rows, level, known, rule)
            near = "pattern_id" if "pattern_id" in pairs.columns else "prefix_id"
            pairs = pairs.join(hinted(allowed.withColumnRenamed("prefix_id", near), generated), [near, "c", "label"], "left_semi").select(*pairs.columns)
        grown = kernel.finish(pairs).persist()
        total = F.sum(F.col("mult").cast("decimal(38,0)")) if exact_counts == "decimal" else F.sum("mult")
        counts = grown.groupBy(*CANDIDATE, tree.alias("tree")).agg(total.alias("s"), F.count(F.lit(1)).alias("n")).groupBy(*CANDIDATE).agg(F.sum("s").alias("support"), F.count(F.lit(1)).alias("tree_support"), F.sum("n").alias("n_records"))
        if trace is not None:
            counts, records = counts.persist(), grown.count()
            made = time.time()
        good = counts.filter(F.col(measure) >= least).orderBy("prefix_id", "c", "label").collect()
        for df in used:
            df.unpersist()
        used = []
        if rule == "all" and guided and size > 2:
            good = [r for r in good if all(p in known for p in pt.one_removed(pt.extend(level[r["prefix_id"]], pt.escape(r["label"]), r["c"])))]
        if trace is not None:
            made_up = generated if generated is not None else sum(n[-1][1] + 1 for n in level.values()) * len(names)
            kept = grown.join(hinted(spark.createDataFrame([(r["prefix_id"], r["c"], r["label"]) for r in good], "prefix_id long, c int, label string"), len(good)), CANDIDATE, "left_semi")
            trace.levels.append({"size": size, "generated": made_up, "met": counts.count(), "frequent": len(good), "records": records, "frequent_records": sum(r["n_records"] for r in good), "occurrences": int(sum(r["support"] for r in good)), "state_bytes": logical_bytes(kept), "pattern_bytes": sum(len(r[1]) + 40 for r in rows), "generation_s": round(made - began, 3), "counting_s": round(time.time() - made, 3)})
            counts.unpersist()
        level_next, new = {}, []
        for r in good:
            nodes = pt.extend(level[r["prefix_id"]], pt.escape(r["label"]), r["c"])
            at = len(rows)
            level_next[at] = nodes
            new.append((r["prefix_id"], r["c"], r["label"], at))
            rows.append((at, pt.code(nodes), size, r["prefix_id"], r["c"], r["label"], int(r["support"]), r["tree_support"], r["n_records"]))
        level = level_next
        known = set(level.values())
        if level and (max_size is None or size < max_size):
            marks = hinted(spark.createDataFrame(new, "prefix_id long, c int, label string, pattern_id long"), len(new))
            after = grown.join(marks, CANDIDATE).select("pattern_id", *kernel.state)
            if checkpoint:
                after.write.mode("overwrite").parquet(f"{checkpoint}/state-{size}")
                spark.createDataFrame([(*r[:6], str(r[6]), *r[7:]) for r in rows], PATTERNS.replace("decimal(38,0)", "string")).coalesce(1).write.mode("overwrite").parquet(f"{checkpoint}/patterns-{size}")
                after = spark.read.parquet(f"{checkpoint}/state-{size}").repartition("tree_id")
            # The new state is made by the next level's first job, from what this level keeps; until then both stay.
            used, state = [*used, state, grown], after.persist()
        else:
            used.append(grown)
    for df in [*used, state]:
        df.unpersist()
    return _result(spark, rows, minsup, measure, exact_counts)


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def _claim(folder: str, v: DataFrame, run: dict) -> None:
    """Binds a checkpoint folder to a call's arguments and input; raises if it belongs to another call."""
    spark = v.sparkSession
    seen = v.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("tree_id", "lo", "hi", "label").cast("decimal(38,0)")).alias("h")).first()
    own = json.dumps({**run, "vertices": seen["n"], "hash": str(seen["h"])}, sort_keys=True)
    if _exists(spark, f"{folder}/run/_SUCCESS"):
        if spark.read.parquet(f"{folder}/run").first()["run"] != own:
            raise ValueError(f"{folder} holds the checkpoints of another run")
    elif _exists(spark, f"{folder}/state-2"):
        raise ValueError(f"{folder} holds checkpoints of an unknown run")
    else:
        spark.createDataFrame([(own,)], "run string").coalesce(1).write.mode("overwrite").parquet(f"{folder}/run")


def _restore(spark: SparkSession, folder: str, state: DataFrame) -> tuple | None:
    """The last level whose patterns and state were both written whole: size, pattern rows, the level's patterns, state."""
    there = lambda name: _exists(spark, f"{folder}/{name}/_SUCCESS")
    size = 1
    while there(f"state-{size + 1}") and there(f"patterns-{size + 1}"):
        size += 1
    if size == 1:
        return None
    rows = [tuple(int(x) if i == 6 else x for i, x in enumerate(r)) for r in spark.read.parquet(f"{folder}/patterns-{size}").orderBy("pattern_id").collect()]
    state.unpersist()
    level = {r[0]: pt.parse(r[1]) for r in rows if r[2] == size}
    return size, rows, level, spark.read.parquet(f"{folder}/state-{size}").repartition("tree_id").persist()


def _allowed(spark: SparkSession, rows: list[tuple], level: dict, known: set, rule: str) -> tuple[DataFrame, int]:
    """(prefix_id, c, label) that a rule lets through, and their number.

    Both rules need a frequent sibling of the prefix that ends in the label: so a candidate is a pair of siblings, which a join of the
    level with itself finds. Rule 'all' then looks its other sub-patterns up, candidate by candidate.
    """
    last = spark.createDataFrame([(at, rows[at][3], nodes[-1][1], rows[at][5]) for at, nodes in level.items()], "pattern_id long, prefix_id long, depth int, label string")
    p, q = last.alias("p"), last.alias("q")
    pairs = p.join(q, (F.col("p.prefix_id") == F.col("q.prefix_id")) & (F.col("q.depth") <= F.col("p.depth")))
    # The sibling's depth tells where the vertex goes: under its own parent, or (at the prefix's depth) under the prefix's last vertex, too.
    c = F.explode(F.when(F.col("q.depth") == F.col("p.depth"), F.array(F.col("q.depth") - 1, F.col("q.depth"))).otherwise(F.array(F.col("q.depth") - 1)))
    out = pairs.select(F.col("p.pattern_id").alias("prefix_id"), F.col("q.label").alias("label"), c.alias("c")).select("prefix_id", "c", "label")
    if rule == "class":
        out = out.persist()
        return out, out.count()
    held = [tuple(r) for r in out.toLocalIterator() if all(x in known for x in pt.one_removed(pt.extend(level[r["prefix_id"]], pt.escape(r["label"]), r["c"])))]
    return spark.createDataFrame(held, "prefix_id long, c int, label string"), len(held)


def _result(spark: SparkSession, rows: list[tuple], minsup: int, measure: str, exact_counts: str) -> DataFrame:
    from decimal import Decimal

    at = 6 if measure == "support" else 7
    df = spark.createDataFrame([(*r[:6], Decimal(r[6]), *r[7:]) for r in rows if r[at] >= minsup], PATTERNS)
    return df if exact_counts == "decimal" else df.withColumn("support", F.col("support").cast("long"))


def embedded(v: DataFrame, minsup: int, max_size: int | None = None, rule: str = "prefix", support: str = "occurrence", merge: str = "canonical", plan: str = "join", exact_counts: str = "long", schedule: str = "levels", batch: int = 1, shrunk: bool = True, trace: Trace | None = None, checkpoint: str | None = None, spread: int | str = 1) -> DataFrame:
    """The compact miner.

    schedule 'classes' mines the patterns of ``batch`` root labels at a time, which
    bounds the live state as a depth-first order does; 'levels' takes all at once.

    spread: for few large trees. Each tree's work is dealt to so many tasks by root occurrence: records of one root never
    merge with another's, so a copy of the tree's vertices for each share of the roots is all they need. 'auto' makes as many
    copies as give each core two shares, 64 at most.

    plan 'counted' keeps no records between levels: tasks make them anew from whole trees (see plans.counted). It has no checkpoints, traces,
    classes, decimal counts or literal records, and n_records is null from size 2 on.

    Defined cases: as for levelwise; a vertex without a label or tree_id is in no pattern.
    """
    keep = frequent_labels(v, minsup, support).persist()
    v = shrink(v, keep) if shrunk and rule != "none" and plan not in ("packed",) else v
    if spread == "auto":
        trees = max(1, v.select("tree_id").distinct().count())
        spread = max(1, min(64, -(-2 * v.sparkSession.sparkContext.defaultParallelism // trees)))
    if plan == "counted":
        if rule == "none" or (merge, exact_counts, schedule) != ("canonical", "long", "levels") or trace is not None or checkpoint:
            raise ValueError("plan 'counted' takes no rule 'none', literal merging, decimal counts, classes, trace or checkpoint")
        from ..plans import counted

        try:
            return counted.mine(v, minsup, max_size, keep, rule, support, spread=spread)
        finally:
            keep.unpersist()
    kernel_of = lambda v: compact_kernel(v, plan, merge)
    if spread > 1:
        v = v.withColumn("tree_id", F.explode(F.transform(F.sequence(F.lit(0), F.lit(spread - 1)), lambda i: F.col("tree_id") * spread + i)))

        def kernel_of(v: DataFrame) -> Kernel:
            own = compact_kernel(v, plan, merge)
            share = F.pmod(F.xxhash64("hi"), F.lit(spread)) == F.pmod("tree_id", F.lit(spread))
            return Kernel(lambda v, ids: own.start(v, ids).filter(share), own.grow, own.finish, own.state, own.name)

    v = v.repartition("tree_id").persist()
    try:
        run = lambda roots=None, size=max_size, **kw: levelwise(v, minsup, kernel_of(v), size, rule, support, roots, trace, exact_counts, labels=keep, spread=spread, **kw)
        if schedule == "levels" or rule == "all":
            return run(checkpoint=checkpoint)
        names = [r["label"] for r in keep.orderBy("label").collect()]
        parts = [run(names[i : i + batch]) for i in range(0, len(names), batch)]
        out = parts[0] if parts else run(size=1)
        for p in parts[1:]:
            out = out.unionByName(p)
        return out
    finally:
        v.unpersist()
        keep.unpersist()


def embedded_reference(v: DataFrame, minsup: int, max_size: int) -> list[tuple[str, int]]:
    """One pattern at a time, depth first, by the given-pattern joins. Small data only: an oracle for the level loop."""
    from .match import records

    labels = [r["label"] for r in frequent_labels(v, minsup).orderBy("label").collect()]
    stack = [(((pt.escape(x), 0),), None) for x in labels]
    out = []
    while stack:
        nodes, _ = stack.pop()
        n = records(v, pt.code(nodes)).agg(F.sum("mult")).first()[0] or 0
        if n >= minsup:
            out.append((pt.code(nodes), int(n)))
            if len(nodes) < max_size:
                stack += [(e, None) for e in pt.extensions(nodes, [pt.escape(x) for x in labels])]
    return sorted(out)


def top_k(v: DataFrame, k: int, start: int, max_size: int | None = None, **options) -> DataFrame:
    """The k patterns of largest support: mined at a threshold that halves until there are k."""
    minsup = max(1, start)
    while True:
        found = embedded(v, minsup, max_size, **options)
        if minsup == 1 or found.count() >= k:
            return found.orderBy(F.desc("support"), "code").limit(k)
        minsup = max(1, minsup // 2)
