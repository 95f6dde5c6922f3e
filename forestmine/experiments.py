"""Threshold sweeps: run time, memory, patterns and candidates of each miner on each forest.

``python -m forestmine.experiments [SF_DIR [CAP]]`` prints one JSON line for each forest,
threshold and method, then the ablations, structure sizes, phases and runs on one and four cores. Run times are those of one call
after a warm-up; a run is stopped after CAP seconds (status 'cap'), and lower thresholds of that method on that forest are then left
out (status 'left out'). bytes is the largest level's state at eight bytes a field, pattern_bytes that of the pattern list beside it.
"""

from __future__ import annotations

import json
import subprocess
import sys

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, joins, match, measures, mine
from .sources import generator, nested, tables
from .workloads import SYNTHETIC, synthetic

CAP = 60.0

METHODS = {
    "compact": lambda v, m, k, t: mine.embedded(v, m, k, trace=t),
    "full match": lambda v, m, k, t: baselines.full_match(v, m, k, trace=t),
    "model guided": lambda v, m, k, t: baselines.model_guided(v, m, k, trace=t),
    "rightmost set": lambda v, m, k, t: baselines.rightmost_set(v, m, k, trace=t),
    "horizontal": lambda v, m, k, t: baselines.horizontal(v, m, k),
}

#: Options of the compact miner, each against its default.
ABLATIONS = {
    "literal merge": {"merge": "literal"}, "packed plan": {"plan": "packed"}, "running totals": {"plan": "cumulative"}, "local plan": {"plan": "local"}, "class rule": {"rule": "class"},
    "all rule": {"rule": "all"}, "class batches": {"schedule": "classes"}, "no shrinking": {"shrunk": False}, "decimal counts": {"exact_counts": "decimal"},
    "spread": {"spread": "auto"},
}


#: Forest, largest size, thresholds as shares of the number of trees, falling.
SWEEPS = {
    "web sessions": (tables.sessions_rank, 4, [(82, 100), (41, 100)]),
    "web sessions by value": (tables.sessions_value, 4, [(82, 100), (41, 100)]),
    "DOM trees": (tables.pages_flat, 3, [(4, 1), (1, 1)]),
    "nested DOM": (nested.pages_nested, 5, [(8, 1), (4, 1)]),
    "large trees": (tables.regions, 3, [(2000, 1), (500, 1)]),
    "customer trees": (tables.customers, 3, [(4, 1), (1, 2)]),
    "library": (tables.library, 3, [(2, 1), (1, 1)]),
    "user histories": (tables.users, 4, [(10, 1), (5, 1)]),
    "stars": (lambda s, d: generator.stars(s, 200, 21), 6, [(1, 1)]),
    "chains": (lambda s, d: generator.chains(s, 200, 16), 6, [(1, 1)]),
    **{f"synthetic, {name}": (synthetic(name), 3, [(1, 5), (1, 10)]) for name in SYNTHETIC},
}


def sweep(spark: SparkSession, sf_dir: str, name: str, cap: float = CAP, methods: list[str] | None = None) -> list[dict]:
    forest, k, shares = SWEEPS[name]
    v = forest(spark, sf_dir).persist()
    trees = v.select("tree_id").distinct().count()
    out, over = [], set()
    for num, den in shares:
        minsup, base = max(1, trees * num // den), None
        for method in methods or METHODS:
            row = {"forest": name, "trees": trees, "minsup": minsup, "size": k, "method": method}
            if method in over:
                out.append({**row, "status": "left out"})
                continue
            trace = mine.Trace()
            got = measures.timed(lambda run=METHODS[method]: run(v, minsup, k, trace), cap=cap, spark=spark)  # noqa: B023
            over |= {method} if got["status"] != "ok" else set()
            base = got["seconds"] if method == "compact" and got["status"] == "ok" else base
            levels = trace.levels
            out.append({**row, **got, "speed_up_of_compact": round(got["seconds"] / base, 2) if base and got["status"] in ("ok", "cap") else None, "bytes": max((x["state_bytes"] for x in levels), default=None), "pattern_bytes": max((x["pattern_bytes"] for x in levels), default=None), "records": max((x["frequent_records"] for x in levels), default=None), "occurrences": max((x["occurrences"] for x in levels), default=None), "candidates": sum(x["generated"] for x in levels), "generation_s": round(sum(x["generation_s"] for x in levels), 2), "counting_s": round(sum(x["counting_s"] for x in levels), 2)})
    v.unpersist()
    return out


def ablation(spark: SparkSession, sf_dir: str, name: str, cap: float = CAP) -> list[dict]:
    forest, k, shares = SWEEPS[name]
    v = forest(spark, sf_dir).persist()
    minsup = mine.threshold(v, *shares[0])
    out = [{"forest": name, "minsup": minsup, "option": option, **measures.timed(lambda: mine.embedded(v, minsup, k, **kw), cap=cap, spark=spark)} for option, kw in {"default": {}, **ABLATIONS}.items()]  # noqa: B023
    v.unpersist()
    return out


def sizes(spark: SparkSession) -> list[dict]:
    """Records against occurrences on stars and chains; logical bytes against those of full matches."""
    out = []
    for shape, make, code in (("star", generator.star, lambda k: " ".join(["a@0", *["b@1"] * (k - 1)])), ("chain", generator.chain, lambda k: " ".join(f"a@{i}" for i in range(k)))):
        for n, k in ((9, 5), (17, 9)):
            r = match.records(make(spark, n), code(k))
            s = measures.record_stats(r).first()
            out.append({"shape": shape, "n": n, "k": k, "records": s["n_records"], "occurrences": s["n_occurrences"], "bytes": measures.logical_bytes(r), "full_match_bytes": 8 * (4 + k + 2 * k) * s["n_occurrences"]})
    return out


def phases(v: DataFrame, minsup: int) -> dict:
    """Seconds of making the pairs of level 2 (generation) and of merging and counting them."""
    ids = mine.frequent_labels(v, minsup).select("label", F.xxhash64("label").alias("pattern_id"))
    pairs = joins.pairs_by_join(joins.singletons(v, ids), mine.shrink(v, ids))
    generated = measures.timed(lambda: pairs.agg(F.count(F.lit(1))))
    counted = measures.timed(lambda: joins.attach(pairs).groupBy(*joins.CANDIDATE).agg(F.sum("mult")))
    return {"generation": generated["seconds"], "generation_and_counting": counted["seconds"]}


def cores(sf_dir: str, name: str = "customer trees", on: tuple[int, ...] = (1, 4)) -> list[dict]:
    """Seconds of the compact miner on one forest with so many cores, each in a session of its own."""
    out = []
    for n in on:
        code = f"import sys, time; from forestmine import experiments as e; s = e.session({n}); e.sweep(s, {sf_dir!r}, {name!r}, 600, ['compact']); began = time.time(); rows = e.sweep(s, {sf_dir!r}, {name!r}, 600, ['compact']); print(sum(r['seconds'] for r in rows))"
        got = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=False)
        out.append({"forest": name, "cores": n, "seconds": float(got.stdout.strip().splitlines()[-1]) if got.returncode == 0 and got.stdout.strip() else None})
    return out


def session(cores: int) -> SparkSession:
    return SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", str(max(4, cores))).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()


def main(sf_dir: str, cap: float) -> None:
    spark = session(8)
    tell = lambda row: print(json.dumps(row, default=int), flush=True)
    mine.embedded(tables.conversations(spark, sf_dir), 1, 3).count()  # compiles code before the first measured run
    for name in SWEEPS:
        for row in sweep(spark, sf_dir, name, cap):
            tell(row)
    for row in ablation(spark, sf_dir, "web sessions by value", cap):
        tell(row)
    for row in sizes(spark):
        tell(row)
    tell({"phases": phases(tables.sessions_rank(spark, sf_dir), 100)})
    spark.stop()
    for row in cores(sf_dir):
        tell(row)


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01", float(sys.argv[2]) if len(sys.argv) > 2 else CAP)
