"""Joins and miners against brute force on random trees and worked examples."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from forestmine import pattern as pt
from forestmine.functions import relations
from forestmine.operators import baselines, encode, joins, match, measures, mine, post
from forestmine.sources import codec, generator, nested, store


def random_tree(rng, n, labels="ab"):
    def build(k):
        parts, left = [], k - 1
        while left:
            take = rng.randint(1, left)
            parts.append(build(take))
            left -= take
        return rng.choice(labels) + (f"({','.join(parts)})" if parts else "")

    return build(n)


@pytest.fixture(scope="module")
def forest(spark):
    rng = random.Random(5)
    v = generator.literal_forest(spark, [random_tree(rng, rng.randint(1, 9)) for _ in range(25)]).persist()
    v.count()
    return v


def embeddings(tree, pattern):
    """All occurrences, from the definition."""
    nodes = pt.parse(pattern)
    above = [pt.rightmost_path(nodes[: i + 1])[:-1] for i in range(len(nodes))]
    out = []

    def go(chosen):
        i = len(chosen)
        if i == len(nodes):
            out.append(tuple(chosen))
            return
        for lo, hi, label in tree:
            if label == nodes[i][0] and all(c[0] < lo for c in chosen) and all(((c[0] < lo) and hi <= c[1]) == (a in above[i]) for a, c in enumerate(chosen)):
                go([*chosen, (lo, hi)])

    go([])
    return out


PATTERNS = ["a@0", "a@0 b@1", "a@0 a@1 b@1", "a@0 b@1 a@2", "a@0 b@1 a@2 b@1", "b@0 a@1 a@1 a@1"]


def test_records_equal_grouped_embeddings(spark, forest):
    trees = {}
    for r in forest.collect():
        trees.setdefault(r["tree_id"], []).append((r["lo"], r["hi"], r["label"]))
    for code in PATTERNS:
        path = pt.rightmost_path(pt.parse(code))
        wanted = {}
        for t, nodes in trees.items():
            for e in embeddings(nodes, code):
                key = (t, e[-1][0], e[-1][1], tuple(e[i][1] for i in path))
                wanted[key] = wanted.get(key, 0) + 1
        got = {(r["tree_id"], r["lo"], r["hi"], tuple(r["rp"])): r["mult"] for r in match.records(forest, code).collect()}
        assert got == wanted, code
        for (_, _, hi, rp), _ in got.items():
            assert rp[-1] == hi and list(rp) == sorted(rp, reverse=True)
        assert sum(baselines.count_in_tree(n, pt.parse(code)) for n in trees.values()) == sum(wanted.values())
    code = "a@0 b@1 a@2 b@1"
    assert {tuple(r) for r in match.brute_force(forest, code).collect()} == {tuple(r) for r in match.count_per_tree(forest, code).collect()}
    full = match.occurrence_trees(forest, code)
    assert full.count() == sum(r["n_occ"] for r in match.count_per_tree(forest, code).collect())
    assert all(len(r["edges"]) == 3 for r in full.collect())


def test_inner_join_forms_agree(forest):
    r = match.records(forest, "a@0 b@1")
    x = forest.filter("label = 'a'")
    rows = lambda df: sorted(map(str, df.select("tree_id", "lo", "hi", "rp", "mult").collect()))
    assert rows(joins.inner(r, x, 0)) == rows(joins.inner_sorted(r, x, 0)) == rows(joins.inner_cumulative(r, x, 0))


def test_extension_check_names_faults(spark):
    v = spark.createDataFrame([(0, [(0, 5), (1, 1)])], "id int, m array<struct<lo:int,hi:int>>")
    ask = lambda y, lo, hi: v.select(relations.extension_faults(F.col("m"), F.lit(y), F.lit(lo), F.lit(hi))).first()[0]
    assert ask(0, 5, 5) is None and ask(1, 5, 5) == "outside" and ask(0, 1, 1) == "order"


def mined(df):
    return {(r["code"], r["support"], r["tree_support"]) for r in df.collect()}


def test_plans_and_baselines_find_the_same_patterns(forest):
    base = mined(mine.embedded(forest, 12, 4))
    assert {(c, s) for c, s, _ in base} == set(mine.embedded_reference(forest, 12, 3)) | {(c, s) for c, s, _ in base if c.count(" ") == 3}
    assert base == mined(mine.embedded(forest, 12, 4, plan="packed"))
    assert base == mined(mine.embedded(forest, 12, 4, plan="cumulative"))
    assert base == mined(mine.embedded(forest, 12, 4, plan="local", merge="literal"))
    assert base == mined(mine.embedded(forest, 12, 4, schedule="classes"))
    assert base == mined(baselines.full_match(forest, 12, 4)) == mined(baselines.horizontal(forest, 12, 4))


def test_binned_plan_checkpoint_and_store(spark, forest, tmp_path, monkeypatch):
    monkeypatch.setattr(mine, "BIN", 2)
    base = mined(mine.embedded(forest, 12, 3))
    assert base == mined(mine.embedded(forest, 12, 3, plan="binned"))
    folder = str(tmp_path / "levels")
    mine.embedded(forest, 12, 3, checkpoint=folder)
    assert base == mined(mine.embedded(forest, 12, 3, checkpoint=folder))
    store.save(forest, str(tmp_path / "store"), 3)
    assert sorted(map(str, store.load(spark, str(tmp_path / "store")).collect())) == sorted(map(str, forest.select("tree_id", "lo", "hi", "depth", "label").collect()))
    assert {r["label"] for r in store.load(spark, str(tmp_path / "store"), ["b"]).collect()} == {"b"}


def test_rules_nest_and_tree_support_makes_them_equal(forest):
    by = {rule: mined(mine.embedded(forest, 12, 4, rule=rule)) for rule in ("prefix", "class", "all")}
    assert by["all"] <= by["class"] <= by["prefix"]
    assert by["all"] == mined(baselines.model_guided(forest, 12, 4))
    tree = {rule: mined(mine.embedded(forest, 5, 3, rule=rule, support="tree")) for rule in ("prefix", "class", "all")}
    assert tree["all"] == tree["class"] == tree["prefix"]
    assert {(c, t) for c, _, t in tree["prefix"]} == {(c, t) for c, _, t in mined(baselines.rightmost_set(forest, 5, 3))}


def test_support_is_not_anti_monotone(spark):
    one = generator.literal_forest(spark, ["a(b,b)"])
    assert ("a@0 b@1", 2, 1) in mined(mine.embedded(one, 2, 2, rule="none")) and not any(c == "a@0" for c, _, _ in mined(mine.embedded(one, 2, 2, rule="none")))
    assert mined(mine.embedded(one, 2, 2)) == {("b@0", 2, 1)}


@pytest.mark.parametrize(("tree", "code", "n"), [("a(x(b),y(c))", "a@0 b@1 c@1", 1), ("a(c,b)", "a@0 b@1 c@1", 0), ("a(b(c))", "a@0 b@1 c@1", 0), ("a(b(c))", "a@0 b@1 c@2", 1)])
def test_micro_forests(spark, tree, code, n):
    assert (match.records(generator.literal_forest(spark, [tree]), code).agg(F.sum("mult")).first()[0] or 0) == n


def test_star_and_chain_sizes(spark):
    star = match.records(generator.star(spark, 9), " ".join(["a@0"] + ["b@1"] * 4)).collect()
    assert {r["lo"]: r["mult"] for r in star} == {i: math.comb(i - 1, 3) for i in range(4, 9)}
    chain = " ".join(f"a@{i}" for i in range(6))
    for merge in ("canonical", "literal"):
        r = match.records(generator.chain(spark, 12), chain, merge)
        assert (r.agg(F.sum("mult")).first()[0], r.count()) == measures.chain_size(12, 6, merge)


def test_isomorphic_and_homomorphic_counts(spark):
    v = generator.literal_forest(spark, ["a(b,x(b),b)"])
    total = lambda df: df.agg(F.sum("n_occ")).first()[0] or 0
    assert total(match.count_per_tree(v, "a@0 b@1")) == 3
    assert total(match.count_isomorphic(v, "a@0 b@1")) == 2
    assert total(match.count_isomorphic(v, "a@0 b@1 b@1")) == 1
    assert total(match.count_homomorphic(v, "a@0 b@1 b@1")) == 3


def test_text_and_adjacency_encoders(spark, forest):
    lines = codec.encode_lines(forest)
    cols = ["tree_id", "lo", "hi", "depth", "label"]
    assert sorted(map(str, codec.decode_lines(lines).select(cols).collect())) == sorted(map(str, forest.select(cols).collect()))
    nodes = relations.parents(forest).select("tree_id", F.col("lo").cast("long").alias("id"), F.col("parent_lo").cast("long").alias("parent"), F.col("lo").alias("ordinal"), "label")
    assert sorted(map(str, encode.from_adjacency(nodes).select(cols).collect())) == sorted(map(str, forest.select(cols).collect()))
    assert sorted(map(str, encode.unpack(encode.pack(forest)).select(cols).collect())) == sorted(map(str, forest.select(cols).collect()))


def test_nested_column(spark):
    df = spark.sql("SELECT 1L AS k, named_struct('a', 1, 'b', array(named_struct('c', 2), named_struct('c', CAST(NULL AS INT)))) AS doc")
    got = [(r["lo"], r["hi"], r["depth"], r["label"]) for r in nested.from_nested(df, "k", "doc").orderBy("lo").collect()]
    assert got == [(0, 5, 0, "doc"), (1, 1, 1, "a"), (2, 5, 1, "b"), (3, 4, 2, "item"), (4, 4, 3, "c"), (5, 5, 2, "item")]


def test_maximal_and_closed(forest):
    p = mine.embedded(forest, 12, 3, rule="all").persist()
    codes = {r["code"]: r["support"] for r in p.collect()}
    inner = {pt.code(s): codes[c] for c in codes for s in pt.one_removed(pt.parse(c))}
    assert {r["code"] for r in post.maximal(p).collect()} == set(codes) - set(inner)
    same = {pt.code(s) for c in codes for s in pt.one_removed(pt.parse(c)) if codes.get(pt.code(s)) == codes[c]}
    assert {r["code"] for r in post.closed(p).collect()} == set(codes) - same


def test_decimal_counts_and_overflow(spark):
    n = 68
    v = generator.chain(spark, n)
    p = mine.embedded(v, 1, 3, exact_counts="decimal")
    assert {int(r["support"]) for r in p.collect()} >= {math.comb(n, 1), math.comb(n, 2), math.comb(n, 3)}


def test_merging_needs_no_exchange(forest):
    plan = joins.attach(joins.pairs_by_join(joins.singletons(forest.repartition(4, "tree_id")), forest.repartition(4, "tree_id")))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan
    assert plan.count("Exchange hashpartitioning") <= 2


def test_empty_forest(spark):
    v = generator.literal_forest(spark, ["a"]).filter("false")
    assert mine.embedded(v, 1, 3).count() == 0
    assert match.count_per_tree(v, "a@0 b@1").count() == 0


def test_a_checkpoint_belongs_to_one_call(spark, forest, tmp_path):
    folder = f"file://{tmp_path}/run"
    brief = lambda df: sorted((r["code"], r["support"]) for r in df.collect())
    whole = brief(mine.embedded(forest, 6, 3))
    assert brief(mine.embedded(forest, 6, 3, checkpoint=folder)) == whole
    assert brief(mine.embedded(forest, 6, 3, checkpoint=folder)) == whole  # goes on from the last level
    for other in ({"minsup": 3}, {"rule": "class"}, {"support": "tree"}):
        with pytest.raises(ValueError, match="another run"):
            mine.embedded(forest, **{"minsup": 6, "max_size": 3, **other, "checkpoint": folder})
    with pytest.raises(ValueError, match="another run"):
        mine.embedded(forest.filter("tree_id > 0"), 6, 3, checkpoint=folder)


@pytest.mark.parametrize("rule", ["prefix", "class", "all"])
@pytest.mark.parametrize("support", ["occurrence", "tree"])
def test_spread_trees_give_the_same_patterns(forest, rule, support):
    brief = lambda df: sorted((r["code"], r["support"], r["tree_support"]) for r in df.collect())
    assert brief(mine.embedded(forest, 6, 4, rule, support, spread=5)) == brief(mine.embedded(forest, 6, 4, rule, support))


def test_rules_differ_where_they_should_and_guided_agrees(spark):
    v = generator.literal_forest(spark, ["a(b,b,b,c(d))", "a(b,b,c)", "c(d,d)", "c", "d(a)"])
    found = {rule: {r["code"] for r in mine.embedded(v, 3, 3, rule=rule).collect()} for rule in ("prefix", "class", "all")}
    assert found["prefix"] > found["class"] >= found["all"] and "a@0 b@1 c@1" in found["prefix"] - found["class"]
    assert {r["code"] for r in baselines.model_guided(v, 3, 3).collect()} == found["all"]
    wanted = set(found["prefix"])
    allowed = {c for c in wanted if len(c.split(" ")) < 3 or all(pt.code(x) in wanted for x in pt.one_removed(pt.parse(c)))}
    assert found["all"] == allowed


def test_trace_tells_records_occurrences_and_phases(forest):
    trace = mine.Trace()
    patterns = mine.embedded(forest, 6, 3, trace=trace).collect()
    for level in trace.levels:
        own = [r for r in patterns if r["size"] == level["size"]]
        assert level["frequent"] == len(own) <= level["met"] <= level["generated"]
        assert level["occurrences"] == sum(r["support"] for r in own) >= level["frequent_records"] == sum(r["n_records"] for r in own)
        assert level["state_bytes"] > 0 and level["generation_s"] >= 0 and level["counting_s"] >= 0


def test_null_labels_and_empty_forests(spark, forest):
    more = forest.union(spark.createDataFrame([(3, 0, 0, 0, None), (None, 0, 0, 0, "a")], generator.SCHEMA))
    brief = lambda df: sorted((r["code"], r["support"]) for r in df.collect())
    assert brief(mine.embedded(more, 6, 3)) == brief(mine.embedded(forest, 6, 3))
    assert mine.embedded(forest.filter("false"), 1).count() == 0
    assert post.features(forest, []).count() == 0


def test_master_has_all_its_vertices_and_depths(spark):
    for vertices, depth, fan_out in ((10_000, 10, 10), (10_000, 5, 10), (300, 4, 5), (5, 1, 10)):
        rows = generator.master(spark, 20, vertices, depth, fan_out).collect()
        assert len(rows) == vertices and {r["depth"] for r in rows} == set(range(depth + 1))
        ids = {r["id"]: r for r in rows}
        assert len(ids) == vertices and all(r["depth"] == 0 or ids[r["parent"]]["depth"] == r["depth"] - 1 for r in rows)
        places = [(r["parent"], r["slot"]) for r in rows if r["depth"]]
        assert len(set(places)) == len(places) and all(0 <= s < fan_out for _, s in places)


def test_navigation_and_class_patterns(spark, forest):
    when = forest.select("tree_id").distinct().withColumn("period", F.when(F.col("tree_id") < 12, "x").otherwise("y"))
    got = {(r["code"], r["period"]): r["support"] for r in post.navigation(forest, when, 8, 3).collect()}
    for r in mine.embedded(forest, 8, 3).filter("size > 1").collect():
        assert r["support"] == sum(n for (code, _), n in got.items() if code == r["code"])
    classes = when.select("tree_id", F.col("period").alias("class"))
    codes = post.class_patterns(forest, classes, (1, 2), 2)
    wanted = set()
    for c in "xy":
        own = forest.join(classes.filter(F.col("class") == c), "tree_id").select(*forest.columns)
        wanted |= {r["code"] for r in mine.embedded(own, mine.threshold(own, 1, 2), 2).collect()}
    assert codes == sorted(wanted)


def test_a_timed_run_is_stopped(spark):
    slow = lambda: spark.range(8).selectExpr("java_method('java.lang.Thread', 'sleep', 20000L)")
    got = measures.timed(slow, cap=1.0, spark=spark)
    assert got["status"] == "cap" and got["seconds"] < 15
    assert measures.timed(lambda: spark.range(3), cap=60.0, spark=spark)["status"] == "ok"


def test_pattern_sinks_round_trip(spark, forest, tmp_path):
    p = mine.embedded(forest, 6, 3).select("code", "support", "tree_support", "size")
    wanted = sorted(tuple(r) for r in p.collect())
    for kind in ("parquet", "orc", "json", "csv"):
        store.save_patterns(p, str(tmp_path / kind), kind)
        assert sorted(tuple(r) for r in store.load_patterns(spark, str(tmp_path / kind), kind, p.schema).select(*p.columns).collect()) == wanted
    store.save_records(match.records(forest, "a@0 b@1"), str(tmp_path / "records"), "csv")
    assert spark.read.option("header", True).csv(str(tmp_path / "records")).count() == match.records(forest, "a@0 b@1").count()


def test_forest_text_source(spark, tmp_path):
    from forestmine.sources import datasource

    datasource.register(spark)
    (tmp_path / "a.txt").write_text("a b -1 c d -1 -1\n\nx\n")
    (tmp_path / "b.txt").write_text("a b c\n")
    rows = spark.read.format("forest_text").load(str(tmp_path)).collect()
    trees = {}
    for r in sorted(rows):
        trees.setdefault(r["tree_id"], []).append((r["lo"], r["hi"], r["depth"], r["label"]))
    same = {}
    for r in codec.read_trees(spark, str(tmp_path)).orderBy("tree_id", "lo").collect():
        same.setdefault(r["tree_id"], []).append((r["lo"], r["hi"], r["depth"], r["label"]))
    assert sorted(trees.values()) == sorted(same.values()) and len(trees) == 3


def test_counted_plan_equals_kept_records(spark, forest):
    """Whatever the rule, the support and the spread, vertices counted tree by tree give the same patterns as kept records."""
    deep = generator.literal_forest(spark, ["a(a(a(b,a(b)),b),a)", "b(a(a(c)),c)", "c"])
    found = lambda df: sorted((r["code"], r["support"], r["tree_support"]) for r in df.collect())
    for v, minsup, k, options in ((forest, 6, 4, {"rule": "prefix"}), (forest, 6, 4, {"rule": "class"}), (forest, 6, 4, {"rule": "all", "support": "tree"}), (deep, 2, None, {"rule": "prefix"})):
        want = found(mine.embedded(v, minsup, k, **options))
        assert found(mine.embedded(v, minsup, k, plan="counted", **options)) == want
        assert found(mine.embedded(v, minsup, k, plan="counted", spread=3, **options)) == want
    full, counted = (baselines.full_match(forest, 6, 4, plan=plan).orderBy("code").collect() for plan in ("join", "counted"))
    assert [(r["code"], r["support"], r["n_records"]) for r in full] == [(r["code"], r["support"], r["n_records"]) for r in counted]
    assert found(baselines.model_guided(forest, 6, 3, plan="counted")) == found(baselines.model_guided(forest, 6, 3))
    assert mine.embedded(forest.filter("false"), 1, 3, plan="counted").count() == 0
    with pytest.raises(ValueError):
        mine.embedded(forest, 6, 3, plan="counted", rule="none")


def test_counted_kernel_in_small_pieces(forest, monkeypatch):
    import pyarrow as pa

    from forestmine.plans import counted

    rows = sorted((r["tree_id"], r["lo"], r["hi"], "ab".index(r["label"])) for r in forest.collect())
    batches = lambda n: iter([pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows[i : i + n])], names=list("tlhx")) for i in range(0, len(rows), n)])

    def tallies(n, by_tree):
        step = counted.Lookup(np.arange(4), np.arange(4), 4)
        out = {}
        for b in counted._kernel(np.arange(2), [step], [2, 4], 2, None, False, by_tree)(batches(n)):
            for code, _, support, trees, pairs in zip(*(c.to_pylist() for c in b.columns)):
                out[code] = tuple(a + b for a, b in zip(out.get(code, (0, 0, 0)), (support, trees, pairs)))
        return out

    whole = tallies(10_000, 1)
    assert whole
    for chunk, pairs, dense in ((1, 1, 1 << 23), (7, 5, 1), (40, 3, 1 << 23), (10_000, 4, 1)):
        for name, value in (("CHUNK", chunk), ("PAIRS", pairs), ("DENSE", dense)):
            monkeypatch.setattr(counted, name, value)
        got = tallies(9, 1)
        assert {c: x[:2] for c, x in got.items()} == {c: x[:2] for c, x in whole.items()}
    with pytest.raises(ArithmeticError):
        counted._safe(np.full(3, 4_000_000_000_000_000_000))


def test_counted_reads_a_large_tree_in_linear_time(spark):
    """One root over 60,000 vertices: joins by tree would compare 3.6 billion pairs of them."""
    import time

    i = F.col("id").cast("int")
    v = spark.range(60_001).select(F.lit(0).cast("long").alias("tree_id"), i.alias("lo"), F.when(i == 0, 60_000).otherwise(i).cast("int").alias("hi"), (i > 0).cast("int").alias("depth"), F.when(i == 0, "a").otherwise("b").alias("label"))
    began = time.time()
    assert {r["code"]: r["support"] for r in mine.embedded(v, 1, 2, plan="counted").collect()} == {"a@0": 1, "b@0": 60_000, "a@0 b@1": 60_000}
    assert time.time() - began < 60


def test_neighbours_of_many_equal_trees(spark):
    """Against a plain version; 40,000 trees of three pattern sets, of which all pairs would be 160 million for 4,000 queries."""
    rng = random.Random(2)
    sets = {i: frozenset(x for x in "pqrst" if rng.random() < 0.5) or frozenset("p") for i in range(60)}
    f = spark.createDataFrame([(i, x, 1) for i, s in sets.items() for x in s], "tree_id long, code string, n_occ long")
    want = []
    for q in range(0, 60, 4):
        near = sorted((-len(sets[q] & s) / len(sets[q] | s), i, len(sets[q] & s), len(sets[q] | s)) for i, s in sets.items() if i != q and sets[q] & s)
        want += [(q, i, common, union, r + 1) for r, (_, i, common, union) in enumerate(near[:3])]
    assert sorted(tuple(r) for r in post.jaccard_neighbours(f, f.filter("tree_id % 4 = 0").select("tree_id"), 3).collect()) == sorted(want)
    many = spark.range(40_000).select(F.col("id").alias("tree_id"), F.explode(F.when(F.col("id") % 3 == 0, F.array(F.lit("p"))).when(F.col("id") % 3 == 1, F.array(F.lit("p"), F.lit("q"))).otherwise(F.array(F.lit("q")))).alias("code"))
    near = post.jaccard_neighbours(many, many.filter("tree_id % 10 = 0").select("tree_id"), 5)
    assert near.count() == 20_000
    assert [tuple(r) for r in near.filter("query_id = 10").orderBy("rank").collect()] == [(10, t, 2, 2, r + 1) for r, t in enumerate((1, 4, 7, 13, 16))]


def test_master_tree_of_rows_gives_each_row_a_place(spark):
    """Few rows, keys below zero, repeated and missing ones, and more rows than ten children a vertex have room for."""
    for n, depth in ((0, 3), (1, 3), (5, 10), (3_000, 3), (500, 0)):
        keys = spark.range(n).select((F.col("id") * 1000 - 70_000).alias("key")).union(spark.createDataFrame([(None,)], "key long"))
        got = generator.master_of(keys, 20, depth, 10).collect()
        assert sorted(r["id"] for r in got) == list(range(n))
        by = {r["id"]: r for r in got}
        if depth:
            assert all((r["parent"] is None) == (r["id"] == 0) for r in got)
            assert all(by[r["parent"]]["depth"] == r["depth"] - 1 for r in got if r["id"])
            assert len({(r["parent"], r["slot"]) for r in got}) == n
