"""Registered queries over the given tables, and their SQL."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles, pattern
from .functions import relations
from .operators import baselines, joins, match, measures, mine, post
from .sources import generator, nested, tables

Query = Callable[[SparkSession, str], DataFrame]

_found: dict[str, tuple[Query, str | None]] = {}


def _add(name: str, query: Query, sql: str | None) -> None:
    _found[name] = (query, sql)


def _minsup(v: DataFrame, minsup: int | tuple[int, int]) -> int:
    return minsup if isinstance(minsup, int) else mine.threshold(v, *minsup)


def _brief(p: DataFrame) -> DataFrame:
    return p.select(F.col("size").cast("long").alias("size"), "code", "support", "tree_support")


def _miner(forest: Query, minsup, run: Callable[[DataFrame, int], DataFrame]) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = forest(spark, sf_dir).persist()
        try:
            return _brief(run(v, _minsup(v, minsup)))
        finally:
            v.unpersist()

    return query


def _of(forest: Query, f: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, sf_dir: f(forest(spark, sf_dir))


#: Forest, largest size, threshold (a number, or a share of the number of trees).
MINED = {
    "orders_k3": ("orders", 3, (2, 15)), "conversations_k4": ("conversations", 4, (1, 2)), "sessions_k3": ("sessions_rank", 3, (82, 100)), "sessions_value_k3": ("sessions_value", 3, (82, 100)), "pages_k3": ("pages_flat", 3, (1, 1)),
    "customers_k2": ("customers", 2, (1, 1)), "regions_k2": ("regions", 2, (1, 1)), "library_k2": ("library", 2, (1, 1)), "outlines_k3": ("outlines", 3, (1, 1)),
}


#: The same for workloads in which the candidate rules differ, and baselines have many occurrences for each record.
RULES = {"customers_k3": ("customers", 3, (1, 2)), "users_k3": ("users", 3, (5, 1)), "library_k3": ("library", 3, (1, 1))}

#: Forests of which kept records outgrow disks or joins by tree take too long; the miners count these tree by tree.
COUNTED_FORESTS = ("library", "regions")


def _plan(forest: str) -> str:
    return "counted" if forest in COUNTED_FORESTS else "join"


def _forests() -> None:
    for name, f in tables.FORESTS.items():
        _add(f"forest_{name}", f, oracles.forest(name))
        _add(f"forest_stats_{name}", _of(f, measures.forest_stats), oracles.stats(name))


def _relations() -> None:
    c, sql = tables.conversations, oracles.forest("conversations")
    pairs = "WITH v AS MATERIALIZED ({}) SELECT a.tree_id, a.lo AS a_lo, b.lo AS b_lo FROM v a JOIN v b ON a.tree_id = b.tree_id AND {}"
    _add("ancestor_pairs_conversations", _of(c, relations.ancestor_pairs), pairs.format(sql, "a.lo < b.lo AND b.lo <= a.hi"))
    _add("right_relative_pairs_conversations", _of(c, relations.right_relative_pairs), pairs.format(sql, "a.hi < b.lo"))
    _add("parents_orders", _of(tables.orders, lambda v: relations.parents(v).select("tree_id", "lo", "parent_lo")), f"WITH v AS MATERIALIZED ({oracles.forest('orders')}) SELECT b.tree_id, b.lo, max(a.lo) AS parent_lo FROM v b LEFT JOIN v a ON a.tree_id = b.tree_id AND a.lo < b.lo AND b.lo <= a.hi GROUP BY b.tree_id, b.lo")
    _add("rightmost_paths_conversations", _of(c, lambda v: relations.rightmost_paths(v).select("tree_id", "lo", F.col("rdepth").cast("long").alias("rdepth"))), f"WITH v AS MATERIALIZED ({sql}), n AS (SELECT tree_id, max(hi) AS last FROM v GROUP BY tree_id) SELECT tree_id, lo, row_number() OVER (PARTITION BY tree_id ORDER BY lo) - 1 AS rdepth FROM v JOIN n USING (tree_id) WHERE hi = last")
    _add("path_label_repeats_sessions_value", _of(tables.sessions_value, measures.path_label_repeats), f"WITH v AS MATERIALIZED ({oracles.forest('sessions_value')}) SELECT DISTINCT a.tree_id FROM v a JOIN v b ON a.tree_id = b.tree_id AND a.label = b.label AND a.lo < b.lo AND b.lo <= a.hi")


def _joins() -> None:
    text = lambda r: r.select("tree_id", F.col("lo").cast("long").alias("lo"), F.col("hi").cast("long").alias("hi"), F.array_join("rp", ",").alias("rp"), "mult")
    v = f"WITH v AS MATERIALIZED ({oracles.forest('orders')}), "
    pick = lambda v, p: v.filter(F.col("label").startswith(p))
    _add("leaf_join_orders", _of(tables.orders, lambda v: text(joins.leaf(joins.singletons(pick(v, "O:F")), pick(v, "F:R")))), v + "r AS (SELECT * FROM v WHERE label LIKE 'O:F%') SELECT r.tree_id, CAST(x.lo AS BIGINT) AS lo, CAST(x.hi AS BIGINT) AS hi, r.hi || ',' || x.hi AS rp, count(*) AS mult FROM r JOIN v x ON x.tree_id = r.tree_id AND x.lo > r.lo AND x.hi <= r.hi WHERE x.label LIKE 'F:R%' GROUP BY ALL")
    fork = v + "r AS (SELECT * FROM v WHERE label LIKE 'O:F%'), y AS (SELECT * FROM v WHERE label LIKE 'F:R%') SELECT r.tree_id, CAST(x.lo AS BIGINT) AS lo, CAST(x.hi AS BIGINT) AS hi, r.hi || ',' || x.hi AS rp, count(*) AS mult FROM r JOIN y ON y.tree_id = r.tree_id AND y.lo > r.lo AND y.hi <= r.hi JOIN y x ON x.tree_id = r.tree_id AND x.lo > y.hi AND x.hi <= r.hi GROUP BY ALL"
    two = lambda v: joins.leaf(joins.singletons(pick(v, "O:F")), pick(v, "F:R"))
    _add("inner_join_orders", _of(tables.orders, lambda v: text(joins.inner(two(v), pick(v, "F:R"), 0))), fork)
    _add("inner_join_sorted_orders", _of(tables.orders, lambda v: text(joins.inner_sorted(two(v), pick(v, "F:R"), 0))), fork)
    _add("inner_join_cumulative_orders", _of(tables.orders, lambda v: text(joins.inner_cumulative(two(v), pick(v, "F:R"), 0))), fork)

    def conv_records(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = tables.conversations(spark, sf_dir).persist()
        out = None
        for r in mine.embedded(v, mine.threshold(v, 1, 2), 3).collect():
            part = match.records(v, r["code"]).select(F.lit(r["code"]).alias("code"), "tree_id", F.col("lo").cast("long").alias("lo"), F.col("hi").cast("long").alias("hi"), F.array_join("rp", ",").alias("rp"), "mult")
            out = part if out is None else out.union(part)
        return out

    _add("records_conv_k3", conv_records, oracles.records_of(oracles.forest("conversations"), (1, 2), 3))


#: Fixed patterns for counting, by forest.
COUNTED = {
    "count_chain3_orders": ("orders", "O:F@0 F:R@1 T:PROMO@2"), "count_fork3_orders": ("orders", "O:F@0 F:R@1 F:A@1"), "count_chain3_conversations": ("conversations", "conv@0 user@1 assistant@2"),
    "count_fork3_conversations": ("conversations", "conv@0 user@1 user@1"), "count_size4_conversations": ("conversations", "conv@0 user@1 assistant@2 user@1"), "count_fork3_sessions": ("sessions_rank", "session@0 view@1 purchase@2"), "count_fork3_pages": ("pages_flat", "body@0 p@1 p@1"),
}


def _counts() -> None:
    for name, (forest, code) in COUNTED.items():
        _add(name, _of(tables.FORESTS[forest], lambda v, code=code: match.count_per_tree(v, code)), oracles.count_pattern(oracles.forest(forest), code))
        for kind, f in (("iso", match.count_isomorphic), ("homo", match.count_homomorphic)):
            sql = oracles.count_pattern(oracles.forest(forest), code, {"iso": "isomorphic", "homo": "homomorphic"}[kind])
            _add(name.replace("count_", f"{kind}_count_"), _of(tables.FORESTS[forest], lambda v, code=code, f=f: f(v, code)), sql)
    code = COUNTED["count_size4_conversations"][1]
    _add("brute_force_conversations", _of(tables.conversations, lambda v: match.brute_force(v, code)), oracles.count_pattern(oracles.forest("conversations"), code))
    _add("occurs_conversations", _of(tables.conversations, lambda v: match.occurs(v, code)), f"SELECT tree_id FROM ({oracles.count_pattern(oracles.forest('conversations'), code)})")
    sizes = f"SELECT count(*) AS n_records, CAST(sum(m) AS BIGINT) AS n_occurrences, CAST(sum(m) AS BIGINT) AS n_full FROM ({oracles.occurrences(oracles.forest('conversations'), 1, 3)} SELECT tree_id, lo, hi, rp, count(*) AS m FROM o3 WHERE code = 'conv@0 user@1 user@1' GROUP BY ALL)"
    _add("record_compression_conversations", _of(tables.conversations, lambda v: measures.compare_sizes(v, "conv@0 user@1 user@1")), sizes)


def _mining() -> None:
    for name, (forest, k, minsup) in MINED.items():
        f, sql = tables.FORESTS[forest], oracles.forest(forest)
        _add(f"mine_{name}", _miner(f, minsup, lambda v, m, k=k, plan=_plan(forest): mine.embedded(v, m, k, plan=plan)), oracles.mine(sql, minsup, k))
    for name in ("orders_k3", "conversations_k3", "sessions_k3"):
        forest, k, minsup = MINED.get(name, ("conversations", 3, (1, 2)))
        f, sql = tables.FORESTS[forest], oracles.forest(forest)
        own = oracles.mine(sql, minsup, k)
        for rule in ("class", "all"):
            _add(f"mine_{name}_{rule}", _miner(f, minsup, lambda v, m, k=k, rule=rule: mine.embedded(v, m, k, rule=rule)), oracles.mine(sql, minsup, k, rule))
        by_tree = oracles.mine(sql, minsup, k, support="tree")
        _add(f"mine_tree_support_{name}", _miner(f, minsup, lambda v, m, k=k: mine.embedded(v, m, k, support="tree")), by_tree)
        _add(f"baseline_full_match_{name}", _miner(f, minsup, lambda v, m, k=k: baselines.full_match(v, m, k)), own)
        _add(f"baseline_model_guided_{name}", _miner(f, minsup, lambda v, m, k=k: baselines.model_guided(v, m, k)), oracles.mine(sql, minsup, k, "all"))
        _add(f"baseline_rightmost_set_{name}", _miner(f, minsup, lambda v, m, k=k: baselines.rightmost_set(v, m, k)), f"SELECT size, code, tree_support AS support, tree_support FROM ({by_tree})")
    c, sql = tables.conversations, oracles.mine(oracles.forest("conversations"), (1, 2), 3)
    _add("baseline_horizontal_conversations_k3", _miner(c, (1, 2), lambda v, m: baselines.horizontal(v, m, 3)), sql)
    for plan in ("packed", "binned", "cumulative", "local"):
        _add(f"mine_conversations_k3_{plan}", _miner(c, (1, 2), lambda v, m, plan=plan: mine.embedded(v, m, 3, plan=plan)), sql)
    _add("mine_conversations_k3_literal", _miner(c, (1, 2), lambda v, m: mine.embedded(v, m, 3, merge="literal")), sql)
    _add("mine_conversations_k3_classes", _miner(c, (1, 2), lambda v, m: mine.embedded(v, m, 3, schedule="classes")), sql)
    _add("mine_conversations_k3_decimal", _miner(c, (1, 2), lambda v, m: mine.embedded(v, m, 3, exact_counts="decimal").withColumn("support", F.col("support").cast("long"))), sql)
    for name, (forest, k, minsup) in RULES.items():
        f, sql = tables.FORESTS[forest], oracles.forest(forest)
        for rule in ("prefix", "class", "all"):
            _add(f"mine_{name}_{rule}", _miner(f, minsup, lambda v, m, k=k, rule=rule, plan=_plan(forest): mine.embedded(v, m, k, rule=rule, plan=plan)), oracles.mine(sql, minsup, k, rule))
        _add(f"baseline_full_match_{name}", _miner(f, minsup, lambda v, m, k=k, plan=_plan(forest): baselines.full_match(v, m, k, plan=plan)), oracles.mine(sql, minsup, k))
        _add(f"baseline_model_guided_{name}", _miner(f, minsup, lambda v, m, k=k, plan=_plan(forest): baselines.model_guided(v, m, k, plan=plan)), oracles.mine(sql, minsup, k, "all"))
    pages = oracles.mine(oracles.forest("pages_flat"), (1, 1), 3)
    _add("baseline_full_match_pages_k3", _miner(tables.pages_flat, (1, 1), lambda v, m: baselines.full_match(v, m, 3)), pages)
    _add("baseline_model_guided_pages_k3", _miner(tables.pages_flat, (1, 1), lambda v, m: baselines.model_guided(v, m, 3)), oracles.mine(oracles.forest("pages_flat"), (1, 1), 3, "all"))
    _add("baseline_full_match_users_k4", _miner(tables.users, (5, 1), lambda v, m: baselines.full_match(v, m, 4)), oracles.mine(oracles.forest("users"), (5, 1), 4))
    _add("mine_users_k4", _miner(tables.users, (5, 1), lambda v, m: mine.embedded(v, m, 4)), oracles.mine(oracles.forest("users"), (5, 1), 4))
    regions = oracles.mine(oracles.forest("regions"), (1, 1), 2)
    _add("mine_regions_k2_spread", _miner(tables.regions, (1, 1), lambda v, m: mine.embedded(v, m, 2, spread="auto", plan="counted")), regions)
    _add("baseline_full_match_regions_k2", _miner(tables.regions, (1, 1), lambda v, m: baselines.full_match(v, m, 2, plan="counted")), regions)
    _add("mine_sessions_k5", _miner(tables.sessions_rank, (82, 100), lambda v, m: mine.embedded(v, m, 5)), None)
    _add("mine_pages_nested_k6", _miner(nested.pages_nested, (4, 1), lambda v, m: mine.embedded(v, m, 6)), None)
    _add("mine_pages_implied_k3", _miner(lambda s, d: nested.pages_nested(s, d, "implied"), (1, 1), lambda v, m: mine.embedded(v, m, 3)), None)
    _add("frequent_labels_orders", _of(tables.orders, lambda v: mine.frequent_labels(v, 1000)), f"SELECT label, count(*) AS support, count(DISTINCT tree_id) AS tree_support FROM ({oracles.forest('orders')}) GROUP BY label HAVING count(*) >= 1000")


def _literal(r: DataFrame, x: DataFrame) -> DataFrame:
    return joins.leaf(r, x, merged=False)


def _shapes() -> None:
    def sizes(forest: Query, grow: Callable[[DataFrame, DataFrame], DataFrame], first: str, more: str):
        """Records of stars or chains of 3, 4 and 5 vertices in the table's trees, by the trees' number of vertices n, which the root's bound tells."""

        def query(spark: SparkSession, sf_dir: str) -> DataFrame:
            v = forest(spark, sf_dir).repartition("tree_id").persist()
            x, out = v.filter(F.col("label") == more), None
            r = joins.singletons(v.filter(F.col("label") == first))
            for k in range(2, 6):
                r = (grow(r, x) if k > 2 else joins.leaf(r, x, merged=grow is not _literal)).persist()
                if k > 2:
                    part = r.groupBy((F.col("rp")[0] + 1).cast("long").alias("n")).agg(F.sum("mult").alias("n_occurrences"), F.count(F.lit(1)).alias("n_records"))
                    part = part.select("n", F.lit(k).cast("long").alias("k"), "n_occurrences", "n_records")
                    out = part if out is None else out.union(part)
            return out

        return query

    def grid(root: int, occurrences, records) -> str:
        trees = f"SELECT n, CAST(count(*) AS HUGEINT) AS t FROM (SELECT count(*) + {root} AS n FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL GROUP BY user_id, CAST(ts AS DATE)) GROUP BY n"
        return f"WITH t AS ({trees}) " + " UNION ALL ".join(f"SELECT n, CAST({k} AS BIGINT) AS k, CAST(t * ({occurrences(k)}) AS BIGINT) AS n_occurrences, CAST(t * ({records(k)}) AS BIGINT) AS n_records FROM t WHERE n >= {k}" for k in (3, 4, 5))

    choose = lambda n, k: f"{' * '.join(f'({n} - {i})' for i in range(k))} // {math.factorial(k)}"
    rest = lambda k: f"n - {k} + 1"
    _add("star_records", sizes(tables.day_stars, lambda r, x: joins.inner(r, x, 0), "a", "b"), grid(1, lambda k: choose("(n - 1)", k - 1), rest))
    _add("chain_records", sizes(tables.day_chains, joins.leaf, "a", "a"), grid(0, lambda k: choose("n", k), rest))
    _add("chain_records_literal", sizes(tables.day_chains, _literal, "a", "a"), grid(0, lambda k: choose("n", k), lambda k: choose("n", k)))

    def anomaly(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = generator.literal_forest(spark, ["a(b,b,c)", "a", "c"])
        out = None
        for rule in ("prefix", "class", "all"):
            p = mine.embedded(v, 2, 3, rule=rule).select(F.lit(rule).alias("rule"), "code", "support")
            out = p if out is None else out.union(p)
        return out

    rows = [(r, c, n) for r in ("prefix", "class", "all") for c, n in (("a@0", 2), ("b@0", 2), ("c@0", 2), ("a@0 b@1", 2), ("a@0 b@1 c@1", 2)) if not (r != "prefix" and c.endswith("c@1"))]
    _add("anomaly_forest", anomaly, "SELECT rule, code, CAST(support AS BIGINT) AS support FROM (VALUES " + ", ".join(f"('{r}', '{c}', {n})" for r, c, n in rows) + ") t(rule, code, support)")
    assert math.comb(8, 4) == measures.star_size(9, 5)[0]


#: Synthetic collections: labels, master's vertices, depth, fan-out; trees and per cent of children that a tree keeps.
SYNTHETIC = {"d10": (100, 10_000, 10, 10, 1000, 45), "d5": (100, 10_000, 5, 10, 1000, 20), "m": (100, 100_000, 10, 10, 1000, 36)}


def synthetic(name: str) -> Query:
    labels, vertices, depth, fan_out, trees, keep = SYNTHETIC[name]
    return lambda spark, sf_dir: generator.browsing_trees(generator.master(spark, labels, vertices, depth, fan_out), trees, keep)


#: Whose rows are the vertices of a registered master tree: table, key. The miners' collections have the vertices above.
MASTERS = {"d10": ("part", "p_partkey"), "d5": ("part", "p_partkey"), "m": ("orders", "o_orderkey")}


def master_of(name: str) -> Query:
    labels, _, depth, fan_out, _, _ = SYNTHETIC[name]
    table, key = MASTERS[name]
    return lambda spark, sf_dir: generator.master_of(spark.read.parquet(f"{sf_dir}/{table}.parquet").select(F.col(key).alias("key")), labels, depth, fan_out)


#: Trees with the most occurrences for each record: how many, of how many vertices, to which size.
SHAPES = {"stars": (50, 21, 6), "chains": (50, 16, 6)}


def shape(name: str) -> Query:
    trees, n, _ = SHAPES[name]
    return lambda spark, sf_dir: getattr(generator, name)(spark, trees, n)


def _synthetic() -> None:
    for name, (trees, n, k) in SHAPES.items():
        found = [(i, " ".join(["a@0", *["b@1"] * (i - 1)] if name == "stars" else [f"a@{j}" for j in range(i)]), trees * (math.comb(n - 1, i - 1) if name == "stars" else math.comb(n, i))) for i in range(1, k + 1)]
        found += [(1, "b@0", trees * (n - 1))] if name == "stars" else []
        sql = f"SELECT CAST(size AS BIGINT) AS size, code, CAST(support AS BIGINT) AS support, CAST({trees} AS BIGINT) AS tree_support FROM (VALUES {', '.join(f"({i}, '{c}', {m})" for i, c, m in found)}) t(size, code, support)"
        _add(f"mine_{name}_k{k}", _miner(shape(name), trees, lambda v, m, k=k: mine.embedded(v, m, k)), sql)
        _add(f"baseline_full_match_{name}_k{k}", _miner(shape(name), trees, lambda v, m, k=k: baselines.full_match(v, m, k)), sql)
        _add(f"baseline_model_guided_{name}_k{k}", _miner(shape(name), trees, lambda v, m, k=k: baselines.model_guided(v, m, k)), sql)
    for name, (labels, vertices, depth, fan_out, trees, keep) in SYNTHETIC.items():
        own = oracles.master(labels, vertices, depth, fan_out)
        sql = oracles.browsing(own, depth, trees, keep)
        table, key = MASTERS[name]
        rows = oracles.master_of(table, key, labels, depth, fan_out)
        _add(f"synthetic_master_{name}", master_of(name), rows)
        _add(f"synthetic_trees_{name}", lambda s, d, name=name, trees=trees, keep=keep: generator.browsing_trees(master_of(name)(s, d).persist(), trees, keep, small=False), oracles.browsing(rows, depth, trees, keep))
        _add(f"mine_synthetic_{name}_k3", _miner(synthetic(name), (1, 10), lambda v, m: mine.embedded(v, m, 3)), oracles.mine(sql, (1, 10), 3))
        _add(f"baseline_full_match_synthetic_{name}_k3", _miner(synthetic(name), (1, 10), lambda v, m: baselines.full_match(v, m, 3)), oracles.mine(sql, (1, 10), 3))
        _add(f"baseline_model_guided_synthetic_{name}_k3", _miner(synthetic(name), (1, 10), lambda v, m: baselines.model_guided(v, m, 3)), oracles.mine(sql, (1, 10), 3, "all"))


def _post() -> None:
    c, minsup = tables.conversations, (1, 2)
    base = oracles.mine(oracles.forest("conversations"), minsup, 3, "all")

    def mined(f):
        def query(spark: SparkSession, sf_dir: str) -> DataFrame:
            v = c(spark, sf_dir)
            return f(mine.embedded(v, mine.threshold(v, *minsup), 3, rule="all"))

        return query

    # Codes of size up to 3 that are left when one vertex goes, as SQL.
    t = "split_part(code, ' ', {})"
    label = lambda i: f"split_part({t.format(i)}, '@', 1)"
    deep = "split_part(split_part(code, ' ', 3), '@', 2)"
    gone = f"""m AS ({{}}), s AS (SELECT code, support, {t.format(1)} AS sub FROM m WHERE size = 2 UNION ALL SELECT code, support, {label(2)} || '@0' FROM m WHERE size = 2
 UNION ALL SELECT code, support, {t.format(1)} || ' ' || {t.format(2)} FROM m WHERE size = 3 UNION ALL SELECT code, support, {t.format(1)} || ' ' || {label(3)} || '@1' FROM m WHERE size = 3
 UNION ALL SELECT code, support, {label(2)} || '@0 ' || {label(3)} || '@1' FROM m WHERE size = 3 AND {deep} = '2')"""
    cte = "WITH " + gone.format(base)
    _add("maximal_conversations", mined(lambda p: _brief(post.maximal(p))), f"{cte} SELECT * FROM m WHERE code NOT IN (SELECT sub FROM s)")
    _add("closed_conversations", mined(lambda p: _brief(post.closed(p))), f"{cte} SELECT * FROM m WHERE NOT EXISTS (SELECT 1 FROM s WHERE s.sub = m.code AND s.support = m.support)")
    _add("pattern_rules_conversations", mined(post.rules), f"WITH m AS ({base}) SELECT a.code AS prefix_code, b.code, b.support, a.support AS prefix_support FROM m b JOIN m a ON a.size = b.size - 1 AND starts_with(b.code, a.code || ' ')")
    _add("topk_patterns_conversations", mined(lambda p: post.top_by_size(p, 3).select(F.col("size").cast("long").alias("size"), "code", "support", F.col("rank").cast("long").alias("rank"))), f"SELECT size, code, support, row_number() OVER (PARTITION BY size ORDER BY support DESC, code) AS rank FROM ({base}) QUALIFY rank <= 3")
    _add("pattern_counts_conversations", mined(measures.pattern_counts), f"SELECT size, count(*) AS n_patterns FROM ({base}) GROUP BY size")

    codes = ["conv@0 user@1", "conv@0 user@1 assistant@2", "conv@0 user@1 user@1"]
    feats = " UNION ALL ".join(f"SELECT tree_id, '{x}' AS code, n_occ FROM ({oracles.count_pattern(oracles.forest('conversations'), x)})" for x in codes)
    _add("pattern_features", _of(c, lambda v: post.features(v, codes)), feats)

    near = f"WITH f AS ({feats}), n AS (SELECT tree_id, count(*) AS n FROM f GROUP BY tree_id), q AS (SELECT tree_id AS query_id, code FROM f WHERE tree_id % 10 = 0), b AS (SELECT query_id, tree_id, count(*) AS common FROM q JOIN f USING (code) WHERE query_id <> tree_id GROUP BY ALL), s AS (SELECT b.*, n.n + m.n - common AS \"union\" FROM b JOIN n ON n.tree_id = b.tree_id JOIN n m ON m.tree_id = b.query_id) SELECT query_id, tree_id, common, \"union\", row_number() OVER (PARTITION BY query_id ORDER BY common / \"union\" DESC, tree_id) AS rank FROM s QUALIFY rank <= 5"

    def neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
        f = post.features(c(spark, sf_dir), codes).persist()
        found = post.jaccard_neighbours(f, f.filter("tree_id % 10 = 0").select("tree_id").distinct(), 5)
        return found.withColumn("rank", F.col("rank").cast("long"))

    _add("pattern_neighbours", neighbours, near)

    order_codes = ["O:F@0 F:R@1", "O:O@0 F:N@1", "O:F@0 F:A@1"]
    order_feats = " UNION ALL ".join(f"SELECT tree_id, '{x}' AS code, n_occ FROM ({oracles.count_pattern(oracles.forest('orders'), x)})" for x in order_codes)
    attrs = lambda s, d: s.read.parquet(f"{d}/orders.parquet").join(s.read.parquet(f"{d}/customer.parquet"), F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").alias("tree_id"), F.col("c_mktsegment").alias("segment"), F.col("o_orderpriority").alias("priority"))
    for how in ("cube", "rollup"):
        clause = f"{how}(code, segment, priority)"
        sql = f"WITH f AS ({order_feats}), a AS (SELECT o_orderkey AS tree_id, c_mktsegment AS segment, o_orderpriority AS priority FROM orders JOIN customer ON o_custkey = c_custkey) SELECT code, segment, priority, CAST(sum(n_occ) AS BIGINT) AS support, count(*) AS tree_support FROM f JOIN a USING (tree_id) GROUP BY {clause} HAVING code IS NOT NULL"
        _add(f"support_{how}_orders", lambda s, d, how=how: post.support_by(post.features(tables.orders(s, d), order_codes), attrs(s, d), ["segment", "priority"], how), sql)
    pop = f"WITH v AS MATERIALIZED ({oracles.forest('library')}), s AS (SELECT a.label AS area, b.label AS publisher, count(*) AS support, count(DISTINCT a.tree_id) AS tree_support FROM v a JOIN v b ON a.tree_id = b.tree_id AND a.lo < b.lo AND b.hi <= a.hi WHERE a.label LIKE 'T:%' AND b.label LIKE 'B:%' GROUP BY ALL) SELECT *, rank() OVER (PARTITION BY area ORDER BY support DESC) AS rank_occ, rank() OVER (PARTITION BY area ORDER BY tree_support DESC) AS rank_tree FROM s"
    _add("library_popular", _of(tables.library, lambda v: post.popular(v, "T:", "B:")), pop)

    line_codes = ["line:long@0", "line:short@0", "sent:short@0", "line:long@0 sent:long@1", "line:long@0 sent:short@1"]
    line_feats = " UNION ALL ".join(f"SELECT tree_id, '{x}' AS code, n_occ FROM ({oracles.count_pattern(oracles.forest('outlines'), x)})" for x in line_codes)
    rules = f"WITH f AS ({line_feats}), k AS (SELECT doc_id AS tree_id, quality AS class FROM labels), h AS (SELECT code, class, count(*) AS n_trees FROM f JOIN k USING (tree_id) GROUP BY ALL), z AS (SELECT class, count(*) AS n_in_class FROM k GROUP BY class) SELECT code, class, n_trees, n_in_class, CAST(sum(n_trees) OVER (PARTITION BY code) AS BIGINT) AS n_with_pattern FROM h JOIN z USING (class)"
    classes = lambda s, d: s.read.parquet(f"{d}/labels.parquet").select(F.col("doc_id").alias("tree_id"), F.col("quality").alias("class"))

    def classified(spark: SparkSession, sf_dir: str) -> DataFrame:
        v, k = tables.outlines(spark, sf_dir).persist(), classes(spark, sf_dir).persist()
        f = post.features(v, post.class_patterns(v, k, (1, 4), 2)).persist()
        return post.classify(f, post.class_counts(f, k))

    outlines = oracles.forest("outlines")
    of_class = lambda c: f"SELECT code FROM ({oracles.mine(f'SELECT * FROM ({outlines}) WHERE tree_id IN (SELECT doc_id FROM labels WHERE quality = {c})', (1, 4), 2)})"
    voted = f"""WITH p AS ({of_class(0)} UNION {of_class(1)}), f AS (SELECT * FROM ({oracles.occurrences(outlines, 1, 2)} SELECT tree_id, code, count(*) AS n_occ FROM (SELECT tree_id, code FROM o1 UNION ALL SELECT tree_id, code FROM o2) GROUP BY ALL) WHERE code IN (SELECT code FROM p)),
k AS (SELECT doc_id AS tree_id, quality AS class FROM labels), h AS (SELECT code, class, count(*) AS n_trees FROM f JOIN k USING (tree_id) GROUP BY ALL), e AS (SELECT *, n_trees / sum(n_trees) OVER (PARTITION BY code) AS confidence FROM h)
SELECT tree_id, class FROM (SELECT tree_id, class, row_number() OVER (PARTITION BY tree_id ORDER BY confidence DESC, n_trees DESC, code DESC, class DESC) AS r FROM f JOIN e USING (code)) WHERE r = 1"""
    _add("classify_documents", classified, voted)

    def navigated(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = tables.sessions_rank(spark, sf_dir).persist()
        when = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_id").alias("tree_id"), F.date_format("ts", "yyyy-MM").alias("period"))
        return post.navigation(v, when, mine.threshold(v, 82, 100), 3)

    months = "SELECT event_id AS tree_id, strftime(ts, '%Y-%m') AS period FROM events"
    _add("navigation_by_month", navigated, f"{oracles.occurrences(oracles.forest('sessions_rank'), (82, 100), 3)} SELECT split_part(code, '@', 1) AS entry, code, period, count(*) AS support, count(DISTINCT tree_id) AS tree_support FROM (SELECT tree_id, code FROM o2 UNION ALL SELECT tree_id, code FROM o3) JOIN ({months}) USING (tree_id) GROUP BY ALL")
    _add("class_rules", lambda s, d: post.class_counts(post.features(tables.outlines(s, d), line_codes), classes(s, d)), rules)


for _build in (_forests, _relations, _joins, _counts, _mining, _shapes, _synthetic, _post):
    _build()


def queries() -> dict[str, Query]:
    return {name: q for name, (q, _) in _found.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _found.items() if sql}


__all__ = ["MINED", "oracle_sql", "pattern", "queries"]
