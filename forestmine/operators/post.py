"""After mining: maximal and closed patterns, rules, features, classifiers, rankings, cubes.

Pattern tables are small beside the data (they are results), but stay DataFrames.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import pattern as pt
from . import mine
from .match import count_per_tree


def pattern_forest(patterns: DataFrame) -> DataFrame:
    """Patterns as trees: vertices with tree_id = pattern_id, so that matching applies to them."""
    token = F.posexplode(F.split("code", " "))
    t = patterns.select(F.col("pattern_id").alias("tree_id"), token.alias("lo", "token"))
    t = t.select("tree_id", "lo", F.substring_index("token", "@", -1).cast("int").alias("depth"), F.regexp_replace("token", "@[0-9]+$", "").alias("label"))
    deepest = t.agg(F.max("depth")).first()[0] or 0
    later = Window.partitionBy("tree_id").orderBy(F.desc("lo")).rowsBetween(Window.unboundedPreceding, -1)
    end = F.lit(None).cast("int")
    for d in range(deepest + 1):
        end = F.when(F.col("depth") == d, F.min(F.when(F.col("depth") <= d, F.col("lo"))).over(later)).otherwise(end)
    last = F.max("lo").over(Window.partitionBy("tree_id"))
    return t.withColumn("hi", F.coalesce(end - 1, last)).select("tree_id", F.col("lo").cast("int"), F.col("hi").cast("int"), "depth", "label")


def sub_patterns(patterns: DataFrame) -> DataFrame:
    """(code, sub_code) for each one-vertex-removed sub-pattern: a chain of them reaches every smaller embedded pattern."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="sub_code string")
    class Removed:
        def eval(self, code: str):
            for nodes in pt.one_removed(pt.parse(code)):
                yield (pt.code(nodes),)

    patterns.sparkSession.udtf.register("one_removed", Removed)
    patterns.createOrReplaceTempView("patterns_to_shrink")
    return patterns.sparkSession.sql("SELECT p.code, s.sub_code FROM patterns_to_shrink p, LATERAL one_removed(p.code) s")


def maximal(patterns: DataFrame) -> DataFrame:
    """Patterns that no other one of the table contains. The table must hold all frequent sub-patterns (rule 'all'), or one level suffices for none."""
    inner = sub_patterns(patterns).select(F.col("sub_code").alias("code")).distinct()
    return patterns.join(inner, "code", "left_anti").select(*patterns.columns)


def closed(patterns: DataFrame) -> DataFrame:
    """Patterns without a one-larger pattern of the table that contains them and has the same support."""
    up = sub_patterns(patterns).join(patterns.select("code", "support"), "code").select(F.col("sub_code").alias("code"), "support").distinct()
    return patterns.join(up, ["code", "support"], "left_anti").select(*patterns.columns)


def rules(patterns: DataFrame) -> DataFrame:
    """(prefix_code, code, support, prefix_support): prefix => pattern; the ratio may pass 1 under per-occurrence support."""
    p = patterns.select(F.col("pattern_id").alias("prefix_id"), F.col("code").alias("prefix_code"), F.col("support").alias("prefix_support"))
    return patterns.join(p, "prefix_id").select("prefix_code", "code", "support", "prefix_support")


def top_by_size(patterns: DataFrame, k: int) -> DataFrame:
    """The k patterns of largest support of each size, ties by code: adds rank."""
    w = Window.partitionBy("size").orderBy(F.desc("support"), "code")
    return patterns.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """(code, support_a, support_b) of two results, 0 where one lacks a pattern."""
    return a.select("code", F.col("support").alias("support_a")).join(b.select("code", F.col("support").alias("support_b")), "code", "full").na.fill(0, ["support_a", "support_b"])


def features(v: DataFrame, codes: list[str]) -> DataFrame:
    """(tree_id, code, n_occ): a sparse tree by pattern table; without codes an empty one."""
    out = None if codes else v.select("tree_id", F.lit("").alias("code"), F.lit(0).cast("long").alias("n_occ")).filter("false")
    for c in codes:
        part = count_per_tree(v, c).select("tree_id", F.lit(c).alias("code"), "n_occ")
        out = part if out is None else out.unionByName(part)
    return out


def jaccard_neighbours(f: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, tree_id, common, union, rank): the k trees most alike each query tree, by the patterns that they hold.

    Trees of equal pattern sets are as alike to any other tree. So sets are compared, not trees: of a set its k + 1 smallest trees can be among
    the nearest (one may be the query itself), and a query takes the list of its set.
    """
    sets = f.groupBy("tree_id").agg(F.array_sort(F.collect_set("code")).alias("codes"))
    asked = sets.join(queries.select("tree_id").distinct(), "tree_id", "left_semi").select(F.col("tree_id").alias("query_id"), F.col("codes").alias("own"))
    least = sets.withColumn("place", F.row_number().over(Window.partitionBy("codes").orderBy("tree_id"))).filter(F.col("place") <= k + 1).drop("place")
    a = asked.select("own").distinct().select("own", F.explode("own").alias("code"))
    b = sets.select("codes").distinct().select("codes", F.explode("codes").alias("code"))
    pairs = a.join(b, "code").groupBy("own", "codes").agg(F.count(F.lit(1)).alias("common")).withColumn("union", (F.size("own") + F.size("codes")).cast("long") - F.col("common"))
    order = [F.desc(F.col("common") / F.col("union")), F.col("tree_id")]
    near = pairs.join(least, "codes").withColumn("rank", F.row_number().over(Window.partitionBy("own").orderBy(*order))).filter(F.col("rank") <= k + 1).drop("rank", "codes")
    found = asked.join(near, "own").filter("query_id <> tree_id").withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(*order)))
    return found.filter(F.col("rank") <= k).select("query_id", "tree_id", "common", "union", "rank")


def class_counts(f: DataFrame, classes: DataFrame) -> DataFrame:
    """(code, class, n_trees, n_in_class, n_with_pattern): evidence of pattern => class. classes: (tree_id, class)."""
    hit = f.join(classes, "tree_id").groupBy("code", "class").agg(F.count(F.lit(1)).alias("n_trees"))
    sizes = classes.groupBy("class").agg(F.count(F.lit(1)).alias("n_in_class"))
    return hit.join(sizes, "class").join(hit.groupBy("code").agg(F.sum("n_trees").alias("n_with_pattern")), "code").select("code", "class", "n_trees", "n_in_class", "n_with_pattern")


def classify(f: DataFrame, evidence: DataFrame) -> DataFrame:
    """(tree_id, class): each tree's vote by its most confident rule (ties: more trees, then code and class)."""
    rule = evidence.select("code", "class", (F.col("n_trees") / F.col("n_with_pattern")).alias("confidence"), "n_trees")
    best = F.max_by("class", F.struct("confidence", "n_trees", "code", "class")).alias("class")
    return f.select("tree_id", "code").join(rule, "code").groupBy("tree_id").agg(best)


def support_by(counts: DataFrame, attributes: DataFrame, dims: list[str], how: str = "cube") -> DataFrame:
    """Support of watched patterns over attributes of trees. counts: (tree_id, code, n_occ); how: 'cube', 'rollup' or 'groupBy'."""
    joined = counts.join(attributes, "tree_id")
    grouped = getattr(joined, how)("code", *dims)
    out = grouped.agg(F.sum("n_occ").alias("support"), F.count(F.lit(1)).alias("tree_support"))
    return out.filter("code is not null")


def popular(v: DataFrame, parent_prefix: str, child_prefix: str) -> DataFrame:
    """(area, publisher, support, tree_support, rank_occ, rank_tree): under each parent label, child labels ranked by both supports."""
    a, b = v.filter(F.col("label").startswith(parent_prefix)), v.filter(F.col("label").startswith(child_prefix))
    j = a.alias("a").join(b.alias("b"), (F.col("a.tree_id") == F.col("b.tree_id")) & (F.col("a.lo") < F.col("b.lo")) & (F.col("b.hi") <= F.col("a.hi")))
    s = j.groupBy(F.col("a.label").alias("area"), F.col("b.label").alias("publisher")).agg(F.count(F.lit(1)).alias("support"), F.countDistinct("a.tree_id").alias("tree_support"))
    by = lambda c: F.rank().over(Window.partitionBy("area").orderBy(F.desc(c))).cast("long")
    return s.withColumn("rank_occ", by("support")).withColumn("rank_tree", by("tree_support"))


def navigation(v: DataFrame, when: DataFrame, minsup: int, max_size: int = 3) -> DataFrame:
    """(entry, code, period, support, tree_support): frequent patterns of two vertices or more by their root's label and the trees' periods. when: (tree_id, period)."""
    codes = [r["code"] for r in mine.embedded(v, minsup, max_size).filter("size > 1").orderBy("code").select("code").collect()]
    found = features(v.persist(), codes).join(when, "tree_id")
    entry = F.regexp_replace(F.substring_index("code", " ", 1), "@0$", "")
    return found.groupBy(entry.alias("entry"), "code", "period").agg(F.sum("n_occ").alias("support"), F.count(F.lit(1)).alias("tree_support"))


def class_patterns(v: DataFrame, classes: DataFrame, share: tuple[int, int], max_size: int) -> list[str]:
    """Codes that are frequent in the trees of some class; the threshold is a share of the class's trees. classes: (tree_id, class)."""
    codes: set[str] = set()
    for c in [r["class"] for r in classes.select("class").distinct().orderBy("class").collect()]:
        own = v.join(classes.filter(F.col("class") == c).select("tree_id").distinct(), "tree_id", "left_semi").select(*v.columns).persist()
        codes |= {r["code"] for r in mine.embedded(own, mine.threshold(own, *share), max_size).select("code").collect()}
        own.unpersist()
    return sorted(codes)
