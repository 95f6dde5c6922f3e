"""Counting given patterns: a fold of record joins along the pattern's preorder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import pattern as pt
from ..functions.relations import parents
from . import joins


def _labelled(v: DataFrame, label: str) -> DataFrame:
    return v.filter(F.col("label") == pt.unescape(label))


def records(v: DataFrame, code: str, merge: str = "canonical") -> DataFrame:
    """Records of a pattern: leaf joins under the last vertex, inner joins above it."""
    nodes = pt.parse(code)
    r = joins.singletons(_labelled(v, nodes[0][0]))
    for (_, last), (label, depth) in zip(nodes, nodes[1:]):
        x = _labelled(v, label)
        r = joins.leaf(r, x, merged=merge == "canonical") if depth == last + 1 else joins.inner(r, x, depth - 1)
    return r


def count_per_tree(v: DataFrame, code: str) -> DataFrame:
    """(tree_id, n_occ) of trees with an occurrence."""
    return records(v, code).groupBy("tree_id").agg(F.sum("mult").alias("n_occ"))


def occurs(v: DataFrame, code: str) -> DataFrame:
    """tree_id of trees in which the pattern occurs."""
    return count_per_tree(v, code).select("tree_id")


def full_matches(v: DataFrame, code: str) -> DataFrame:
    """One row an occurrence: tree_id and matched, the (lo, hi) of every vertex in pattern preorder."""
    nodes = pt.parse(code)
    r = _labelled(v, nodes[0][0]).select("tree_id", F.array(F.struct("lo", "hi")).alias("matched"))
    for i in range(1, len(nodes)):
        path = pt.rightmost_path(nodes[:i])
        c = nodes[i][1] - 1
        x = _labelled(v, nodes[i][0]).select(F.col("tree_id").alias("t"), F.col("lo").alias("x_lo"), F.col("hi").alias("x_hi"))
        above, ok = F.col("matched")[path[c]], F.col("x_lo") > F.col("matched")[i - 1]["lo"]
        ok = ok & (F.col("x_lo") > above["lo"]) & (F.col("x_hi") <= above["hi"])
        if c + 1 < len(path):
            ok = ok & (F.col("x_lo") > F.col("matched")[path[c + 1]]["hi"])
        r = r.join(x, (F.col("tree_id") == F.col("t")) & ok).select("tree_id", F.concat("matched", F.array(F.struct(F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi")))).alias("matched"))
    return r


def occurrence_trees(v: DataFrame, code: str) -> DataFrame:
    """full_matches with edges: the (parent, child) vertices of each occurrence's image."""
    nodes = pt.parse(code)
    edges = [(pt.rightmost_path(nodes[: i + 1])[-2], i) for i in range(1, len(nodes))]
    pairs = [F.struct(F.col("matched")[a]["lo"].alias("parent"), F.col("matched")[b]["lo"].alias("child")) for a, b in edges]
    return full_matches(v, code).withColumn("edges", F.array(*pairs) if pairs else F.array().cast("array<struct<parent:int,child:int>>"))


def count_isomorphic(v: DataFrame, code: str) -> DataFrame:
    """(tree_id, n_occ) with pattern edges on parent-child pairs.

    Along such a path depths are consecutive, so the image's last depth tells the depth that a new vertex must have.
    """
    nodes = pt.parse(code)
    r = _labelled(v, nodes[0][0]).select("tree_id", "lo", "hi", F.array("hi").alias("rp"), F.col("depth").alias("dl"), F.lit(1).cast("long").alias("mult"))
    for (_, last), (label, depth) in zip(nodes, nodes[1:]):
        c = depth - 1
        x = _labelled(v, label).select(F.col("tree_id").alias("t"), F.col("lo").alias("x_lo"), F.col("hi").alias("x_hi"), F.col("depth").alias("x_dl"))
        ok = (F.col("x_lo") > F.col("lo")) & (F.col("x_lo") <= F.col("rp")[c]) & (F.col("x_dl") == F.col("dl") - last + c + 1)
        if c < last:
            ok = ok & (F.col("rp")[c + 1] < F.col("x_lo"))
        j = r.join(x, (F.col("tree_id") == F.col("t")) & ok)
        r = j.groupBy("tree_id", F.col("x_lo").alias("lo"), F.col("x_hi").alias("hi"), F.concat(F.slice("rp", 1, c + 1), F.array("x_hi")).alias("rp"), F.col("x_dl").alias("dl")).agg(F.sum("mult").alias("mult"))
    return r.groupBy("tree_id").agg(F.sum("mult").alias("n_occ"))


def count_homomorphic(v: DataFrame, code: str) -> DataFrame:
    """(tree_id, n_occ) with pattern edges on parent-child pairs and preorder only weakly kept: successive siblings may share an image."""
    nodes = pt.parse(code)
    own = parents(v).select("tree_id", "lo", "label", "parent_lo")
    r = _labelled(own, nodes[0][0]).select("tree_id", F.array("lo").alias("path"), F.lit(1).cast("long").alias("mult"))
    for label, depth in nodes[1:]:
        x = _labelled(own, label).select(F.col("tree_id").alias("t"), F.col("lo").alias("x_lo"), "parent_lo")
        j = r.join(x, (F.col("tree_id") == F.col("t")) & (F.col("parent_lo") == F.col("path")[depth - 1]) & (F.col("x_lo") >= F.element_at("path", -1)))
        r = j.groupBy("tree_id", F.concat(F.slice("path", 1, depth), F.array("x_lo")).alias("path")).agg(F.sum("mult").alias("mult"))
    return r.groupBy("tree_id").agg(F.sum("mult").alias("n_occ"))


def brute_force(v: DataFrame, code: str) -> DataFrame:
    """(tree_id, n_occ) straight from the definition: a join of k copies with a condition for every pair of vertices. For tests."""
    nodes = pt.parse(code)
    out = None
    ancestors: list[tuple[int, int]] = []
    for i in range(len(nodes)):
        ancestors += [(a, i) for a in pt.rightmost_path(nodes[: i + 1])[:-1]]
    for i, (label, _) in enumerate(nodes):
        x = _labelled(v, label).select(F.col("tree_id").alias(f"t{i}"), F.col("lo").alias(f"l{i}"), F.col("hi").alias(f"h{i}"))
        if out is None:
            out = x
            continue
        ok = F.col("t0") == F.col(f"t{i}")
        for a in range(i):
            inside = (F.col(f"l{a}") < F.col(f"l{i}")) & (F.col(f"h{i}") <= F.col(f"h{a}"))
            ok = ok & (F.col(f"l{a}") < F.col(f"l{i}")) & (inside if (a, i) in ancestors else ~inside)
        out = out.join(x, ok)
    return out.groupBy(F.col("t0").alias("tree_id")).agg(F.count(F.lit(1)).alias("n_occ"))
