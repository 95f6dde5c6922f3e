"""SQL surface: scalar functions and a table function that mines one class of trees at a time."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .. import pattern as pt
from ..operators.baselines import count_in_tree


class MineForest:
    """Rows of vertices of one partition in, frequent patterns (prefix rule, per-occurrence support) out. For classes that fit a task."""

    def __init__(self) -> None:
        self.trees: dict[int, list] = {}
        self.minsup, self.size = 1, 1

    def eval(self, row, minsup: int, max_size: int):
        self.trees.setdefault(row["tree_id"], []).append((row["lo"], row["hi"], row["label"]))
        self.minsup, self.size = minsup, max_size

    def terminate(self):
        trees = [sorted(t) for t in self.trees.values()]
        labels = sorted({pt.escape(x[2]) for t in trees for x in t})
        level = [((x, 0),) for x in labels]
        kept: list[str] = []
        for size in range(1, self.size + 1):
            good = []
            for nodes in level:
                n = sum(count_in_tree(t, nodes) for t in trees)
                if n >= self.minsup:
                    good.append(nodes)
                    yield pt.code(nodes), size, n
            kept = [n[0][0] for n in good] if size == 1 else kept
            level = [e for nodes in good for e in pt.extensions(nodes, kept)]


def register(spark: SparkSession) -> None:
    """is_ancestor, attach_depth, extend_rp as SQL expressions; pattern_size and pattern_depth; mine_forest as a table function."""
    for text in (
        "CREATE OR REPLACE TEMPORARY FUNCTION is_ancestor(a_lo INT, a_hi INT, b_lo INT, b_hi INT) RETURNS BOOLEAN RETURN a_lo < b_lo AND b_hi <= a_hi",
        "CREATE OR REPLACE TEMPORARY FUNCTION attach_depth(rp ARRAY<INT>, lo INT) RETURNS INT RETURN size(filter(rp, u -> u >= lo)) - 1",
        "CREATE OR REPLACE TEMPORARY FUNCTION extend_rp(rp ARRAY<INT>, c INT, hi INT) RETURNS ARRAY<INT> RETURN concat(slice(rp, 1, c + 1), array(hi))",
        "CREATE OR REPLACE TEMPORARY FUNCTION pattern_size(code STRING) RETURNS INT RETURN size(split(code, ' '))",
        "CREATE OR REPLACE TEMPORARY FUNCTION pattern_depth(code STRING) RETURNS INT RETURN array_max(transform(split(code, ' '), t -> int(substring_index(t, '@', -1))))",
    ):
        spark.sql(text)
    spark.udtf.register("mine_forest", udtf(MineForest, returnType="code string, size int, support long"))
