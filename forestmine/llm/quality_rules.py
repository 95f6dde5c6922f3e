"""Quality rules as a learned decision list, run as one conditional expression.

Sequential covering: on labelled statistics a rule (a conjunction of thresholds)
is grown for the class of poor documents by FOIL gain, pruned on rows set apart,
kept if it is precise there, and the rows it covers are taken out; then the next.
The list becomes an ordered chain of Spark conditions. Statistics are built-in
functions only, inside the row: no document is exploded or shuffled.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import masked

#: Labelled rows that the list is fitted on at most, those of least hash.
MAX_LABELLED = 20_000
#: Rules, conditions of a rule, thresholds tried of a statistic; least precision on rows set apart, and rows a rule must cover.
MAX_RULES, MAX_CONDITIONS, MAX_CUTS, MIN_PRECISION, MIN_COVER = 12, 3, 32, 0.97, 8

#: Statistics that rules may use.
STATISTICS = ["n_words", "mean_word", "symbol_share", "dup_line_share", "repeat_share", "upper_share", "digit_share", "bar_share", "exclaim_share"]
_SPACES = "\t\n\x0b\x0c\r"
WINDOW = 5


def words(text: Column) -> Column:
    """Words: runs of characters other than space and tab to carriage return."""
    return F.array_remove(F.split(F.translate(text, _SPACES, " " * len(_SPACES)), " "), "")


def _count(text: Column, characters: str) -> Column:
    return F.length(text) - F.length(F.translate(text, characters, ""))


def with_base(df: DataFrame, text: str = "text", to: str = "__q") -> DataFrame:
    """Adds ``to``: a struct of n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and the shares of STATISTICS.

    Each step is a projection that the next uses more than once, so that Spark evaluates it once.
    """
    own = df.columns
    t, h, w = "__q_text", "__q_hash", "__q_window"
    df = df.withColumn(t, F.coalesce(F.col(text), F.lit("")))
    df = df.withColumn(h, F.transform(words(F.col(t)), lambda x: F.xxhash64(x)))
    n = F.size(h)
    at = lambda i, k: F.get(F.col(h), i + F.lit(k))
    df = df.withColumn(w, F.when(n >= WINDOW, F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*(at(i, k) for k in range(WINDOW))))).otherwise(F.array().cast("array<long>")))
    # Windows found twice: neighbours after sorting; the words they cover, from their sorted places.
    sort = lambda: F.sort_array(F.transform(F.col(w), lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

    def repeated(s: Column) -> Column:
        same = lambda x, j: F.coalesce(F.get(s, j)["h"] == x["h"], F.lit(False))
        places = F.sort_array(F.transform(F.filter(s, lambda x, j: same(x, j - 1) | same(x, j + 1)), lambda x: x["i"]))
        step = lambda a, p: F.struct((a["n"] + F.least(F.lit(WINDOW), p - a["last"])).alias("n"), p.alias("last"))
        return F.aggregate(places, F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")), step, lambda a: a["n"])

    repeats = F.when(F.size(F.array_distinct(F.col(w))) == F.size(w), F.lit(0)).otherwise(F.transform(F.array(sort()), repeated)[0])
    lines = F.filter(F.split(F.col(t), "\n"), lambda x: F.length(F.translate(x, " " + _SPACES, "")) > 0)
    df = df.withColumn("__q_lines", lines)
    text_ = F.col(t)
    # A generator of one row: filters on the struct stay above it, so they don't repeat what is below.
    return df.select(
        *own,
        F.explode(F.array(F.struct(
            n.cast("long").alias("n_words"), F.length(F.translate(text_, " " + _SPACES, "")).cast("long").alias("word_chars"), _count(text_, "#*$%&|<>").cast("long").alias("n_symbols"),
            (F.size("__q_lines") - F.size(F.array_distinct(F.col("__q_lines")))).cast("long").alias("n_dup_lines"), repeats.cast("long").alias("n_repeat_words"),
            F.size("__q_lines").alias("n_lines"), F.length(F.translate(text_, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "")).alias("no_upper"), F.length(text_).alias("n_chars"),
            _count(text_, "0123456789").alias("n_digits"), _count(text_, "|").alias("n_bars"), _count(text_, "!").alias("n_exclaims"),
        ))).alias(to),
    )


def statistics(q: str = "__q") -> dict[str, Column]:
    """The statistics of a struct that with_base made."""
    f = lambda name: F.col(f"{q}.{name}").cast("double")
    share = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    return {
        "n_words": f("n_words"), "mean_word": share(f("word_chars"), f("n_words")), "symbol_share": share(f("n_symbols"), f("word_chars")), "dup_line_share": share(f("n_dup_lines"), f("n_lines")),
        "repeat_share": share(f("n_repeat_words"), f("n_words")), "upper_share": share(f("n_chars") - f("no_upper"), f("word_chars")), "digit_share": share(f("n_digits"), f("word_chars")),
        "bar_share": share(f("n_bars"), f("n_words")), "exclaim_share": share(f("n_exclaims"), f("n_words")),
    }


def base_failed(q: str = "__q") -> Column:
    n = F.col(f"{q}.n_words")
    return (n < 10) | (100 * F.col(f"{q}.n_repeat_words") > 20 * n)


@dataclass(frozen=True)
class Rule:
    """A conjunction of (statistic, '<=' or '>', threshold) that marks a poor document."""

    conditions: tuple[tuple[str, str, float], ...]

    def covers(self, row: dict) -> bool:
        return all(row[s] <= t if op == "<=" else row[s] > t for s, op, t in self.conditions)

    def column(self, stats: dict[str, Column]) -> Column:
        out = F.lit(True)
        for s, op, t in self.conditions:
            out = out & (stats[s] <= t if op == "<=" else stats[s] > t)
        return out


def _cuts(rows: list[dict], s: str) -> list[float]:
    values = sorted({r[s] for r in rows})
    middle = [(a + b) / 2 for a, b in zip(values, values[1:])]
    return middle[:: max(1, len(middle) // MAX_CUTS)]


def _grow(rows: list[dict]) -> tuple:
    """Adds the condition of largest FOIL gain until no good row is covered."""
    conditions: tuple = ()
    while len(conditions) < MAX_CONDITIONS:
        poor = sum(r["poor"] for r in rows)
        if poor == len(rows):
            break
        before, best = math.log2(poor / len(rows)), (1e-9, None)
        for s in STATISTICS:
            ordered = sorted(rows, key=lambda r: r[s])
            cuts, i, below, poor_below = _cuts(rows, s), 0, 0, 0
            for t in cuts:
                while i < len(ordered) and ordered[i][s] <= t:
                    below, poor_below, i = below + 1, poor_below + ordered[i]["poor"], i + 1
                for op, n, p in (("<=", below, poor_below), (">", len(rows) - below, poor - poor_below)):
                    if p:
                        gain = p * (math.log2(p / n) - before)
                        if gain > best[0]:
                            best = (gain, (s, op, t))
        if best[1] is None:
            break
        conditions = (*conditions, best[1])
        rows = [r for r in rows if Rule((best[1],)).covers(r)]
    return conditions


def _worth(conditions: tuple, rows: list[dict]) -> float:
    covered = [r["poor"] for r in rows if Rule(conditions).covers(r)]
    return (2 * sum(covered) - len(covered)) / len(covered) if covered else -1.0


def fit(rows: list[dict]) -> list[Rule]:
    """The decision list of labelled statistics (poor: 0 or 1, fold: any integer), most precise first."""
    grow, prune = [r for r in rows if r["fold"] % 3], [r for r in rows if not r["fold"] % 3]
    rules: list[Rule] = []
    while len(rules) < MAX_RULES and any(r["poor"] for r in grow):
        conditions = _grow(grow)
        if not conditions:
            break
        for end in range(len(conditions) - 1, 0, -1):  # drop last conditions while that isn't worse
            if _worth(conditions[:end], prune) >= _worth(conditions, prune):
                conditions = conditions[:end]
        rule = Rule(conditions)
        covered = [r["poor"] for r in prune if rule.covers(r)]
        inside = [r["poor"] for r in grow if rule.covers(r)]
        if len(covered) + len(inside) < MIN_COVER or sum(covered) < MIN_PRECISION * len(covered) or sum(inside) < MIN_PRECISION * len(inside):
            break
        rules.append(rule)
        grow, prune = [r for r in grow if not rule.covers(r)], [r for r in prune if not rule.covers(r)]
    return rules


def learn(docs: DataFrame, labels: DataFrame, most: int = MAX_LABELLED) -> list[Rule]:
    """Fits the list on at most ``most`` labelled documents, the ones of least id hash; none if there are no poor ones."""
    known = labels.select(F.col("doc_id").alias("__id"), "quality").filter("quality is not null and __id is not null").groupBy("__id").agg(F.min("quality").alias("__quality"))
    known = known.orderBy(F.xxhash64("__id"), "__id").limit(most)
    rows = with_base(docs.select("doc_id", "text").join(F.broadcast(known), F.col("doc_id") == F.col("__id")))
    got = rows.select(F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(997)).alias("fold"), (F.col("__quality") == 0).cast("int").alias("poor"), *(c.alias(s) for s, c in statistics().items()))
    return fit(sorted((r.asDict() for r in got.collect()), key=lambda r: sorted(r.items())))


def verdict(rules: list[Rule], stats: dict[str, Column]) -> Column:
    """Number (from 1) of the first rule that a document meets; 0 for none."""
    chain = F.when(F.lit(False), 0)
    for i, rule in enumerate(rules, 1):
        chain = chain.when(rule.column(stats), i)
    return chain.otherwise(0)


def judge(docs: DataFrame, rules: list[Rule]) -> DataFrame:
    """docs' columns (none called ``__q`` or ``__rule``), ``__q`` and ``__rule``; see quality for what is kept and for the defined cases."""
    return with_base(docs).withColumn("__rule", verdict(rules, statistics()))


def quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Per row: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, rule.

    Defined cases: null or empty text has no words and fails the base. Null or
    repeated doc_ids don't matter but that labels join by id (a repeated label
    counts as its least quality). Without labels there are no rules. An empty table gives no rows.
    """
    q = judge(docs.select(F.col("doc_id").cast("long"), "text"), learn(docs, labels))
    base = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    return q.select("doc_id", *(F.col(f"__q.{c}").alias(c) for c in base), base_failed().alias("base_failed"), (~base_failed() & (F.col("__rule") == 0)).alias("kept"), F.col("__rule").alias("rule"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs' rows that are kept, with docs' columns, whatever these are called. Defined cases: as for quality; an empty table gives no rows."""
    rows, own = masked(docs)
    judged = with_base(rows, own["text"]).withColumn("__rule", verdict(learn(docs, labels), statistics()))
    return judged.filter(~base_failed() & (F.col("__rule") == 0)).select(*own.values()).toDF(*own)
