"""Mixing sources to target weights by iterative proportional fitting.

Token weights are summed into cells (source, language, topic). Raking then scales one marginal at a time to its target: the factors of a
dimension are refitted from the cells times the other factors. A document's calibrated probability is its cell's factor over the largest one, and
it is drawn by a hash of its id.
"""

from __future__ import annotations

import functools
import math
import warnings
from collections.abc import Callable, Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._spark import masked, materialize

DIMENSIONS = ["source", "lang", "topic"]
#: Default targets: each dimension's own shares to these powers (1 leaves them, 0 makes them equal).
TEMPER = {"source": 0.7, "lang": 0.9, "topic": 1.0}
#: SWEEPS are made at least; then raking goes on until no marginal's share is off by more than TOLERANCE.
SWEEPS, TOLERANCE, STALL = 6, 1e-5, 1000
#: Cells that are raked on the driver; more are raked by shuffles.
ONE_TASK_CELLS = 100_000
#: A token is a word: a run of characters other than space and tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"
#: Probabilities are in millionths.
UNIT = 1_000_000


def topic(text: Column) -> Column:
    """A topic by surface: symbols for over 5 % of # * $ % & | < >, numbers for over 5 % of digits, headline for over 40 % of capitals, else prose."""
    n = F.length(text)
    of = lambda characters: F.regexp_count(text, F.lit(f"[{characters}]"))
    return F.when(20 * of("#*$%&|<>") > n, "symbols").when(20 * of("0-9") > n, "numbers").when(10 * of("A-Z") > 4 * n, "headline").otherwise("prose")


def draw(doc_id: Column) -> Column:
    """A number from 0 to UNIT - 1 fixed by the id (null as the empty text)."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), 1, 8), 16, 10).cast("long") % UNIT


def _with_cells(docs: DataFrame, text: str = "text", source: str = "source", lang: str = "lang") -> DataFrame:
    """Adds __source, __lang, __topic (null as empty) and __tokens (words)."""
    text = F.coalesce(text, F.lit(""))
    return docs.withColumns({"__source": F.coalesce(F.col(source).cast("string"), F.lit("")), "__lang": F.coalesce(F.col(lang).cast("string"), F.lit("")), "__topic": topic(text), "__tokens": F.regexp_count(text, F.lit(WORD)).cast("long")})


class _Progress:
    """When raking ends: after a given number of rounds, else once all marginals are met.

    Targets that no factors meet are found by the error: it is looked at each time the rounds have doubled,
    and must have fallen by a tenth from STALL rounds on. The error left is then reported by a warning.
    """

    def __init__(self, sweeps: int | None):
        self.sweeps, self.rounds, self.due, self.last = sweeps, 0, SWEEPS, math.inf

    def more(self, error: Callable[[], float]) -> bool:
        """Whether another round is due; error gives the largest distance of a marginal's share from its target."""
        if self.sweeps is not None or self.rounds < SWEEPS:
            self.rounds += 1
            return self.rounds <= (SWEEPS if self.sweeps is None else self.sweeps)
        now = error()
        if now <= TOLERANCE:
            return False
        if self.rounds == self.due:
            if self.rounds >= STALL and now > 0.9 * self.last:
                warnings.warn(f"Raking stopped after {self.rounds} rounds: no factors meet the targets; a marginal is off by {now:.2g}.", RuntimeWarning, stacklevel=2)
                return False
            self.due, self.last = 2 * self.due, now
        self.rounds += 1
        return True


def _fit_on_driver(cells: DataFrame, targets: dict[str, DataFrame] | None, sweeps: int | None) -> DataFrame:
    """cells with f_source, f_lang and f_topic. A few cells are gathered; rounds then cost next to nothing, however many it takes."""
    got = cells.select(*DIMENSIONS, "weight").toArrow()
    weight = got["weight"].to_numpy().astype(float)
    at, share, factor = {}, {}, {}
    for d in DIMENSIONS:
        coded = got[d].combine_chunks().dictionary_encode()
        values, at[d] = coded.dictionary.to_pylist(), coded.indices.to_numpy(zero_copy_only=False)
        given = targets.get(d) if targets else None
        if given is None:
            own = np.bincount(at[d], weight, len(values))
            share[d] = np.where(own > 0, own ** TEMPER[d], 0.0)
            share[d] = share[d] / (share[d].sum() or 1.0)
        else:
            wanted = {r["value"]: r["share"] for r in _shares(given).collect()}
            share[d] = np.array([wanted.get(v) or 0.0 for v in values])
        factor[d] = np.ones(len(values))

    def sums(d: str) -> np.ndarray:
        product = weight.copy()
        for e in DIMENSIONS:
            if e != d:
                product *= factor[e][at[e]]
        return np.bincount(at[d], product, len(share[d]))

    def error() -> float:
        most = 0.0
        for d in DIMENSIONS:
            now, want = sums(d) * factor[d], share[d]
            if now.sum() > 0 and want.sum() > 0:
                most = max(most, float(np.abs(now / now.sum() - want / want.sum()).max()))
        return most

    progress = _Progress(sweeps)
    while progress.more(error):
        for d in DIMENSIONS:
            now = sums(d)
            factor[d] = np.divide(share[d], now, out=np.zeros(len(now)), where=now > 0)
    schema = T.StructType([cells.select(*DIMENSIONS, "weight").schema[c] for c in [*DIMENSIONS, "weight"]] + [T.StructField(f"f_{d}", T.DoubleType()) for d in DIMENSIONS])
    for d in DIMENSIONS:
        got = got.append_column(f"f_{d}", pa.array(factor[d][at[d]], "double"))
    return cells.sparkSession.createDataFrame(got, schema)


def _fit_by_tables(cells: DataFrame, targets: dict[str, DataFrame] | None, sweeps: int | None) -> DataFrame:
    """The same by shuffles with partial sums: a table of factors for each dimension, refitted in turn."""
    wanted, factors = {}, {}
    for d in DIMENSIONS:
        own = cells.groupBy(F.col(d).alias("value")).agg(F.sum("weight").cast("double").alias("weight"))
        given = targets.get(d) if targets else None
        if given is None:
            given = own.select("value", F.when(F.col("weight") > 0, F.pow("weight", F.lit(TEMPER[d]))).otherwise(0.0).alias("share"))
        wanted[d] = materialize(_shares(given), "target")
        factors[d] = materialize(own.select("value", F.lit(1.0).alias("factor")), "factor")

    def error() -> float:
        most, fitted = 0.0, cells
        for d in DIMENSIONS:
            fitted = fitted.join(factors[d].toDF(d, f"f_{d}"), d)
        for d in DIMENSIONS:
            sums = fitted.groupBy(F.col(d).alias("value")).agg(F.sum(_product(DIMENSIONS)).alias("now")).join(wanted[d], "value", "left").select("now", F.coalesce("share", F.lit(0.0)).alias("share"))
            all_ = sums.agg(F.sum("now").alias("now"), F.sum("share").alias("share")).first()
            if (all_["now"] or 0) > 0 and all_["share"] > 0:
                most = max(most, sums.agg(F.max(F.abs(F.col("now") / F.lit(all_["now"]) - F.col("share") / F.lit(all_["share"])))).first()[0])
        return most

    progress = _Progress(sweeps)
    while progress.more(error):
        for d in DIMENSIONS:
            others, rest = cells, [e for e in DIMENSIONS if e != d]
            for e in rest:
                others = others.join(factors[e].toDF(e, f"f_{e}"), e)
            sums = others.groupBy(F.col(d).alias("value")).agg(F.sum(_product(rest)).alias("now"))
            factors[d] = materialize(sums.join(wanted[d], "value", "left").select("value", _factor(F.col("now"), F.col("share")).alias("factor")), "factor")
    for d in DIMENSIONS:
        cells = cells.join(factors[d].toDF(d, f"f_{d}"), d)
    return cells


def _shares(given: DataFrame) -> DataFrame:
    """(value, share) with shares that sum to 1."""
    total = given.agg(F.sum("share").alias("all")).first()["all"] or 1.0
    return given.select("value", (F.col("share") / F.lit(float(total))).alias("share"))


def _product(dimensions: Iterable[str]) -> Column:
    return functools.reduce(lambda x, d: x * F.col(f"f_{d}"), dimensions, F.col("weight").cast("double"))


def _factor(now: Column, share: Column) -> Column:
    return F.when((now > 0) & share.isNotNull(), share / now).otherwise(0.0)


def fit(cells: DataFrame, targets: dict[str, DataFrame] | None = None, sweeps: int | None = None) -> DataFrame:
    """cells (source, lang, topic, weight; one row each) with f_source, f_lang, f_topic, written once.

    The cells are counted first: ONE_TASK_CELLS of them are fitted on the driver, more
    by shuffles. Both compute the same factors. Without ``sweeps``, rounds go on until each
    marginal's shares are within TOLERANCE of its target (see _Progress).
    """
    way = _fit_on_driver if cells.count() <= ONE_TASK_CELLS else _fit_by_tables
    return materialize(way(cells, targets, sweeps), "fitted")


def rake(cells: DataFrame, targets: dict[str, DataFrame] | None = None, sweeps: int | None = None) -> dict[str, DataFrame]:
    """Factors of each dimension: (value, factor), so that cells' weights times factors meet the targets.

    cells: source, lang, topic, weight. targets: (value, share) of dimensions;
    the rest is tempered. A value without a target, or without weight, gets factor 0.
    """
    fitted = fit(cells, targets, sweeps)
    return {d: fitted.groupBy(F.col(d).alias("value")).agg(F.first(f"f_{d}").alias("factor")) for d in DIMENSIONS}


def probabilities(docs: DataFrame, targets: dict[str, DataFrame] | None = None, sweeps: int | None = None) -> DataFrame:
    """docs' columns (none of these names among them), __source, __lang, __topic, __tokens, __ppm (probability in millionths) and __selected. Defined cases: as for mix."""
    return _rated(_with_cells(docs), targets, sweeps)


def _rated(marked: DataFrame, targets: dict[str, DataFrame] | None, sweeps: int | None = None, key: str = "doc_id") -> DataFrame:
    """marked (documents with cells and tokens) with __ppm and __selected."""
    cells = marked.groupBy("__source", "__lang", "__topic").agg(F.sum("__tokens").alias("weight")).toDF("source", "lang", "topic", "weight")
    fitted = fit(materialize(cells, "cells"), targets, sweeps)
    product = F.col("f_source") * F.col("f_lang") * F.col("f_topic")
    rated = fitted.select(*(F.col(d).alias(f"__{d}") for d in DIMENSIONS), F.when(F.col("weight") > 0, product).alias("__factor"))
    most = rated.agg(F.max("__factor").alias("most")).first()["most"] or 1.0
    # Documents of cells without a token get probability 0: they have no weight to calibrate.
    joined = marked.join(rated, ["__source", "__lang", "__topic"])
    ppm = F.round(F.coalesce("__factor", F.lit(0.0)) / F.lit(most) * UNIT).cast("long")
    return joined.select(*marked.columns, ppm.alias("__ppm")).withColumn("__selected", draw(F.col(key)) < F.col("__ppm"))


def mix(docs: DataFrame, targets: dict[str, DataFrame] | None = None) -> DataFrame:
    """Per row: doc_id, source, lang, topic, n_tokens, ppm, selected.

    Defined cases: null source or lang is the empty string's cell; null or empty
    text has no token and adds no weight. A repeated row adds its weight each time
    and shares its id's draw; a null id draws as the empty text. An empty table gives no rows.
    """
    # Without texts the marked rows are small: they are written, so that texts are read once.
    marked = _with_cells(docs.select(F.col("doc_id").cast("long"), "text", "source", "lang")).select("doc_id", "__source", "__lang", "__topic", "__tokens")
    p = _rated(materialize(marked, "marked"), targets)
    return p.select("doc_id", F.col("__source").alias("source"), F.col("__lang").alias("lang"), F.col("__topic").alias("topic"), F.col("__tokens").alias("n_tokens"), F.col("__ppm").alias("ppm"), F.col("__selected").alias("selected"))


def sample(docs: DataFrame, targets: dict[str, DataFrame] | None = None) -> DataFrame:
    """The drawn rows of docs, with docs' columns, whatever else these are called. Defined cases: as for mix."""
    rows, own = masked(docs)
    named = rows.withColumns({"__id": F.col(own["doc_id"]), "__s": F.col(own["source"]), "__l": F.col(own["lang"])})
    marked = _with_cells(named, own["text"], "__s", "__l")
    return _rated(marked, targets, key="__id").filter("__selected").select(*own.values()).toDF(*own)
