"""Tree-local kernel: a tree's records and vertices meet inside one Python call over Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

_PAIRS = "pattern_id long, tree_id long, lo int, hi int, rp array<int>, mult long, x_lo int, x_hi int, x_depth int, label string, c int"


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        cols = {n: batch.column(n).to_pylist() for n in batch.schema.names}
        out: list[list] = [[] for _ in range(11)]
        for i, nodes in enumerate(cols["nodes"]):
            lo, rp = cols["lo"][i], np.array(cols["rp"][i])
            for x in nodes:
                if lo < x["lo"] <= rp[0]:
                    row = (cols["pattern_id"][i], cols["tree_id"][i], lo, cols["hi"][i], cols["rp"][i], cols["mult"][i], x["lo"], x["hi"], x["depth"], x["label"], int((rp >= x["lo"]).sum()) - 1)
                    for column, value in zip(out, row):
                        column.append(value)
        kinds = ["int64", "int64", "int32", "int32", pa.list_(pa.int32()), "int64", "int32", "int32", "int32", "string", "int32"]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds)], names=["pattern_id", "tree_id", "lo", "hi", "rp", "mult", "x_lo", "x_hi", "x_depth", "label", "c"])


def pairs_by_kernel(r: DataFrame, packed: DataFrame) -> DataFrame:
    """As joins.pairs_by_join."""
    return r.join(packed.select("tree_id", "nodes"), "tree_id").select("pattern_id", "tree_id", "lo", "hi", "rp", "mult", "nodes").mapInArrow(_pairs, _PAIRS)
