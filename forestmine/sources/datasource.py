"""A data source of tree text: spark.read.format("forest_text").load(folder).

Files are read by Python, so the folder must be mounted where the executors run; elsewhere
sources.codec.read_trees reads the same text through Spark's own reader.
"""

from __future__ import annotations

from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .codec import UP


def vertices(tokens: list[str]) -> Iterator[tuple[int, int, int, str]]:
    """(lo, hi, depth, label) of one tree's tokens; steps up at the end may be left out."""
    rows: list[list] = []
    path: list[int] = []
    for token in tokens:
        if token == UP:
            if path:
                rows[path.pop()][1] = len(rows) - 1
        else:
            rows.append([len(rows), -1, len(path), token])
            path.append(len(rows) - 1)
    for at in path:
        rows[at][1] = len(rows) - 1
    return (tuple(r) for r in rows)


class _File(InputPartition):
    def __init__(self, number: int, path: str):
        super().__init__(number)
        self.number, self.path = number, path


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        root = Path(self.path.removeprefix("file://"))
        files = sorted(p for p in ([root] if root.is_file() else root.iterdir()) if p.is_file() and p.name[0] not in "._")
        return [_File(i, str(p)) for i, p in enumerate(files)]

    def read(self, partition: _File) -> Iterator[tuple]:
        """A file's trees: a tree_id is the file's number times 2^40 and the line's."""
        with open(partition.path, encoding="utf-8") as f:
            for line_no, line in enumerate(f):
                for row in vertices(line.split()):
                    yield ((partition.number << 40) + line_no, *row)


class ForestText(DataSource):
    @classmethod
    def name(cls) -> str:
        return "forest_text"

    def schema(self) -> str:
        return "tree_id long, lo int, hi int, depth int, label string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ForestText)
