"""``spark.read.format("allpairs_raw")``: raw rows from files of ``entity<TAB>element<TAB>mult`` lines, one split a file.

Batch and stream.  Paths are those of the file system that executors see.
"""

from __future__ import annotations

import glob
import json
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


class _File(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


def _files(folder: str) -> list[str]:
    """Files of lines, as people name them or as Spark writes them."""
    return sorted(p for end in ("tsv", "txt") for p in glob.glob(f"{folder}/*.{end}"))


def _rows(path: str) -> Iterator[tuple]:
    with open(path, encoding="utf-8") as f:
        for line in f:
            entity, element, mult = line.rstrip("\n").split("\t")
            yield int(entity), element, int(mult)


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        return [_File(p) for p in _files(self.path)] or [_File("")]

    def read(self, partition) -> Iterator[tuple]:
        return _rows(partition.path) if partition.path else iter(())


class _StreamReader(SimpleDataSourceStreamReader):
    """Files that came since the last offset, in name order."""

    def __init__(self, path: str):
        self.path = path

    def initialOffset(self) -> dict:  # noqa: N802
        return {"done": json.dumps("")}

    def _after(self, start: dict) -> list[str]:
        return [p for p in _files(self.path) if p > json.loads(start["done"])]

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        files = self._after(start)
        end = {"done": json.dumps(files[-1])} if files else start
        return iter([r for p in files for r in _rows(p)]), end

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        return iter([r for p in self._after(start) if p <= json.loads(end["done"]) for r in _rows(p)])


class RawSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "allpairs_raw"

    def schema(self) -> str:
        return "entity bigint, element string, mult bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:  # noqa: N802
        return _StreamReader(self.options["path"])


def register(spark) -> None:
    spark.dataSource.register(RawSource)
