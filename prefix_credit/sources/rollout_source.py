"""A Python data source for rollout logs: one JSON object a line, read with declared columns, split by file."""

from __future__ import annotations

import json
from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _File(InputPartition):
    def __init__(self, path: str) -> None:
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str, columns: list[str]) -> None:
        self.path, self.columns = path, columns

    def partitions(self) -> list[InputPartition]:
        at = Path(self.path)
        files = [at] if at.is_file() else sorted(p for p in at.iterdir() if p.suffix in (".json", ".jsonl"))
        return [_File(str(p)) for p in files]

    def read(self, partition: _File) -> Iterator[tuple]:
        with open(partition.path, encoding="utf-8") as f:
            for line in f:
                if line.strip():
                    row = json.loads(line)
                    yield tuple(row.get(c) for c in self.columns)


class RolloutSource(DataSource):
    """`spark.read.format("rollouts").schema(...).load(path)`; for paths that every executor can open."""

    @classmethod
    def name(cls) -> str:
        return "rollouts"

    def schema(self) -> str:
        return "task long, traj long, t int, text string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"], schema.names)


def install(spark: SparkSession) -> None:
    spark.dataSource.register(RolloutSource)
