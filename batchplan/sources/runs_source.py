"""Run logs as a Spark data source, ``spark.read.format("batchplan_runs")`` and ``readStream``.

Option ``path``: a folder of JSON-lines files, one run a line. Each file is a partition; a stream takes
files in order of name, so a file that has been read is never read again.
"""

from __future__ import annotations

import glob
import json
import os
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "round_id string, run_id long, query_id long, config_id int, conn_id int, start_us long, finish_us long"
_NAMES = [c.split()[0] for c in SCHEMA.split(", ")]


def _rows(path: str) -> Iterator[tuple]:
    with open(path) as f:
        for line in f:
            if line.strip():
                run = json.loads(line)
                yield tuple(run.get(n) for n in _NAMES)


class _Reader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(p) for p in sorted(glob.glob(os.path.join(self.path, "*.json")))] or [InputPartition(None)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        return _rows(partition.value) if partition.value else iter(())


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def initialOffset(self) -> dict:
        return {"after": ""}

    def _files(self, after: str) -> list[str]:
        return [p for p in sorted(glob.glob(os.path.join(self.path, "*.json"))) if os.path.basename(p) > after]

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        files = self._files(start["after"])
        return (r for p in files for r in _rows(p)), {"after": os.path.basename(files[-1]) if files else start["after"]}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return (r for p in self._files(start["after"]) if os.path.basename(p) <= end["after"] for r in _rows(p))


class RunsSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "batchplan_runs"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RunsSource)
