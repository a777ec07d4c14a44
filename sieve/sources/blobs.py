"""A Python data source for filter blobs: one file a shard, readable outside Spark."""

from __future__ import annotations

import os
import re

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


class FilterBlobs(DataSource):
    """``format("sieve_blobs")`` over a shared folder given as option ``path``."""

    @classmethod
    def name(cls) -> str:
        return "sieve_blobs"

    def schema(self) -> str:
        return "filter_id string, shard int, blob binary"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options["path"])


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.removeprefix("file://")

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(f) for f in sorted(os.listdir(self.path)) if f.endswith(".blob")]

    def read(self, partition: InputPartition):
        m = re.fullmatch(r"(.*)-(\d+)\.blob", partition.value)
        with open(os.path.join(self.path, partition.value), "rb") as f:
            yield m[1], int(m[2]), f.read()


class _Writer(DataSourceWriter):
    def __init__(self, path: str):
        self.path = path.removeprefix("file://")

    def write(self, rows) -> WriterCommitMessage:
        os.makedirs(self.path, exist_ok=True)
        for r in rows:
            to = os.path.join(self.path, f"{r['filter_id']}-{r['shard']}.blob")
            with open(f"{to}.tmp", "wb") as f:
                f.write(bytes(r["blob"]))
            os.replace(f"{to}.tmp", to)  # a retried task writes the same file again
        return WriterCommitMessage()


def register(spark) -> None:
    spark.dataSource.register(FilterBlobs)
