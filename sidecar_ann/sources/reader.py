"""The blob container as a Spark data source: spark.read.format("ann_container").load(path) gives a row for each blob.

Only the footer is read unless the payload column is asked for by option("payload", "true")."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

_SCHEMA = "position int, type string, offset long, length long, raw_length long, codec string, snapshot_id long, properties string, payload binary"


class _One(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str, payload: bool):
        self.path, self.payload = path, payload

    def partitions(self) -> list[InputPartition]:
        return [_One(p) for p in self.path.split(",")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from sidecar_ann.sources.container import read_blob, read_footer

        for i, b in enumerate(read_footer(partition.path).blobs):
            data = read_blob(partition.path, b) if self.payload else None
            yield (i, b.type, b.offset, b.length, b.raw_length, b.codec, b.snapshot_id, json.dumps(b.properties, sort_keys=True), data)


class ContainerSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ann_container"

    def schema(self) -> str:
        return _SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options["path"], self.options.get("payload", "false").lower() == "true")


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ContainerSource)
