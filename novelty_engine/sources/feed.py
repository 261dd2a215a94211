"""A small Python data source: items from a JSON-lines folder, one partition per file, and a streaming reader."""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class FilePartition(InputPartition):
    def __init__(self, path: str):
        self.path = path


class FeedReader(DataSourceReader):
    def __init__(self, folder: str, columns: list[str]):
        self.folder, self.columns = folder, columns

    def partitions(self) -> list[FilePartition]:
        return [FilePartition(os.path.join(self.folder, f)) for f in sorted(os.listdir(self.folder)) if f.endswith((".json", ".jsonl"))]

    def read(self, partition: FilePartition) -> Iterator[tuple]:
        with open(partition.path, encoding="utf-8") as lines:
            for line in lines:
                if line.strip():
                    row = json.loads(line)
                    yield tuple(row.get(c) for c in self.columns)


class ItemFeed(DataSource):
    """`spark.read.format("item_feed").option("path", folder)`; missing fields are null."""

    @classmethod
    def name(cls) -> str:
        return "item_feed"

    def schema(self) -> str:
        return "item_id bigint, title string, body string, pub_date string, year int"

    def reader(self, schema) -> FeedReader:
        return FeedReader(self.options["path"], [f.name for f in schema.fields])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ItemFeed)
