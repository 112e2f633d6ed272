"""A Python data source over the parameters of a stored model."""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ModelSource(DataSource):
    """Option ``parameters``: the parameter table as JSON records (name, shape, value); gives one row per parameter."""

    @classmethod
    def name(cls) -> str:
        return "tinyff_model"

    def schema(self) -> str:
        return "name string, rows bigint, numbers bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(json.loads(self.options.get("parameters", "[]")))


class _Reader(DataSourceReader):
    def __init__(self, records: list[dict]):
        self.records = records

    def partitions(self):
        return [InputPartition(i) for i in range(len(self.records))]

    def read(self, partition):
        r = self.records[partition.value]
        yield (r["name"], int(r["shape"][0]), len(r["value"]))
