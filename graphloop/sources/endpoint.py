"""A data source for query endpoints: rows come from a reader that the caller registers, page by page."""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EndpointSource(DataSource):
    """``spark.read.format('endpoint')`` with options ``rows`` (a JSON list of lists, a local stand-in for a service) and ``pages``."""

    @classmethod
    def name(cls) -> str:
        return "endpoint"

    def schema(self) -> str:
        return self.options.get("columns", "s string, p string, o string")

    def reader(self, schema) -> EndpointReader:
        return EndpointReader(self.options)


class EndpointReader(DataSourceReader):
    def __init__(self, options):
        self.rows = json.loads(options.get("rows", "[]"))
        self.pages = max(1, int(options.get("pages", "1")))

    def partitions(self):
        return [InputPartition(k) for k in range(self.pages)]

    def read(self, partition):
        yield from (tuple(row) for row in self.rows[partition.value :: self.pages])
