"""Rows fetched page by page, as from a paged interface: each page is a partition, fetched in its task."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class PagedRows(DataSource):
    @classmethod
    def name(cls) -> str:
        return "paged_rows"

    def schema(self) -> str:
        return "row long, page int"

    def reader(self, schema):
        return PagedReader(int(self.options.get("rows", 100)), int(self.options.get("pages", 4)))


class PagedReader(DataSourceReader):
    def __init__(self, rows: int, pages: int):
        self.rows, self.pages = rows, pages

    def partitions(self):
        return [InputPartition(i) for i in range(self.pages)]

    def read(self, partition):
        size = -(-self.rows // self.pages)
        for i in range(partition.value * size, min(self.rows, (partition.value + 1) * size)):
            yield (i, partition.value)
