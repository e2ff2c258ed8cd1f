"""A Python data source that generates pages of rows, one partition a page."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class PagedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "paged"

    def schema(self) -> str:
        return "page int, id bigint, prompt string"

    def reader(self, schema) -> DataSourceReader:
        return PagedReader(int(self.options.get("rows", 100)), int(self.options.get("pages", 2)))


class PagedReader(DataSourceReader):
    def __init__(self, rows: int, pages: int):
        self.rows, self.pages = rows, pages

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.pages)]

    def read(self, partition: InputPartition):
        for i in range(partition.value, self.rows, self.pages):
            yield partition.value, i, f"prompt {i}"
