"""A data source of rows that are not valid, for padding tables to a public size."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class DummyRows(DataSource):
    """options: rows, partitions; columns: k (0, 1, ...) and v (null)."""

    @classmethod
    def name(cls) -> str:
        return "sealed_dummy_rows"

    def schema(self) -> str:
        return "k long, v long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("rows", 0)), int(self.options.get("partitions", 1)))


class _Span(InputPartition):
    def __init__(self, first: int, stop: int):
        super().__init__((first, stop))
        self.first, self.stop = first, stop


class _Reader(DataSourceReader):
    def __init__(self, rows: int, parts: int):
        self.rows, self.parts = rows, parts

    def partitions(self):
        edges = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [_Span(a, b) for a, b in zip(edges, edges[1:])]

    def read(self, partition):
        for k in range(partition.first, partition.stop):
            yield k, None
