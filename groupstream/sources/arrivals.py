"""A data source of synthetic item arrivals, for load tests: numbered items with hashed attributes."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, start: int, end: int):
        super().__init__(start)
        self.start, self.end = start, end


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.parts = int(options.get("rows", 100)), int(options.get("partitions", 2))

    def partitions(self):
        step = -(-self.rows // self.parts)
        return [_Range(a, min(a + step, self.rows)) for a in range(0, self.rows, step)]

    def read(self, partition):
        for i in range(partition.start, partition.end):
            yield (i, (i * 7919) % 1000, f"tag{i % 13}")


class ItemArrivals(DataSource):
    """spark.dataSource.register(ItemArrivals); spark.read.format('item_arrivals').option('rows', n).load()"""

    @classmethod
    def name(cls) -> str:
        return "item_arrivals"

    def schema(self) -> str:
        return "v long, price long, tag string"

    def reader(self, schema):
        return _Reader(self.options)
