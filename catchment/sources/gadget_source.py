"""A data source of synthetic squares: ``spark.read.format("gadget").option("kind", "diagonal").option("n", 8)``."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, first: int, past: int):
        super().__init__(first)
        self.first, self.past = first, past


class GadgetReader(DataSourceReader):
    """Squares by formula from their number, a range of numbers a task."""

    def __init__(self, options: dict):
        self.kind, self.n, self.parts = options.get("kind", "diagonal"), int(options.get("n", 8)), int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        step = max(1, -(-self.n // self.parts))
        return [_Range(lo, min(self.n, lo + step)) for lo in range(0, self.n, step)] or [_Range(0, 0)]

    def read(self, part: InputPartition):
        for i in range(part.first, part.past):
            if self.kind == "diagonal":
                low, high = 2 * (i + 1) - self.n, 2 * (i + 1) + self.n
            elif self.kind == "disjoint":
                low, high = 10 * i, 10 * i + 4
            else:
                raise ValueError(f"no gadget {self.kind!r}")
            yield i + 1, low, high, low, high, 1


class GadgetSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gadget"

    def schema(self) -> str:
        return "oid long, xl long, xh long, yl long, yh long, weight long"

    def reader(self, schema) -> DataSourceReader:
        return GadgetReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(GadgetSource)
