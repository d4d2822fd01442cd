"""A Python data source of rank families: spark.read.format("rank_family").option("kind", "geometric").option("n", 1000)."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.kind, self.n = options.get("kind", "all"), int(options.get("n", 0))
        self.parts, self.m = int(options.get("parts", 10)), int(options.get("m", 100))

    def _count(self) -> int:
        return {"all": self.n, "top": min(self.m, self.n), "even": min(self.parts - 1, self.n), "geometric": self.n.bit_length()}[self.kind]

    def partitions(self) -> list[_Range]:
        count, step = self._count(), 1_000_000
        return [_Range(k, min(k + step, count)) for k in range(0, count, step)] or [_Range(0, 0)]

    def read(self, partition: _Range):
        for k in range(partition.lo, partition.hi):
            yield ({"all": k + 1, "top": self.n - self._count() + 1 + k, "even": max(1, -(-(k + 1) * self.n // self.parts)), "geometric": 1 << k}[self.kind],)


class RankFamilySource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rank_family"

    def schema(self) -> str:
        return "rank long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))
