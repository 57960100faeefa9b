"""Data source `virtual_array`: cells computed on access, with index bounds pushed into the partitions."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual


class _Span(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__((lo, hi))
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.lo, self.hi, self.parts = 0, n, parts

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        """Takes bounds on idx; whatever else there is stays with Spark."""
        for f in filters:
            if getattr(f, "attribute", None) == ("idx",) and isinstance(f, (GreaterThan, GreaterThanOrEqual, LessThan, LessThanOrEqual, EqualTo)):
                v = f.value
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    self.lo = max(self.lo, v + isinstance(f, GreaterThan))
                if isinstance(f, (LessThan, LessThanOrEqual, EqualTo)):
                    self.hi = min(self.hi, v + (not isinstance(f, LessThan)))
            else:
                yield f

    def partitions(self) -> list[_Span]:
        step = max(1, -(-max(0, self.hi - self.lo) // self.parts))
        return [_Span(i, min(i + step, self.hi)) for i in range(self.lo, self.hi, step)] or [_Span(0, 0)]

    def read(self, part: _Span) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for lo in range(part.lo, part.hi, 1 << 16):
            i = np.arange(lo, min(lo + (1 << 16), part.hi), dtype=np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(np.sin(i.astype(float)))], names=["idx", "val"])


class VirtualArraySource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "virtual_array"

    def schema(self) -> str:
        return "idx long, val double"

    def reader(self, schema) -> _Reader:
        return _Reader(int(self.options.get("n", 1024)), int(self.options.get("partitions", 8)))


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(VirtualArraySource)
