"""Stored samples as a Python data source, and a table function that samples its input."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThanOrEqual, InputPartition, LessThanOrEqual

from spreadsample.operators.exchange import WorkingSet


class FilePart(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class SampleReader(DataSourceReader):
    """One task per Parquet file of the stored sample; range filters on x and y go down to the file reader."""

    def __init__(self, options):
        self.files = [f for f in options.get("files", "").split("\n") if f]
        self.ranges: list[tuple[str, str, float]] = []

    def pushFilters(self, filters) -> Iterator:
        for f in filters:
            op = {GreaterThanOrEqual: ">=", LessThanOrEqual: "<=", EqualTo: "=="}.get(type(f))
            if op and f.attribute in (("x",), ("y",)):
                self.ranges.append((f.attribute[0], op, float(f.value)))
            else:
                yield f

    def partitions(self):
        return [FilePart(f) for f in self.files] or [FilePart("")]

    def read(self, partition) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq

        if not partition.path:
            return
        table = pq.read_table(partition.path, columns=["id", "x", "y", "value", "density"], filters=self.ranges or None)
        yield from table.cast(pa.schema([("id", pa.string()), ("x", pa.float64()), ("y", pa.float64()), ("value", pa.float64()), ("density", pa.int64())])).to_batches()


class SampleSource(DataSource):
    """spark.read.format("spread_sample").option("files", newline-separated paths)."""

    @classmethod
    def name(cls) -> str:
        return "spread_sample"

    def schema(self) -> str:
        return "id string, x double, y double, value double, density long"

    def reader(self, schema) -> SampleReader:
        return SampleReader(self.options)


class SampleFunction:
    """A table function: spread_sample(TABLE t PARTITION BY g, k, eps) gives each partition's spread sample (id, x, y, burden)."""

    def __init__(self):
        self.work = None

    def eval(self, row, k: int, eps: float):
        if self.work is None:
            self.work = WorkingSet(int(k), float(eps))
        self.work.offer(np.array([row["id"]], object), np.array([row["x"]]), np.array([row["y"]]))

    def terminate(self):
        if self.work is not None:
            batch = self.work.members()
            yield from zip(*(batch.column(c).to_pylist() for c in range(1, 5)))


def register(spark: SparkSession) -> None:
    from pyspark.sql.functions import udtf

    spark.conf.set("spark.sql.python.filterPushdown.enabled", True)
    spark.dataSource.register(SampleSource)
    spark.udtf.register("spread_sample", udtf(SampleFunction, returnType="id string, x double, y double, burden double"))
