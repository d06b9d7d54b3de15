"""A data source of streams in adversarial orders, for tests of order independence."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def ordered_values(n: int, order: str, seed: int = 0) -> np.ndarray:
    """0 .. n - 1 as doubles: ascending, descending, ends (smallest, largest, ...), blocks (sorted runs, shuffled) or random."""
    x = np.arange(n, dtype=np.float64)
    if order == "descending":
        return x[::-1].copy()
    if order == "ends":
        out = np.empty(n)
        out[0::2], out[1::2] = x[: (n + 1) // 2], x[(n + 1) // 2 :][::-1]
        return out
    if order == "blocks":
        runs = np.array_split(x, max(1, n // 97))
        return np.concatenate([runs[i] for i in np.random.default_rng(seed).permutation(len(runs))])
    return np.random.default_rng(seed).permutation(x) if order == "random" else x


class OrderedStreamSource(DataSource):
    """spark.read.format('ordered_stream').option('n', ..).option('order', ..).option('parts', ..): column value double."""

    @classmethod
    def name(cls) -> str:
        return "ordered_stream"

    def schema(self) -> str:
        return "value double"

    def reader(self, schema: object) -> DataSourceReader:
        return _OrderedReader(self.options)


class _OrderedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.order, self.parts = int(options.get("n", 1000)), options.get("order", "ascending"), int(options.get("parts", 1))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        values = np.array_split(ordered_values(self.n, self.order), self.parts)[partition.value]
        for part in np.array_split(values, max(1, len(values) // 4096)):
            yield pa.RecordBatch.from_arrays([pa.array(part)], names=["value"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(OrderedStreamSource)
