"""A Python data source of generated examples: blobs around planted centres, in any number of partitions.

spark.dataSource.register(KernelBlobs); spark.read.format("kernel_blobs").option("rows", 1000).load()
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


class _Range(InputPartition):
    def __init__(self, low: int, high: int) -> None:
        self.low, self.high = low, high


class _BlobReader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.rows, self.d = int(options.get("rows", 1000)), int(options.get("d", 2))
        self.classes, self.parts = int(options.get("classes", 2)), int(options.get("partitions", 4))
        self.seed, self.spread = int(options.get("seed", 0)), float(options.get("spread", 0.5))

    def partitions(self) -> list[InputPartition]:
        cuts = [self.rows * k // self.parts for k in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        import numpy as np

        from kernelblocks.functions.rng import portable_normal

        centres = 2.0 * portable_normal(self.seed + 1, np.arange(self.classes)[:, None], np.arange(self.d)[None, :])
        for i in range(partition.low, partition.high):
            label = i % self.classes
            x = centres[label] + self.spread * portable_normal(self.seed, i, np.arange(self.d))
            yield i, x.tolist(), [1.0 if k == label else -1.0 for k in range(self.classes)], label


class KernelBlobs(DataSource):
    """Options: rows, d, classes, partitions, seed, spread. Row i is the same whatever the partitions."""

    @classmethod
    def name(cls) -> str:
        return "kernel_blobs"

    def schema(self) -> str:
        return "row_id long, x array<double>, y array<double>, label int"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _BlobReader(self.options)
