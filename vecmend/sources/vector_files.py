"""Vector files: a reader of records of one 32-bit length and as many 32-bit floats, as a Spark data source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

RECORDS = 1 << 16


class _Range(InputPartition):
    def __init__(self, path: str, first: int, last: int):
        self.path, self.first, self.last = path, first, last


class _Reader(DataSourceReader):
    def __init__(self, path: str, per_part: int):
        self.path, self.per_part = path, per_part

    def _shape(self) -> tuple[int, int]:
        import os
        import struct

        with open(self.path, "rb") as f:
            head = f.read(4)
        if not head:
            return 0, 0
        dim = struct.unpack("<i", head)[0]
        return dim, os.path.getsize(self.path) // (4 * dim + 4)

    def partitions(self) -> list[InputPartition]:
        _, n = self._shape()
        return [_Range(self.path, i, min(i + self.per_part, n)) for i in range(0, n, self.per_part)] or [_Range(self.path, 0, 0)]

    def read(self, partition: _Range) -> Iterator:
        import numpy as np
        import pyarrow as pa

        dim, _ = self._shape()
        n = partition.last - partition.first
        if not n:
            return
        with open(partition.path, "rb") as f:
            f.seek(partition.first * (4 * dim + 4))
            rows = np.frombuffer(f.read(n * (4 * dim + 4)), dtype="<f4").reshape(n, dim + 1)[:, 1:]
        flat = pa.array(np.ascontiguousarray(rows).ravel().astype(np.float64))
        vecs = pa.ListArray.from_arrays(pa.array(np.arange(0, n * dim + 1, dim), pa.int32()), flat)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(partition.first, partition.last)), vecs], names=["vec_id", "vec"])


class VectorFiles(DataSource):
    """``spark.read.format("float_vectors").load(path)``: (vec_id, vec), in ranges of whole records.

    The path must be one that the driver and all executors see as a file.
    """

    @classmethod
    def name(cls) -> str:
        return "float_vectors"

    def schema(self) -> str:
        return "vec_id bigint, vec array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"], int(self.options.get("records", RECORDS)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(VectorFiles)
