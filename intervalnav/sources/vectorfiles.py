"""Data source for public vector files: records of a 32-bit dimension and that many 4-byte values (fvecs, ivecs)."""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, path: str, first: int, count: int, dim: int):
        self.path, self.first, self.count, self.dim = path, first, count, dim


class VectorFiles(DataSource):
    """spark.dataSource.register(VectorFiles); spark.read.format("vectors").option("kind", "fvecs").load(path).

    The path is one that all executors can open; every record has the first one's dimension.
    """

    @classmethod
    def name(cls) -> str:
        return "vectors"

    def schema(self) -> str:
        return "id long, vec array<int>" if self.options.get("kind") == "ivecs" else "id long, vec array<float>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.kind = options["path"], options.get("kind", "fvecs")
        self.records = int(options.get("records", 65536))

    def partitions(self) -> list[InputPartition]:
        size = os.path.getsize(self.path)
        if not size:
            return []
        with open(self.path, "rb") as f:
            dim = int(np.frombuffer(f.read(4), "<i4")[0])
        n, rest = divmod(size, 4 * (dim + 1))
        if rest:
            raise ValueError("the file's size is not a whole number of records")
        return [_Range(self.path, a, min(self.records, n - a), dim) for a in range(0, n, self.records)]

    def read(self, partition: _Range) -> Iterator[pa.RecordBatch]:
        width = partition.dim + 1
        raw = np.fromfile(partition.path, "<i4", partition.count * width, offset=partition.first * width * 4).reshape(-1, width)
        values = np.ascontiguousarray(raw[:, 1:])
        flat = pa.array(values.ravel() if self.kind == "ivecs" else values.ravel().view("<f4"))
        offsets = pa.array(np.arange(0, len(raw) * partition.dim + 1, partition.dim, dtype=np.int32))
        yield pa.RecordBatch.from_arrays([pa.array(partition.first + np.arange(len(raw))), pa.ListArray.from_arrays(offsets, flat)], names=["id", "vec"])
