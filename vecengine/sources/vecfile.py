"""Vector files: every row is its length as a 32-bit integer, then its components.

``spark.dataSource.register(VecFile)``, then ``spark.read.format("vecfile")``
with the options path (readable on all executors), kind (float, int or byte)
and rows (rows of a partition).
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Bytes of a component by kind of file.
KINDS = {"float": np.dtype("<f4"), "int": np.dtype("<i4"), "byte": np.dtype("u1")}


class Range(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))
        self.first, self.last = first, last


class VecFile(DataSource):
    @classmethod
    def name(cls) -> str:
        return "vecfile"

    def schema(self) -> str:
        return "id long, vec array<double>"

    def reader(self, schema) -> DataSourceReader:
        return Reader(self.options)


class Reader(DataSourceReader):
    def __init__(self, options):
        self.path, self.kind = options["path"], KINDS[options.get("kind", "float")]
        self.rows = int(options.get("rows", 100_000))

    def _stride(self) -> int:
        with open(self.path, "rb") as f:
            head = f.read(4)
        return 4 + int(np.frombuffer(head, "<i4")[0]) * self.kind.itemsize if head else 0

    def partitions(self) -> list[Range]:
        stride = self._stride()
        size = os.path.getsize(self.path)
        if stride and size % stride:
            raise ValueError("the file does not hold whole rows of one length")
        n = size // stride if stride else 0
        return [Range(a, min(n, a + self.rows)) for a in range(0, n, self.rows)] or [Range(0, 0)]

    def read(self, partition: Range) -> Iterator[pa.RecordBatch]:
        stride, at = self._stride(), partition.first
        while at < partition.last:
            n = min(8192, partition.last - at)
            with open(self.path, "rb") as f:
                f.seek(at * stride)
                raw = np.frombuffer(f.read(n * stride), np.uint8).reshape(n, stride)
            x = np.ascontiguousarray(raw[:, 4:]).view(self.kind).astype(np.float64)
            ids = pa.array(np.arange(at, at + n))
            yield pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32), pa.array(x.ravel()))], ["id", "vec"])
            at += n


def write_vecfile(x: np.ndarray, path: str, kind: str = "float") -> None:
    """Rows of a matrix as a vector file."""
    body = np.ascontiguousarray(x, KINDS[kind]).view(np.uint8).reshape(len(x), -1)
    head = np.full(len(x), x.shape[1], "<i4").view(np.uint8).reshape(len(x), 4)
    np.concatenate((head, body), axis=1).tofile(path)
