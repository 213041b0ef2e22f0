"""A Python data source for vector files: each record a little-endian int32 length and that many 4-byte values."""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class VectorFile(DataSource):
    """spark.read.format("packvec_vectors").option("dim", 64).option("kind", "float" | "int").load(path).

    The path must be readable on the executors as a file (one file, or a folder of files).
    """

    @classmethod
    def name(cls) -> str:
        return "packvec_vectors"

    def schema(self) -> str:
        return f"vec_id long, embedding array<{'int' if self.options.get('kind') == 'int' else 'float'}>"

    def reader(self, schema) -> DataSourceReader:
        return VectorFileReader(self.options)


class VectorFileReader(DataSourceReader):
    def __init__(self, options):
        self.dim, self.path = int(options["dim"]), options["path"]
        self.kind = "<i4" if options.get("kind") == "int" else "<f4"
        self.rows = int(options.get("rows", 100_000))

    def partitions(self) -> list[InputPartition]:
        names = [self.path] if os.path.isfile(self.path) else sorted(os.path.join(self.path, n) for n in os.listdir(self.path))
        out, first = [], 0
        for n in names:
            total = os.path.getsize(n) // (4 * (self.dim + 1))
            out += [InputPartition((n, at, min(self.rows, total - at), first + at)) for at in range(0, total, self.rows)]
            first += total
        return out

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        name, at, n, first = partition.value
        width = self.dim + 1
        raw = np.fromfile(name, "<i4", n * width, offset=4 * width * at).reshape(n, width)
        if not (raw[:, 0] == self.dim).all():
            raise ValueError(f"{name}: a record's length is not {self.dim}")
        values = np.ascontiguousarray(raw[:, 1:]).view(self.kind).ravel()
        lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * self.dim), pa.array(values))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(first, first + n)), lists], names=["vec_id", "embedding"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(VectorFile)


def write_vectors(rows: np.ndarray, path: str) -> None:
    """One vector file from a matrix; for tests and exports of small results."""
    rows = np.ascontiguousarray(rows)
    kind = "<i4" if rows.dtype.kind in "iu" else "<f4"
    body = rows.astype(kind).view("<i4").reshape(len(rows), -1)
    np.hstack([np.full((len(rows), 1), rows.shape[1], "<i4"), body]).astype("<i4").tofile(path)
