"""A Python data source for vector files of the form that public nearest-neighbour sets come in: for each vector its dimension as a
little-endian 32-bit integer and its components.

    spark.dataSource.register(VectorFiles)
    spark.read.format("vector_files").option("path", "/shared/base.fvecs").load()      # (id long, vec array<float>)

``kind`` is float (4 bytes a component, the default), int (4) or byte (1); ids count from ``first_id``. The file must be readable on the
driver and on every executor under its path; a task reads ``rows_per_task`` vectors at its own place of the file and nothing else.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_TYPES = {"float": "<f4", "int": "<i4", "byte": "u1"}
_SCHEMA = pa.schema([("id", pa.int64()), ("vec", pa.list_(pa.float32()))])
#: Vectors in a batch that a task hands on.
BATCH_ROWS = 4096


@dataclass
class RowRange(InputPartition):
    first: int
    last: int


class VectorFileReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.type = options["path"], _TYPES[options.get("kind", "float")]
        self.step, self.first_id = int(options.get("rows_per_task", 1_000_000)), int(options.get("first_id", 0))
        size = os.path.getsize(self.path)
        with open(self.path, "rb") as f:
            head = f.read(4)
        self.dim = int(np.frombuffer(head, "<i4")[0]) if size else 0
        self.width = 4 + self.dim * np.dtype(self.type).itemsize
        if size and (self.dim <= 0 or size % self.width):
            raise ValueError(f"{self.path} does not hold whole vectors of one dimension")
        self.rows = size // self.width if size else 0

    def partitions(self) -> list[RowRange]:
        return [RowRange(at, min(self.rows, at + self.step)) for at in range(0, self.rows, self.step)] or [RowRange(0, 0)]

    def read(self, partition: RowRange) -> Iterator[pa.RecordBatch]:
        with open(self.path, "rb") as f:
            f.seek(partition.first * self.width)
            for at in range(partition.first, partition.last, BATCH_ROWS):
                n = min(BATCH_ROWS, partition.last - at)
                raw = np.frombuffer(f.read(n * self.width), np.uint8).reshape(n, self.width)
                if (np.ascontiguousarray(raw[:, :4]).view("<i4") != self.dim).any():
                    raise ValueError(f"{self.path} changes its dimension")
                x = np.ascontiguousarray(raw[:, 4:]).view(self.type).astype(np.float32)
                vec = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * self.dim), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(at, at + n) + self.first_id), vec], schema=_SCHEMA)


class VectorFiles(DataSource):
    @classmethod
    def name(cls) -> str:
        return "vector_files"

    def schema(self) -> str:
        return "id long, vec array<float>"

    def reader(self, schema) -> VectorFileReader:
        return VectorFileReader(self.options)


def write(x: np.ndarray, path: str, kind: str = "float") -> None:
    """A matrix as such a file (for tests and exports of bounded sets)."""
    x = np.ascontiguousarray(x, _TYPES[kind])
    head = np.full((len(x), 1), x.shape[1], "<i4").view(np.uint8)
    np.concatenate([head, x.view(np.uint8).reshape(len(x), -1)], axis=1).tofile(path)
