"""A Python data source for flat binary vector files: each row is a 32-bit count and that many components.

``spark.dataSource.register(VecsSource)``, then ``spark.read.format("vecs").option("kind", "f4" | "u1" | "i4").load(path)``.
Rows have one width, so a file is cut into row ranges that tasks read independently.
"""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

KINDS = {"f4": ("<f4", 4), "u1": ("u1", 1), "i4": ("<i4", 4)}


class Rows(InputPartition):
    def __init__(self, path: str, start: int, count: int, first: int):
        self.path, self.start, self.count, self.first = path, start, count, first


class VecsReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.kind, self.rows = options["path"], options.get("kind", "f4"), int(options.get("rows", 100_000))

    def partitions(self):
        files = sorted(os.path.join(self.path, f) for f in os.listdir(self.path)) if os.path.isdir(self.path) else [self.path]
        out, first = [], 0
        for f in files:
            size = os.path.getsize(f)
            if not size:
                continue
            dim = int(np.fromfile(f, "<i4", 1)[0])
            n = size // (4 + dim * KINDS[self.kind][1])
            out += [Rows(f, s, min(self.rows, n - s), first + s) for s in range(0, n, self.rows)]
            first += n
        return out or [Rows("", 0, 0, 0)]

    def read(self, part):
        if not part.count:
            return
        dtype, width = KINDS[self.kind]
        dim = int(np.fromfile(part.path, "<i4", 1)[0])
        row = np.dtype([("n", "<i4"), ("v", dtype, dim)])
        data = np.fromfile(part.path, row, part.count, offset=part.start * (4 + dim * width))
        if (data["n"] != dim).any():
            raise ValueError(f"{part.path}: rows of different width")
        v = data["v"].astype(np.float32).reshape(-1)
        off = np.arange(part.count + 1, dtype=np.int32) * dim
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(part.first, part.first + part.count)), pa.ListArray.from_arrays(pa.array(off), pa.array(v))], names=["id", "vec"])


class VecsSource(DataSource):
    @classmethod
    def name(cls):
        return "vecs"

    def schema(self):
        return "id long, vec array<float>"

    def reader(self, schema):
        return VecsReader(self.options)


def write_vecs(rows: np.ndarray, path: str, kind: str = "f4") -> None:
    dtype, _ = KINDS[kind]
    out = np.zeros(len(rows), np.dtype([("n", "<i4"), ("v", dtype, rows.shape[1])]))
    out["n"], out["v"] = rows.shape[1], rows
    out.tofile(path)
