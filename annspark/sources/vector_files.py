"""Readers for raw vector files: fvecs, bvecs and ivecs.

Each record is a little-endian 32-bit length and so many 4-byte floats, bytes or
4-byte integers. All records of a file have the same size, so a file splits at
record boundaries and its parts are read in parallel through binaryFile-free
offsets. The files must lie on a path that every executor mounts.
"""

from __future__ import annotations

import glob
import os
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

KINDS = {"fvecs": ("<f4", 4), "bvecs": ("u1", 1), "ivecs": ("<i4", 4)}


class _Part(InputPartition):
    def __init__(self, path: str, kind: str, first: int, count: int, base: int, dim: int):
        self.path, self.kind, self.first, self.count, self.base, self.dim = path, kind, first, count, base, dim


class _Reader(DataSourceReader):
    def __init__(self, path: str, rows: int):
        self.path, self.rows = path, rows

    def partitions(self):
        out, base = [], 0
        for path in sorted(glob.glob(self.path)):
            kind = path.rsplit(".", 1)[-1]
            if kind not in KINDS:
                raise ValueError(f"unknown vector file {path}")
            size = os.path.getsize(path)
            if not size:
                continue
            with open(path, "rb") as f:
                dim = struct.unpack("<i", f.read(4))[0]
            record = 4 + dim * KINDS[kind][1]
            if size % record:
                raise ValueError(f"{path} has a broken record")
            n = size // record
            out += [_Part(path, kind, i, min(self.rows, n - i), base, dim) for i in range(0, n, self.rows)]
            base += n
        return out

    def read(self, part):
        kind, width = KINDS[part.kind]
        record = 4 + part.dim * width
        with open(part.path, "rb") as f:
            f.seek(part.first * record)
            raw = np.frombuffer(f.read(part.count * record), np.uint8).reshape(part.count, record)
        x = np.ascontiguousarray(raw[:, 4:]).view(kind).astype(np.float32)
        ids = np.arange(part.base + part.first, part.base + part.first + part.count)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, part.count * part.dim + 1, part.dim, dtype=np.int32)), pa.array(x.reshape(-1)))
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), lists], ["vec_id", "embedding"])


class VectorFiles(DataSource):
    """spark.read.format("vecs").load(glob): vec_id and embedding; option rowsPerPartition."""

    @classmethod
    def name(cls) -> str:
        return "vecs"

    def schema(self) -> str:
        return "vec_id long, embedding array<float>"

    def reader(self, schema):
        return _Reader(self.options["path"], int(self.options.get("rowsPerPartition", 100_000)))
