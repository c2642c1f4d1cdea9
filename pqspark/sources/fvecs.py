"""A data source for the common binary vector format: per row a 32-bit count, then that many 32-bit floats."""

from __future__ import annotations

import glob
import os
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


@dataclass
class Span(InputPartition):
    path: str
    first: int
    rows: int
    dim: int


class FvecsSource(DataSource):
    """format("fvecs"): option path is a file or a folder; rows are numbered in order of file name."""

    @classmethod
    def name(cls) -> str:
        return "fvecs"

    def schema(self) -> str:
        return "vec_id long, embedding array<float>"

    def reader(self, schema) -> FvecsReader:
        return FvecsReader(self.options)

    def writer(self, schema, overwrite: bool) -> FvecsWriter:
        return FvecsWriter(self.options["path"])


class FvecsReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = urlparse(options["path"]).path
        self.rows = int(options.get("rowsPerPartition", 100_000))

    def partitions(self) -> list[Span]:
        files = sorted(glob.glob(f"{self.path}/*.fvecs")) if os.path.isdir(self.path) else [self.path]
        out, first = [], 0
        for f in files:
            if os.path.getsize(f) == 0:
                continue
            dim = int(np.fromfile(f, "<i4", 1)[0])
            n = os.path.getsize(f) // (4 * (dim + 1))
            for a in range(0, n, self.rows):
                out.append(Span(f"{f}:{a}", first + a, min(self.rows, n - a), dim))
            first += n
        return out or [Span("", 0, 0, 0)]

    def read(self, partition: Span) -> Iterator[pa.RecordBatch]:
        if not partition.rows:
            return
        path, _, at = partition.path.rpartition(":")
        size = partition.dim + 1
        raw = np.fromfile(path, "<i4", partition.rows * size, offset=int(at) * size * 4).reshape(-1, size)
        if (raw[:, 0] != partition.dim).any():
            raise ValueError("rows differ in length")
        x = np.ascontiguousarray(raw[:, 1:]).view("<f4")
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, partition.dim), pa.int32()), pa.array(x.reshape(-1)))
        ids = pa.array(np.arange(partition.first, partition.first + partition.rows))
        yield pa.RecordBatch.from_arrays([ids, lists], names=["vec_id", "embedding"])


@dataclass
class Done(WriterCommitMessage):
    path: str


class FvecsWriter(DataSourceWriter):
    """One file per task, in the folder that all machines see; ids are not stored."""

    def __init__(self, path: str):
        self.path = urlparse(path).path

    def write(self, iterator) -> Done:
        from pyspark import TaskContext

        os.makedirs(self.path, exist_ok=True)
        name = f"{self.path}/part-{TaskContext.get().partitionId():05d}"
        with open(f"{name}.{TaskContext.get().taskAttemptId()}.tmp", "wb") as f:
            for row in iterator:
                np.array([len(row.embedding)], "<i4").tofile(f)
                np.array(row.embedding, "<f4").tofile(f)
            made = f.name
        os.replace(made, f"{name}.fvecs")
        return Done(f"{name}.fvecs")
