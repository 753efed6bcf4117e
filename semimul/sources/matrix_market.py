"""Matrix exchange text files (coordinate form) as a Python data source, for reading and writing (row, col, v)."""

from __future__ import annotations

import glob
import os

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


class _Part(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        return [_Part(p) for p in sorted(glob.glob(os.path.join(self.path, "*.mtx")) if os.path.isdir(self.path) else [self.path])]

    def read(self, partition):
        with open(partition.value) as f:
            head = f.readline().lower()
            symmetric, whole = "symmetric" in head, "integer" in head or "pattern" in head
            sized = False
            for line in f:
                if line.startswith("%") or not line.strip():
                    continue
                parts = line.split()
                if not sized:
                    sized = True
                    continue
                row, col = int(parts[0]), int(parts[1])
                v = (int(parts[2]) if whole else float(parts[2])) if len(parts) > 2 else 1
                yield row, col, float(v)
                if symmetric and row != col:
                    yield col, row, float(v)


class _Writer(DataSourceWriter):
    def __init__(self, path: str, overwrite: bool):
        self.path = path
        os.makedirs(path, exist_ok=True)
        if overwrite:
            for p in glob.glob(os.path.join(path, "*.mtx")):
                os.remove(p)

    def write(self, iterator):
        from pyspark import TaskContext

        rows = [(r[0], r[1], r[2]) for r in iterator]
        name = os.path.join(self.path, f"part-{TaskContext.get().partitionId():05d}.mtx")
        with open(name + ".tmp", "w") as f:
            f.write("%%MatrixMarket matrix coordinate real general\n")
            f.write(f"{max((r[0] for r in rows), default=0)} {max((r[1] for r in rows), default=0)} {len(rows)}\n")
            f.writelines(f"{a} {b} {v!r}\n" for a, b, v in rows)
        os.replace(name + ".tmp", name)
        return WriterCommitMessage()


class MatrixMarket(DataSource):
    """format("matrix_market"): a file, or a folder of .mtx files in a file system that driver and executors share."""

    @classmethod
    def name(cls):
        return "matrix_market"

    def schema(self):
        return "row long, col long, v double"

    def reader(self, schema):
        return _Reader(self.options["path"])

    def writer(self, schema, overwrite):
        return _Writer(self.options["path"], overwrite)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(MatrixMarket)
