"""Python data sources: raw row-major arrays, read by ranges of planes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _opened(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path, with or without a scheme, and the path within it."""
    return fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


class Planes(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class RawFieldReader(DataSourceReader):
    """One partition per run of planes; a task seeks to its bytes and reads nothing else."""

    def __init__(self, options: dict):
        self.path = options["path"]
        self.shape = tuple(int(n) for n in options["shape"].split("x"))
        self.dtype = np.dtype(options.get("dtype", "<f8"))
        self.planes = int(options.get("planes", "16"))

    def partitions(self):
        return [Planes(a, min(a + self.planes, self.shape[0])) for a in range(0, self.shape[0], self.planes)]

    def read(self, part: Planes):
        _, ny, nz = self.shape
        place, path = _opened(self.path)
        with place.open_input_file(path) as f:
            size = (part.last - part.first) * ny * nz * self.dtype.itemsize
            v = np.frombuffer(f.read_at(size, part.first * ny * nz * self.dtype.itemsize), self.dtype)
        i = np.arange(len(v))
        yield pa.RecordBatch.from_arrays([pa.array((part.first + i // (ny * nz)).astype(np.int32)), pa.array((i // nz % ny).astype(np.int32)), pa.array((i % nz).astype(np.int32)), pa.array(v.astype(np.float64))], names=["x", "y", "z", "v"])


class RawField(DataSource):
    """``spark.read.format("rawfield").option("shape", "64x64x64").option("dtype", "<f4").load(path)``; the file must be readable by every task."""

    @classmethod
    def name(cls):
        return "rawfield"

    def schema(self):
        return "x int, y int, z int, v double"

    def reader(self, schema):
        return RawFieldReader(self.options)


class PacketFile(InputPartition):
    def __init__(self, path: str, level: int):
        self.path, self.level = path, level


class PacketReader(DataSourceReader):
    """One partition per file of a packet store; folders of unwanted levels are not opened."""

    def __init__(self, options: dict):
        self.path = options["path"]
        wanted = options.get("levels")
        self.levels = None if wanted is None else {int(k) for k in wanted.split(",")}

    def partitions(self):
        place, root = _opened(self.path)
        found = []
        for info in place.get_file_info(fs.FileSelector(root, recursive=True)):
            folder = info.path.rsplit("/", 2)[-2]
            if info.path.endswith(".parquet") and folder.startswith("level="):
                level = int(folder.removeprefix("level="))
                if self.levels is None or level in self.levels:
                    found.append(PacketFile(info.path, level))
        return found

    def read(self, part: PacketFile):
        import pyarrow.parquet as pq

        from .codec.apply import coordinates
        from .engine import _decoded

        place, _ = _opened(self.path)
        with place.open_input_file(part.path) as f:
            for batch in pq.ParquetFile(f).iter_batches(batch_size=1, columns=["keys", "body", "raw_bytes", "settings"]):
                for row in batch.to_pylist():
                    _, nby, nbz, keys, vals = _decoded(row)
                    side = vals.shape[1]
                    inner = np.stack(np.meshgrid(*[np.arange(side)] * 3, indexing="ij"), axis=-1).reshape(1, -1, 3)
                    at = (coordinates(keys, nby, nbz)[:, None, :] * side + inner).reshape(-1, 3).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), part.level, np.int32)), *(pa.array(at[:, k]) for k in range(3)), pa.array(vals.ravel())], names=["level", "x", "y", "z", "v"])


class Packets(DataSource):
    """``spark.read.format("packets").option("levels", "0,1").load(path)``: the decoded cells of a packet store."""

    @classmethod
    def name(cls):
        return "packets"

    def schema(self):
        return "level int, x int, y int, z int, v double"

    def reader(self, schema):
        return PacketReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(RawField)
    spark.dataSource.register(Packets)
