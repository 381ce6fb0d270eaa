"""Packed vectors: binary blocks of ids and float32 matrices, with a Python data source that reads them block by block."""

from __future__ import annotations

import struct
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

BLOCK = 4096
_HEAD = "<8sqq"
_MAGIC = b"VBLOCKS1"


def _store(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder) if ":" in folder else (fs.LocalFileSystem(), folder)


def pack(vectors: DataFrame, folder: str) -> str:
    """Write (id, vec) as blocks under ``folder``; a file belongs to the data only if the list of finished files names it."""

    def write(batches):
        import pyarrow as pa

        store, top = _store(folder)
        store.create_dir(top, recursive=True)
        for b in batches:
            for i in range(0, b.num_rows, BLOCK):
                part = b.slice(i, BLOCK)
                x = np.array(part.column(1).to_pylist(), "<f4").reshape(part.num_rows, -1)
                name = f"{uuid.uuid4().hex}.vec"
                with store.open_output_stream(f"{top}/{name}") as out:
                    out.write(struct.pack(_HEAD, _MAGIC, *x.shape) + part.column(0).to_numpy().astype("<i8").tobytes() + x.tobytes())
                yield pa.RecordBatch.from_pydict({"name": [name], "n": [part.num_rows]}, schema=pa.schema([("name", pa.string()), ("n", pa.int64())]))

    vectors.select("id", "vec").mapInArrow(write, "name string, n long").write.parquet(f"{folder}/_files")
    return folder


class PackedVectors(DataSource):
    """Format ``packed_vectors``; option path: a folder written by ``pack``."""

    @classmethod
    def name(cls) -> str:
        return "packed_vectors"

    def schema(self) -> str:
        return "id long, vec array<float>"

    def reader(self, schema) -> DataSourceReader:
        return PackedVectorsReader(self.options["path"])


class PackedVectorsReader(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds

        store, top = _store(self.folder)
        return [InputPartition(n) for n in ds.dataset(f"{top}/_files", filesystem=store, format="parquet", exclude_invalid_files=True).to_table().column("name").to_pylist()]

    def read(self, partition: InputPartition):
        import pyarrow as pa

        store, top = _store(self.folder)
        with store.open_input_file(f"{top}/{partition.value}") as f:
            data = f.read()
        magic, n, d = struct.unpack_from(_HEAD, data)
        if magic != _MAGIC:
            raise ValueError("not a block of vectors")
        at = struct.calcsize(_HEAD)
        x = np.frombuffer(data, "<f4", n * d, at + 8 * n)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * d, pa.int32()), pa.array(x, pa.float32()))
        yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(data, "<i8", n, at)), lists], names=["id", "vec"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PackedVectors)
