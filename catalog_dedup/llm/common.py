"""Shared folder, written intermediate tables and column handling for the training-data operators."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid
from collections.abc import Callable
from itertools import count

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Java and RE2 pattern of the six ASCII white-space characters that part words.
SPACE = r"[\x20\x09-\x0D]+"
#: Rows up to which a table keyed by language, source or the like is broadcast; beyond it, joins shuffle.
BROADCAST_ROWS = 100_000
#: Bytes of rows in an Arrow batch, about: Spark's own 64 MB are held several times over, in the JVM and in Python, by each task.
BATCH_BYTES = 4 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir. Where it is unset, a temporary one if everything runs in one
    process (tests); on a cluster executors could not see each other's files there, so that is an error."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir names no folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="catalog_dedup_")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def open_store(folder: str):
    """(file system, path) of a folder given as URI or local path."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)


_WRITES = count(1)


def stash(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: later jobs start from it, and a lost executor loses nothing.
    Iterative methods come here again and again, so what is left of earlier plans and shuffles is let go now and then."""
    spark = df.sparkSession
    if next(_WRITES) % 5 == 0:
        release(spark)
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stashed = path
    return out


def discard(*stashed: DataFrame) -> None:
    """Remove stashed tables that nothing will read again."""
    for df in stashed:
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._stashed)
        path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop shuffle files of finished jobs now and not when the driver happens to collect garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` (already stashed, so counting is cheap) marked for broadcast if it has at most ``rows`` rows, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def words(text: Column) -> Column:
    """The runs of other characters between ASCII white space, in order; null gives an empty array."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE), "")


def others(keep: list[str], made: list[str]) -> list[str]:
    """The names in ``keep``, once each, but those of the columns ``made``, whatever their case."""
    gone = {n.lower() for n in made}
    return [c for c in dict.fromkeys(keep) if c.lower() not in gone]


def carried(keep: list[str]) -> Column:
    """``keep`` columns as one struct, so that their names meet no other name until ``unpacked``."""
    return F.struct(*[F.col(f"`{c}`") for c in keep]) if keep else F.lit(None).cast("int")


def unpacked(row: str, keep: list[str]) -> list[Column]:
    return [F.col(row)[c].alias(c) for c in keep]


def map_text(df: DataFrame, keep: list[str], fields: list[tuple[str, T.DataType]], fn: Callable[[list], list], binary: bool = False) -> DataFrame:
    """``keep`` columns of ``df`` and the new ``fields``, which ``fn`` makes from a batch's whole texts (a list of str or
    bytes with None for null) as a list of arrays. Rows stay where they are; a batch is one Arrow record batch of about ``BATCH_BYTES``.
    A column of ``keep`` named like a new field is replaced by it; all other names are free. Text that is kept travels once."""
    keep = others(keep, [n for n, _ in fields])
    kind, held = T.BinaryType() if binary else T.StringType(), "text" in keep and df.schema["text"].dataType
    at = keep.index("text") if held == kind else None
    rows = df.select(carried(keep).alias("row"), *([F.col("text").cast(kind).alias("text")] if at is None else []))
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", f"{BATCH_BYTES}b")
    schema = T.StructType([*(rows.schema["row"].dataType.fields if keep else []), *[T.StructField(n, t) for n, t in fields]])
    names = schema.fieldNames()

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for i in range(0, b.num_rows, 1024):  # bounds what Python objects hold at once
                part = b.slice(i, 1024)
                kept = part.column(0).flatten() if keep else []
                made = [a if isinstance(a, pa.Array) else pa.array(a) for a in fn((part.column(1) if at is None else kept[at]).to_pylist())]
                yield pa.RecordBatch.from_arrays([*kept, *made], names=names)

    return rows.mapInArrow(run, schema)


def remainder(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; a null id counts as empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % parts


def uniform(*columns: Column) -> Column:
    """A hash-random number in [0, 1) of the columns."""
    return F.shiftrightunsigned(F.xxhash64(F.lit("uniform"), *columns), 11) / float(1 << 53)
