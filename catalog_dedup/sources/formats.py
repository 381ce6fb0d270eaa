"""Exchange formats."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame


def scratch(spark) -> str:
    """A new folder name in the shared checkpoint folder of the session. Where none is set, in a temporary one if everything runs in
    one process (tests); on a cluster that is an error, as executors would not see each other's files."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir names no folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="catalog_dedup_")
        spark.sparkContext.setCheckpointDir(folder)
    return f"{folder.rstrip('/')}/{uuid.uuid4().hex}"


def open_store(folder: str):
    """(file system, path) of a folder given as URI or local path."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """``df`` written in the format and read with its own schema (nothing is inferred)."""
    path = scratch(df.sparkSession)
    options = {"header": "true"} if kind == "csv" else {}
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.format(kind).options(**options).schema(df.schema).load(path)


def written(df: DataFrame) -> DataFrame:
    """``df`` as a Parquet table in the shared folder: cuts the lineage of iterative methods."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
