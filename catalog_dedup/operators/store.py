"""A keyed collection of vectors or texts with continuous changes: base and delta files under one folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class Store:
    """Rows are (id, version, deleted, payload columns). A batch is written once under its own name and seen only when it is complete,
    so replays change nothing; reading takes the newest version of each id and drops deleted ones; compaction writes one base."""

    def __init__(self, spark: SparkSession, path: str, schema: str):
        self.spark, self.path, self.schema = spark, path.rstrip("/"), f"id long, version long, deleted boolean, {schema}"

    def _batches(self) -> list[str]:
        fs_path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = fs_path.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(fs_path):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(fs_path)]
        done = [n for n in names if fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS"))]
        bases = [n for n in done if n.startswith("base-")]
        last = max(bases, default="")
        return [n for n in done if n == last or (n.startswith("delta-") and n[6:] > last[5:])]

    def upsert(self, rows: DataFrame, batch: int) -> None:
        """Add or change rows (id, version and payload; deleted where given). The same batch number again is ignored."""
        name = f"delta-{batch:012d}"
        if name in self._batches():
            return
        if "deleted" not in rows.columns:
            rows = rows.withColumn("deleted", F.lit(False))
        wanted = [c.strip().split(" ")[0] for c in self.schema.split(",")]
        rows.select(*wanted).write.mode("overwrite").parquet(f"{self.path}/{name}")

    def delete(self, ids: DataFrame, version: int, batch: int) -> None:
        empty = [F.lit(None).cast(c.strip().split(" ", 1)[1]).alias(c.strip().split(" ")[0]) for c in self.schema.split(",")[3:]]
        self.upsert(ids.select("id", F.lit(version).cast("long").alias("version"), F.lit(True).alias("deleted"), *empty), batch)

    def read(self) -> DataFrame:
        found = self._batches()
        if not found:
            return self.spark.createDataFrame([], self.schema).drop("deleted")
        rows = self.spark.read.schema(self.schema).parquet(*[f"{self.path}/{n}" for n in found])
        names = [c for c in rows.columns if c != "id"]
        newest = rows.groupBy("id").agg(F.max_by(F.struct(*names), "version").alias("x"))
        return newest.select("id", "x.*").filter("NOT deleted").drop("deleted")

    def compact(self, batch: int) -> None:
        """One base of all that is alive; older batches are no longer read."""
        wanted = [c.strip().split(" ")[0] for c in self.schema.split(",")]
        self.read().withColumn("deleted", F.lit(False)).select(*wanted).write.mode("overwrite").parquet(f"{self.path}/base-{batch:012d}")

    def sink(self, batch: DataFrame, number: int) -> None:
        """For foreachBatch of a stream."""
        self.upsert(batch, number)
