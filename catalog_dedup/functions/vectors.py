"""Fixed-point vectors: floor(x * 4096) makes sums exact in every engine and order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SCALE = 4096


def fixed_point(vector: Column) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * SCALE).cast("int"))


def embeddings(df: DataFrame) -> DataFrame:
    """id, vec (array<int>) of the rows of ``embeddings``."""
    return df.select(F.col("vec_id").alias("id"), fixed_point(F.col("embedding")).alias("vec"))


def squared_norm(vec: Column) -> Column:
    return F.aggregate(vec, F.lit(0).cast("long"), lambda a, x: a + x.cast("long") * x)


def seed_order(key: Column) -> Column:
    return F.md5(key.cast("string"))
