"""Principal components from one pass of block sums."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import matrix

#: Matrices that meet in one task of the sum.
FAN_IN = 16


def gram(vectors: DataFrame) -> DataFrame:
    """i, j, s: sums of products for i <= j; one matrix a task, added up by a shuffle of at most tasks x d^2 / 2 rows."""

    def run(batches):
        import pyarrow as pa

        total = None
        for b in batches:
            x = matrix(b.column(0))
            if len(x):
                total = x.T @ x + (0 if total is None else total)
        if total is not None:
            i, j = np.triu_indices(len(total))
            yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(total[i, j])], names=["i", "j", "s"])

    return vectors.select("vec").mapInArrow(run, "i int, j int, s double").groupBy("i", "j").agg(F.sum("s").alias("s"))


def moments(vectors: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """Count, mean and covariance from the products of (1, x) with itself in one pass: a task hands on one matrix, matrices are added
    in a tree, and FAN_IN of them at most reach the driver."""

    def run(batches):
        import pyarrow as pa

        total = None
        for b in batches:
            x = matrix(b.column(0))
            if len(x):
                x = np.hstack([np.ones((len(x), 1)), x])
                total = x.T @ x + (0 if total is None else total)
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["g"])

    def add(batches):
        import pyarrow as pa

        total = None
        for b in batches:
            for g in b.column(0).to_pylist():
                total = np.frombuffer(g) + (0 if total is None else total)
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["g"])

    parts, tasks = vectors.select("vec").mapInArrow(run, "g binary"), vectors.rdd.getNumPartitions()
    while tasks > FAN_IN:
        tasks = -(-tasks // FAN_IN)
        parts = parts.repartition(tasks).mapInArrow(add, "g binary")
    found = sorted(bytes(r["g"]) for r in parts.collect())  # the order of arrival doesn't matter
    if not found:
        return 0, np.zeros(0), np.zeros((0, 0))
    g = sum(np.frombuffer(x) for x in found)
    g = g.reshape(int(len(g) ** 0.5), -1)
    n = int(round(g[0, 0]))
    mean = g[0, 1:] / max(n, 1)
    return n, mean, g[1:, 1:] / max(n, 1) - np.outer(mean, mean)


def fit(vectors: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """mean, components (k x d, the largest entry of each positive) and the variances of all directions, falling."""
    _, mean, cov = moments(vectors)
    values, v = np.linalg.eigh(cov)
    order = np.argsort(values)[::-1]
    c = v[:, order[:k]].T
    c *= np.sign(c[np.arange(len(c)), np.abs(c).argmax(1)])[:, None]
    return mean, c, values[order]


def project(vectors: DataFrame, mean: np.ndarray, components: np.ndarray) -> DataFrame:
    def run(batches):
        import pyarrow as pa

        for b in batches:
            y = (matrix(b.column(1)) - mean) @ components.T if b.num_rows else np.zeros((0, len(components)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, y.size + 1, len(components)), pa.int32()), pa.array(y.ravel()))], names=["id", "vec"])

    return vectors.select("id", "vec").mapInArrow(run, "id long, vec array<double>")
