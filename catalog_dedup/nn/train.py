"""Synchronous data-parallel training: weights go out with the task, gradients come back summed."""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tape import Tensor

#: Partial gradients that meet in one task of the first level of the sum; the driver gets as many rows as tasks remain.
FAN_IN = 16
#: Rows that are worth a task of their own.
TASK_ROWS = 2048


class AdamW:
    """Adaptive moments with bias correction; decay acts on weights apart from the adaptive step."""

    def __init__(self, decay: float = 0.01, b1: float = 0.9, b2: float = 0.999):
        self.decay, self.b1, self.b2, self.t = decay, b1, b2, 0
        self.m: dict[str, np.ndarray] = {}
        self.v: dict[str, np.ndarray] = {}

    def step(self, weights: dict[str, np.ndarray], grads: dict[str, np.ndarray], lr: float) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = self.b1 * self.m.get(k, 0) + (1 - self.b1) * g
            self.v[k] = self.b2 * self.v.get(k, 0) + (1 - self.b2) * g * g
            m, v = self.m[k] / (1 - self.b1**self.t), self.v[k] / (1 - self.b2**self.t)
            weights[k] = weights[k] - lr * (m / (np.sqrt(v) + 1e-8) + self.decay * weights[k])


def rate(step: int, steps: int, lr: float, schedule: str = "cosine") -> float:
    return lr * (1 + math.cos(math.pi * step / steps)) / 2 if schedule == "cosine" else lr


Loss = Callable[[dict[str, Tensor], dict[str, list], int], tuple[Tensor, int]]


def columns(batch) -> dict[str, list]:
    """Columns of a batch: lists of equally many numbers without nulls as one matrix, everything else as Python lists."""
    import pyarrow as pa

    out = {}
    for name, c in zip(batch.schema.names, batch.columns, strict=True):
        width = {len(c[0])} if pa.types.is_list(c.type) and len(c) and c.null_count == 0 else set()
        if width and c.flatten().null_count == 0 and (c.value_lengths().to_numpy(zero_copy_only=False) == (n := width.pop())).all() and n:
            out[name] = c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), n)
        else:
            out[name] = c.to_pylist()
    return out


def gradients(rows: DataFrame, weights: dict[str, np.ndarray], loss: Loss, seed: int) -> tuple[float, int, dict[str, np.ndarray]]:
    """Loss sum, count and gradient sums over all rows."""

    def run(batches):
        import pyarrow as pa

        total, n, grads = 0.0, 0, {}
        for b in batches:
            if not b.num_rows:
                continue
            w = {k: Tensor(v) for k, v in weights.items()}
            value, count = loss(w, columns(b), seed)
            value.backward()
            total, n = total + float(value.data), n + count
            for k, t in w.items():
                if t.grad is not None:
                    grads[k] = grads[k] + t.grad if k in grads else t.grad
        if n:
            yield pa.RecordBatch.from_pydict({"loss": [total], "n": [n], "g": [pickle.dumps(grads)]}, schema=pa.schema([("loss", pa.float64()), ("n", pa.int64()), ("g", pa.binary())]))

    def add(batches):
        import pyarrow as pa

        total, n, grads = 0.0, 0, {}
        for b in batches:
            for r in b.to_pylist():
                total, n = total + r["loss"], n + r["n"]
                for k, g in pickle.loads(r["g"]).items():
                    grads[k] = grads[k] + g if k in grads else g
        if n:
            yield pa.RecordBatch.from_pydict({"loss": [total], "n": [n], "g": [pickle.dumps(grads)]}, schema=pa.schema([("loss", pa.float64()), ("n", pa.int64()), ("g", pa.binary())]))

    parts = rows.mapInArrow(run, "loss double, n long, g binary")
    tasks = rows.rdd.getNumPartitions()
    while tasks > FAN_IN:
        tasks = -(-tasks // FAN_IN)
        parts = parts.repartition(tasks).mapInArrow(add, "loss double, n long, g binary")
    total, n, grads = 0.0, 0, {}
    for r in sorted(parts.collect(), key=lambda r: (r["n"], r["loss"])):  # the order of arrival doesn't matter
        total, n = total + r["loss"], n + r["n"]
        for k, g in pickle.loads(bytes(r["g"])).items():
            grads[k] = grads[k] + g if k in grads else g
    return total, n, grads


def fit(rows: DataFrame, key: str, weights: dict[str, np.ndarray], loss: Loss, steps: int, lr: float = 1e-4, schedule: str = "cosine", share: float = 1.0, decay: float = 0.01) -> list[float]:
    """Train ``weights`` in place; returns the mean loss of every step. A step sees the share of rows that a hash of key and step picks."""
    optimiser, curve = AdamW(decay), []
    rows = rows.coalesce(max(1, -(-rows.count() // TASK_ROWS)))  # small samples need no more tasks; large ones keep theirs
    for t in range(steps):
        part = rows if share >= 1 else rows.filter(F.pmod(F.xxhash64(key, F.lit(t)), F.lit(1 << 20)) < int(share * (1 << 20)))
        total, n, grads = gradients(part, weights, loss, t)
        if n:
            optimiser.step(weights, {k: g / n for k, g in grads.items()}, rate(t, steps, lr, schedule))
            curve.append(total / n)
    return curve


def evaluate(rows: DataFrame, weights: dict[str, np.ndarray], loss: Loss, seed: int = 0) -> float:
    """Mean loss over all rows."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            if b.num_rows:
                value, count = loss({k: Tensor(v) for k, v in weights.items()}, columns(b), seed)
                yield pa.RecordBatch.from_pydict({"loss": [float(value.data)], "n": [count]}, schema=pa.schema([("loss", pa.float64()), ("n", pa.int64())]))

    r = rows.mapInArrow(run, "loss double, n long").agg(F.sum("loss").alias("s"), F.sum("n").alias("n")).first()
    return r["s"] / r["n"] if r["n"] else float("nan")
