"""Pair classifiers over stored vectors: the decider and, for comparison, a two-tower model."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..nn import train
from ..nn.tape import Tensor, binary_loss
from ..sources.formats import written
from . import metrics


def attach(pairs: DataFrame, vectors: DataFrame, a: str, b: str) -> DataFrame:
    """Vectors of both sides by two equi-joins on the id; a missing vector stays null."""
    side = lambda k, name: vectors.select(F.col("id").alias(k), F.col("vec").alias(name))
    return pairs.join(side("a", a), "a", "left").join(side("b", b), "b", "left")


def cosines(pairs: DataFrame, vectors: DataFrame) -> DataFrame:
    j = attach(pairs, vectors, "va", "vb")
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, v: s + v)
    return j.withColumn("cosine", F.coalesce(dot("va", "vb") / F.sqrt(dot("va", "va") * dot("vb", "vb")), F.lit(0.0))).drop("va", "vb")


def best_cut(scored: DataFrame, score: str = "cosine") -> float:
    """The cut with the best F1 of Match, over scores rounded to thousandths."""
    s = metrics.sweep(scored.withColumn("_s", F.floor(F.col(score) * 1000) / 1000), "_s", "is_match")
    return s.orderBy(F.desc("f1"), F.desc("cut")).first()["cut"]


def macro_f1(scored: DataFrame) -> float:
    return metrics.macro_f1(metrics.class_report(scored, "is_match", "verdict")).first()[0]


def _block(rows: list, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Matrix of vectors, zero where missing, and a column that tells."""
    if isinstance(rows, np.ndarray):
        return rows.astype(float), np.zeros((len(rows), 1))
    out, gone = np.zeros((len(rows), width)), np.zeros((len(rows), 1))
    for k, r in enumerate(rows):
        if r is None:
            gone[k] = 1
        else:
            out[k] = r
    return out, gone


@dataclass
class Decider:
    """One classifier for all leaves. ``raw`` features are the vectors side by side; otherwise their differences and products too.
    A score averages both orders of a pair, so it doesn't depend on the order."""

    weights: dict[str, np.ndarray]
    modalities: tuple[str, ...]
    width: dict[str, int]
    raw: bool = False
    cut: float = 0.5

    @staticmethod
    def features(batch: dict[str, list], modalities: tuple[str, ...], width: dict[str, int], raw: bool, turned: bool) -> np.ndarray:
        parts = []
        for m in modalities:
            (a, ga), (b, gb) = (_block(batch[f"{m}_{s}"], width[m]) for s in ("ba" if turned else "ab"))
            parts += [a, b, ga, gb] + ([] if raw else [np.abs(a - b), a * b, (a * b).sum(1, keepdims=True)])
        return np.hstack(parts)

    @staticmethod
    def logits(w: dict[str, Tensor], x: np.ndarray) -> Tensor:
        h = (Tensor(x) @ w["w1"] + w["c1"]).relu()
        return ((h @ w["w2"] + w["c2"]).relu() @ w["w3"] + w["c3"])[:, 0]

    @classmethod
    def untrained(cls, modalities: tuple[str, ...], width: dict[str, int], raw: bool = False) -> Decider:
        inputs, r = sum((2 * width[m] + 2) if raw else (4 * width[m] + 3) for m in modalities), np.random.default_rng(0)
        w = {"w1": r.normal(0, inputs**-0.5, (inputs, 64)), "c1": np.zeros(64), "w2": r.normal(0, 0.12, (64, 32)), "c2": np.zeros(32), "w3": r.normal(0, 0.18, (32, 1)), "c3": np.zeros(1)}
        return cls(w, modalities, width, raw)

    @classmethod
    def fit(cls, pairs: DataFrame, text: DataFrame | None, image: DataFrame | None, steps: int = 40, lr: float = 1e-2, modalities: tuple[str, ...] = ("text", "image"), raw: bool = False, share: float = 1.0) -> Decider:
        rows, width = pairs.select("a", "b", "is_match"), {}
        for m, v in (("text", text), ("image", image)):
            if m in modalities:
                rows = attach(rows, v, f"{m}_a", f"{m}_b")
                width[m] = v.select(F.size("vec")).first()[0]
        rows = written(rows)
        n = rows.agg(F.count("*").alias("n"), F.sum(F.col("is_match").cast("int")).alias("p")).first()
        balance = n["p"] / max(n["n"] - n["p"], 1)
        w = cls.untrained(modalities, width, raw).weights

        def loss(t: dict[str, Tensor], batch: dict[str, list], seed: int):
            y = np.array(batch["is_match"], float)
            weight = np.where(y > 0, 1.0, balance)
            both = [binary_loss(cls.logits(t, cls.features(batch, modalities, width, raw, turned)), y, weight) for turned in (False, True)]
            return both[0] + both[1], 2 * len(y)

        train.fit(rows, "a", w, loss, steps, lr, share=share)
        return cls(w, modalities, width, raw)

    def score(self, pairs: DataFrame, text: DataFrame | None, image: DataFrame | None) -> DataFrame:
        """a, b, is_match, confidence and verdict of pairs."""
        rows = pairs.select("a", "b", "is_match")
        for m, v in (("text", text), ("image", image)):
            if m in self.modalities:
                rows = attach(rows, v, f"{m}_a", f"{m}_b")
        me = self

        def run(batches):
            import pyarrow as pa

            for b in batches:
                if not b.num_rows:
                    continue
                d = train.columns(b)
                w = {k: Tensor(v) for k, v in me.weights.items()}
                z = sum(me.logits(w, me.features(d, me.modalities, me.width, me.raw, turned)).data for turned in (False, True)) / 2
                yield pa.RecordBatch.from_pydict({"a": d["a"], "b": d["b"], "is_match": d["is_match"], "confidence": 1 / (1 + np.exp(-np.clip(z, -60, 60)))})

        out = rows.mapInArrow(run, "a long, b long, is_match boolean, confidence double")
        return out.withColumn("verdict", F.col("confidence") >= self.cut)


@dataclass
class Siamese:
    """Both sides through one tower; contrastive loss on the distance; verdict by a cut fitted on the training pairs."""

    weights: dict[str, np.ndarray]
    cut: float

    @classmethod
    def fit(cls, pairs: DataFrame, vectors: DataFrame, steps: int = 20, lr: float = 1e-2, margin: float = 1.0) -> Siamese:
        rows = written(attach(pairs.select("a", "b", "is_match"), vectors, "va", "vb").filter("va IS NOT NULL AND vb IS NOT NULL"))
        d = vectors.select(F.size("vec")).first()[0]
        w = {"tower": np.random.default_rng(1).normal(0, d**-0.5, (d, 64))}

        def loss(t: dict[str, Tensor], batch: dict[str, list], seed: int):
            a, b = (Tensor(np.array(batch[k])) @ t["tower"] for k in ("va", "vb"))
            gap = ((a - b) * (a - b)).sum(1)
            y = np.array(batch["is_match"], float)
            far = ((gap + 1e-9).power(0.5) * -1.0 + margin).relu()
            return (gap * y + far * far * (1 - y)).sum(), len(y)

        train.fit(rows, "a", w, loss, steps, lr)
        me = cls(w, 0.0)
        me.cut = best_cut(me.score(pairs, vectors), "confidence")
        return me

    def score(self, pairs: DataFrame, vectors: DataFrame) -> DataFrame:
        rows = attach(pairs.select("a", "b", "is_match"), vectors, "va", "vb").filter("va IS NOT NULL AND vb IS NOT NULL")
        tower = self.weights["tower"]

        def run(batches):
            import pyarrow as pa

            for b in batches:
                if b.num_rows:
                    d = train.columns(b)
                    gap = (((np.array(d["va"]) - np.array(d["vb"])) @ tower) ** 2).sum(1)
                    yield pa.RecordBatch.from_pydict({"a": d["a"], "b": d["b"], "is_match": d["is_match"], "confidence": np.exp(-gap)})

        return rows.mapInArrow(run, "a long, b long, is_match boolean, confidence double").withColumn("verdict", F.col("confidence") >= self.cut)
