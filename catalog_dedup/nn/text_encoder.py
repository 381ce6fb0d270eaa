"""Titles to 128-d vectors: Transformer backbones, compression of the sentence token, and masked-token training.

Miniatures in numpy with weights from a seed: they show how the variants compare, not what pretrained models reach.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as tx
from . import train
from .tape import Tensor, concat, conv1d, cross_entropy

PAD, MASK, SENTENCE, FIRST_WORD = 0, 1, 2, 3


@dataclass(frozen=True)
class TextEncoder:
    """kind: cls (last layer's sentence token) or multilayer (chosen layers and the last, convolved); backbone: full, conv (every
    second block mixes by convolution) or distilled (half the layers); head: mlm, leaf (category) or, for encoding, none."""

    kind: str = "multilayer"
    backbone: str = "full"
    layers: tuple[int, ...] = (1, 3, 5, 7, 9, 11)
    depth: int = 12
    width: int = 32
    heads: int = 2
    vocab: int = 512
    length: int = 32
    dim: int = 128
    leaves: int = 0

    @property
    def blocks(self) -> int:
        return self.depth // 2 if self.backbone == "distilled" else self.depth

    def taps(self) -> list[int]:
        if any(i >= self.blocks for i in self.layers):
            raise ValueError(f"layers {self.layers} of a backbone with {self.blocks} blocks")
        return list(self.layers)

    def weights(self, seed: int = 0) -> dict[str, np.ndarray]:
        r, h = np.random.default_rng(seed), self.width
        mat = lambda a, b, s=None: r.normal(0, s or a**-0.5, (a, b))
        w = {"tok": mat(self.vocab, h, 0.1), "pos": mat(self.length + 1, h, 0.1)}
        for i in range(self.blocks):
            if self._mixes(i):
                w[f"b{i}conv"] = mat(3 * h, h)
            else:
                w |= {f"b{i}{k}": mat(h, h) for k in "qkvo"}
            w |= {f"b{i}up": mat(h, 2 * h), f"b{i}down": mat(2 * h, h, 0.3 * (2 * h) ** -0.5)}
        if self.kind == "multilayer":
            c = h * (len(self.taps()) + 1)
            w |= {"conv1": mat(3 * c, h), "conv2": mat(3 * h, h), "compress": mat(h, self.dim)}
        else:
            w["compress"] = mat(h, self.dim)
        w |= {"spread": mat(self.dim, self.length * 8), "where": mat(self.length, 8, 0.3), "logits": mat(8, self.vocab)}
        if self.leaves:
            w["leaf"] = mat(self.dim, self.leaves)
        return w

    def _mixes(self, i: int) -> bool:
        return self.backbone == "conv" and i % 2 == 1

    def hidden(self, w: dict[str, Tensor], ids: np.ndarray) -> list[Tensor]:
        """Output of every block for ids (batch, 1 + length), the sentence token first."""
        h, heads = self.width, self.heads
        x = w["tok"][ids] + (w["pos"] if ids.shape[1] == self.length + 1 else w["pos"][: ids.shape[1]])
        away = Tensor(np.where(ids[:, None, None, :] == PAD, -1e9, 0.0))
        out = []
        for i in range(self.blocks):
            y = x.norm()
            if self._mixes(i):
                x = x + conv1d(y, w[f"b{i}conv"])
            else:
                b, n, _ = y.shape
                q, k, v = ((y @ w[f"b{i}{z}"]).reshape(b, n, heads, h // heads).swap(1, 2) for z in "qkv")
                a = ((q @ k.swap(2, 3)) * (h // heads) ** -0.5 + away).softmax()
                x = x + (a @ v).swap(1, 2).reshape(b, n, h) @ w[f"b{i}o"]
            x = x + (x.norm() @ w[f"b{i}up"]).relu() @ w[f"b{i}down"]
            out.append(x)
        return out

    def vector(self, w: dict[str, Tensor], ids: np.ndarray) -> Tensor:
        layers = self.hidden(w, ids)
        if self.kind == "multilayer":
            y = concat([layers[i].norm() for i in self.taps()] + [layers[-1].norm()], 2)
            y = conv1d(conv1d(y, w["conv1"]).relu(), w["conv2"])[:, 0]
        else:
            y = layers[-1][:, 0].norm()
        return (y @ w["compress"]).norm().tanh()

    def mlm(self, w: dict[str, Tensor], batch: dict[str, list], seed: int) -> tuple[Tensor, int]:
        """Masked tokens predicted from the compressed vector alone, spread over positions again."""
        ids = self.pad(batch["ids"])
        hide = _chance(np.array(batch["key"], np.uint64), ids.shape[1], seed) < 0.15
        hide &= ids >= FIRST_WORD
        v = self.vector(w, np.where(hide, MASK, ids))
        spread = (v @ w["spread"]).reshape(len(ids), self.length, 8) + w["where"]
        row, col = np.nonzero(hide[:, 1:])
        if not len(row):
            return v.sum() * 0.0, 0
        return cross_entropy(spread[row, col].tanh() @ w["logits"], ids[:, 1:][row, col]), len(row)

    def leaf(self, w: dict[str, Tensor], batch: dict[str, list], seed: int) -> tuple[Tensor, int]:
        """Supervised adaptation: the leaf category from the vector."""
        v = self.vector(w, self.pad(batch["ids"]))
        return cross_entropy(v @ w["leaf"], np.array(batch["leaf"])), len(batch["leaf"])

    def pad(self, rows: list[list[int]]) -> np.ndarray:
        out = np.zeros((len(rows), self.length + 1), np.int64)
        out[:, 0] = SENTENCE
        for k, r in enumerate(rows):
            out[k, 1 : 1 + len(r)] = r
        return out

    def encode(self, rows: DataFrame, weights: dict[str, np.ndarray]) -> DataFrame:
        """id, vec (array<float>) of rows with id and ids."""
        me = self

        def run(batches):
            import pyarrow as pa

            for b in batches:
                for i in range(0, b.num_rows, 256):
                    p = b.slice(i, 256)
                    v = me.vector({k: Tensor(x) for k, x in weights.items()}, me.pad(p.column(1).to_pylist())).data.astype(np.float32)
                    yield pa.RecordBatch.from_arrays([p.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, v.size + 1, v.shape[1]), pa.int32()), pa.array(v.ravel()))], names=["id", "vec"])

        return rows.select("id", "ids").mapInArrow(run, "id long, vec array<float>")

    def unit_sums(self, rows: DataFrame, weights: dict[str, np.ndarray], by: str) -> DataFrame:
        """``by`` (an int), n, s (array<double>): number and sum of the vectors, scaled to unit length, of the rows of each ``by``; a row
        for each task that has some. Vectors themselves stay in their task."""
        me = self

        def run(batches):
            import pyarrow as pa

            w, sums, counts = {k: Tensor(x) for k, x in weights.items()}, {}, {}
            for b in batches:
                for i in range(0, b.num_rows, 256):
                    p = b.slice(i, 256)
                    v = me.vector(w, me.trimmed(me.pad(p.column(1).to_pylist()))).data.astype(np.float32).astype(float)
                    v /= np.sqrt((v * v).sum(1, keepdims=True))
                    groups = p.column(0).to_numpy()
                    for g in np.unique(groups).tolist():
                        sums[g] = sums.get(g, 0) + v[groups == g].sum(0)
                        counts[g] = counts.get(g, 0) + int((groups == g).sum())
            if counts:
                yield pa.RecordBatch.from_arrays([pa.array(list(counts), pa.int32()), pa.array(list(counts.values()), pa.int64()), pa.array([sums[g].tolist() for g in counts])], names=[by, "n", "s"])

        return rows.select(by, "ids").mapInArrow(run, f"{by} int, n long, s array<double>")

    def trimmed(self, ids: np.ndarray) -> np.ndarray:
        """``ids`` without places that are PAD in all rows, where those weigh nothing: attention skips them, convolutions do not."""
        if self.kind != "cls" or self.backbone == "conv":
            return ids
        return ids[:, : np.flatnonzero((ids != PAD).any(0))[-1] + 1]


def _chance(keys: np.ndarray, width: int, seed: int) -> np.ndarray:
    """Hash-random numbers by row and position: the same under any partitioning."""
    x = keys[:, None] * np.uint64(0x9E3779B97F4A7C15) + (np.arange(width, dtype=np.uint64) + np.uint64(1000 * seed + 1)) * np.uint64(0xC2B2AE3D27D4EB4F)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    return (x >> np.uint64(11)).astype(float) / float(1 << 53)


def token_ids(df: DataFrame, key: str, text: str, enc: TextEncoder) -> DataFrame:
    """id, key, ids: tokens of the first positions hashed into the vocabulary. A null text has none, like an empty one."""
    hashed = F.transform(tx.first_tokens(F.col(text), enc.length), lambda t: (tx.token_hash(t) % (enc.vocab - FIRST_WORD) + FIRST_WORD).cast("int"))
    return df.select(F.col(key).alias("id"), F.abs(F.xxhash64(key)).alias("key"), F.coalesce(hashed, F.array().cast("array<int>")).alias("ids"))


def train_mlm(rows: DataFrame, enc: TextEncoder, steps: int, lr: float = 3e-3, share: float = 1.0, schedule: str = "cosine", start: dict | None = None) -> tuple[dict[str, np.ndarray], list[float]]:
    w = dict(start) if start else enc.weights()
    return w, train.fit(rows, "id", w, enc.mlm, steps, lr, schedule, share)
