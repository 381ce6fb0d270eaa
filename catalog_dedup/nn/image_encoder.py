"""Images to 128-d vectors: autoencoders plain and masked, and their loss measures.

Images are 24 x 24 gray in a 3 x 3 grid of 8 x 8 patches. Kinds: conv_ae (two strided 3 x 3
convolutions, a bottleneck that no path goes around, and a decoder of two upsampling convolutions), patch_ae (all patches
through a block, pooled), mae_random (4 random patches, 32 numbers each, hidden patches reconstructed) and mae_guided (centre,
two others, the whole shrunk to a patch; the full image reconstructed). Backbones: global (attention over all patches), windowed
(attention of neighbours only) and conv_stem (convolution in place of attention).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from ..functions import raster
from . import train
from .tape import Tensor, concat, conv1d, conv2d, doubled

SIDE, PATCH, CELLS = 24, 8, 9
#: Channels of the two convolutions of conv_ae, which halve the side twice (24, 12, 6).
CHANNELS = (6, 12)
#: Pictures that numpy works on at once.
PART = 512
EXPONENTS = (0.0448, 0.2856, 0.3001, 0.2363, 0.1333)


@dataclass(frozen=True)
class ImageEncoder:
    kind: str = "mae_guided"
    backbone: str = "global"
    width: int = 48
    loss: str = "mse"

    def weights(self, seed: int = 0) -> dict[str, np.ndarray]:
        r, h, p = np.random.default_rng(seed), self.width, PATCH * PATCH
        mat = lambda a, b: r.normal(0, a**-0.5, (a, b))
        w = {"embed": mat(p, h), "place": r.normal(0, 0.1, (CELLS + 1, h)), "up": mat(h, 2 * h), "down": mat(2 * h, h), "decode": mat(128, 2 * h), "pixels": mat(2 * h, SIDE * SIDE)}
        w |= {k: mat(h, h) for k in "qkvo"} | {"mix": mat(3 * h, h)}
        if self.kind == "conv_ae":
            c, d = CHANNELS
            return {"in1": mat(9, c), "in2": mat(9 * c, d), "code": mat(36 * d, 128), "spread": mat(128, 36 * d), "out1": mat(9 * d, c), "out2": mat(9 * c, 1)}
        w["code"] = mat(h, 32) if self.kind.startswith("mae") else mat(h, 128)
        return w

    def vector(self, w: dict[str, Tensor], images: np.ndarray, keys: np.ndarray, seed: int = 0) -> tuple[Tensor, np.ndarray]:
        """Vectors (n, 128) and the cells that were seen (n, k; CELLS is the shrunk whole)."""
        cells = raster.cells(images)  # n, 9, 64
        if self.kind == "conv_ae":
            y = conv2d(Tensor(images.reshape(len(images), -1, 1)), w["in1"], 2).relu()
            y = conv2d(y, w["in2"], 2).relu().reshape(len(images), 36 * CHANNELS[1])
            return (y @ w["code"]).tanh(), np.tile(np.arange(CELLS), (len(images), 1))
        if self.kind == "patch_ae":
            seen, at = cells, np.tile(np.arange(CELLS), (len(images), 1))
        elif self.kind == "mae_random":
            at = raster.random_cells(keys, 4, seed)
            seen = np.take_along_axis(cells, at[:, :, None], 1)
        else:
            at = raster.guided_cells(keys, seed)
            seen = np.concatenate([np.take_along_axis(cells, at[:, :3, None], 1), raster.shrunk(images)[:, None]], 1)
        x = Tensor(seen) @ w["embed"] + w["place"][at]
        y = x.norm()
        if self.backbone == "conv_stem":
            x = x + conv1d(y, w["mix"])
        else:
            far = 0.0 if self.backbone == "global" else np.where(np.abs(at[:, :, None] // 3 - at[:, None, :] // 3) + np.abs(at[:, :, None] % 3 - at[:, None, :] % 3) > 1, -1e9, 0.0)
            q, k, v = (y @ w[z] for z in "qkv")
            x = x + (((q @ k.swap(1, 2)) * self.width**-0.5 + far).softmax() @ v) @ w["o"]
        x = x + (x.norm() @ w["up"]).relu() @ w["down"]
        if self.kind == "patch_ae":
            return (x.mean(1) @ w["code"]).tanh(), at
        return (x @ w["code"]).tanh().reshape(len(images), 128), at

    def rebuilt(self, w: dict[str, Tensor], v: Tensor) -> Tensor:
        if self.kind == "conv_ae":
            y = (v @ w["spread"]).relu().reshape(v.shape[0], 36, CHANNELS[1])
            return conv2d(doubled(conv2d(doubled(y), w["out1"]).relu()), w["out2"]).sigmoid().reshape(v.shape[0], SIDE * SIDE)
        return ((v @ w["decode"]).relu() @ w["pixels"]).sigmoid()

    def objective(self, w: dict[str, Tensor], batch: dict[str, list], seed: int) -> tuple[Tensor, int]:
        images = raster.unpack(batch["pixels"])
        v, at = self.vector(w, images, np.array(batch["key"], np.uint64), seed)
        out = self.rebuilt(w, v)
        if self.loss == "ssim":
            return structure_loss(out, images), len(images)
        weight = np.ones((len(images), CELLS))
        if self.kind == "mae_random":
            np.put_along_axis(weight, at, 0.0, 1)  # only what was hidden counts
        pixel = raster.uncells(np.repeat(weight[:, :, None], PATCH * PATCH, 2)).reshape(len(images), -1)
        d = (out - images.reshape(len(images), -1)) * pixel
        return (d * d).sum() * (1.0 / (SIDE * SIDE)), len(images)

    def reconstruct(self, weights: dict[str, np.ndarray], images: np.ndarray, keys: np.ndarray) -> np.ndarray:
        w = {k: Tensor(x) for k, x in weights.items()}
        return self.rebuilt(w, self.vector(w, images, keys)[0]).data.reshape(-1, SIDE, SIDE)

    def encode(self, rows: DataFrame, weights: dict[str, np.ndarray]) -> DataFrame:
        """id, vec of rows (id, key, pixels); the random cells of an id never change."""
        me = self

        def run(batches):
            import pyarrow as pa

            for b in batches:
                for i in range(0, b.num_rows, 512):
                    p = b.slice(i, 512)
                    images = raster.unpack(p.column("pixels").to_pylist())
                    v = me.vector({k: Tensor(x) for k, x in weights.items()}, images, p.column("key").to_numpy().astype(np.uint64))[0].data
                    yield pa.RecordBatch.from_arrays([p.column("id"), pa.ListArray.from_arrays(pa.array(np.arange(0, v.size + 1, v.shape[1]), pa.int32()), pa.array(v.astype(np.float32).ravel()))], names=["id", "vec"])

        return rows.select("id", "key", "pixels").mapInArrow(run, "id long, vec array<float>")

    def vectors_of_codes(self, weights: dict[str, np.ndarray], keys: np.ndarray, codes: np.ndarray, shapes: tuple) -> np.ndarray:
        """``vector`` of drawn pictures (n, 128). Every distinct picture is drawn once, and what doesn't depend on the key is worked out once for it."""
        distinct, of = np.unique(codes, return_inverse=True)
        images = np.concatenate([raster.halve_all(raster.draw_codes(distinct[i : i + PART], shapes)) for i in range(0, len(distinct), PART)]) / 255.0
        if not self.kind.startswith("mae"):
            w = {k: Tensor(x) for k, x in weights.items()}
            return np.concatenate([self.vector(w, images[i : i + PART], distinct[i : i + PART])[0].data for i in range(0, len(distinct), PART)])[of]
        if self.backbone == "conv_stem":
            w = {k: Tensor(x) for k, x in weights.items()}
            return np.concatenate([self.vector(w, images[of[i : i + PART]], keys[i : i + PART])[0].data for i in range(0, len(of), PART)])
        x, scores, values = self._cell_states(weights, images)
        w, code = weights, weights["down"] @ weights["code"]
        at = raster.random_cells(keys, 4) if self.kind == "mae_random" else raster.guided_cells(keys)
        out = []
        for i in range(0, len(of), PART):
            u, seen = of[i : i + PART, None], at[i : i + PART]
            e = scores[u[:, :, None], seen[:, :, None], seen[:, None, :]]
            e = np.exp(e - e.max(-1, keepdims=True))
            e /= e.sum(-1, keepdims=True)
            y = (x[u, seen] + e @ values[u, seen]).reshape(-1, self.width)
            rest = y @ w["code"]
            y -= y.mean(-1, keepdims=True)
            y *= (np.einsum("ij,ij->i", y, y)[:, None] / self.width + 1e-5) ** -0.5
            hidden = y @ w["up"]
            rest += np.maximum(hidden, 0, out=hidden) @ code
            out.append(np.tanh(rest, out=rest).reshape(len(u), 128))
        return np.concatenate(out)

    def _cell_states(self, w: dict[str, np.ndarray], images: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of all cells and the shrunk whole of each picture: embedding (n, 10, width), attention scores (n, 10, 10), and what each adds where it is attended to."""
        seen = np.concatenate([raster.cells(images), raster.shrunk(images)[:, None]], 1)
        x = (seen.reshape(-1, PATCH * PATCH) @ w["embed"]).reshape(len(images), CELLS + 1, -1) + w["place"]
        y = x - x.mean(-1, keepdims=True)
        y = (y * ((y * y).mean(-1, keepdims=True) + 1e-5) ** -0.5).reshape(-1, self.width)
        q, k, v = ((y @ m).reshape(x.shape) for m in (w["q"], w["k"], w["v"] @ w["o"]))
        scores = q @ k.swapaxes(1, 2) * self.width**-0.5
        if self.backbone == "windowed":
            r, c = np.divmod(np.arange(CELLS + 1), 3)
            scores = scores + np.where(np.abs(r[:, None] - r) + np.abs(c[:, None] - c) > 1, -1e9, 0.0)
        return x, scores, v

    def encode_codes(self, rows: DataFrame, weights: dict[str, np.ndarray]) -> DataFrame:
        """id, vec of coded listings (id, code), as ``encode`` of their pictures. Rows of one code are best neighbours: they share the work within a batch."""
        me = self

        def run(batches):
            import pyarrow as pa

            shapes = raster._shapes()
            for b in batches:
                for i in range(0, b.num_rows, 8 * PART):
                    p = b.slice(i, 8 * PART)
                    v = me.vectors_of_codes(weights, p.column("key").to_numpy().astype(np.uint64), p.column("code").to_numpy(), shapes)
                    yield pa.RecordBatch.from_arrays([p.column("id"), pa.ListArray.from_arrays(pa.array(np.arange(0, v.size + 1, v.shape[1]), pa.int32()), pa.array(v.astype(np.float32).ravel()))], names=["id", "vec"])

        return raster.keyed(rows).mapInArrow(run, "id long, vec array<float>")


def structure_loss(out: Tensor, images: np.ndarray) -> Tensor:
    """Sum over images of 1 - structural similarity of 8 x 8 windows."""
    n, p = len(images), PATCH * PATCH
    a = out.reshape(n, 3, PATCH, 3, PATCH).swap(2, 3).reshape(n, CELLS, p)
    b = raster.cells(images)
    mb, ma = b.mean(2, keepdims=True), a.mean(2, True)
    da, db = a - ma, b - mb
    va, vb, cov = (da * da).mean(2, True), (db * db).mean(2, keepdims=True), (da * db).mean(2, True)
    top = (ma * (2 * mb) + 1e-4) * (cov * 2.0 + 9e-4)
    low = (ma * ma + (mb * mb + 1e-4)) * (va + (vb + 9e-4))
    return (top * low.power(-1.0)).mean(1).sum() * -1.0 + float(n)


def _blur(x: np.ndarray) -> np.ndarray:
    """Gaussian window of 11 pixels (fewer if the image is smaller), sigma 1.5, valid part."""
    k = min(11, x.shape[-1])
    g = np.exp(-((np.arange(k) - (k - 1) / 2) ** 2) / (2 * 1.5**2))
    g /= g.sum()
    rows = np.lib.stride_tricks.sliding_window_view(x, k, -1) @ g
    return np.swapaxes(np.lib.stride_tricks.sliding_window_view(rows, k, -2) @ g, -1, -1)


def ms_ssim(a: np.ndarray, b: np.ndarray, scales: int | None = None, peak: float = 1.0) -> np.ndarray:
    """Multi-scale structural similarity of image pairs (n, h, w). Scales are as many as leave at least 3 pixels, five at most;
    exponents are scaled to sum to 1 when there are fewer."""
    most = 1
    while most < 5 and min(a.shape[1:]) >> most >= 3:
        most += 1
    scales = min(scales or most, most)
    weight = np.array(EXPONENTS[:scales]) / sum(EXPONENTS[:scales])
    c1, c2, out = (0.01 * peak) ** 2, (0.03 * peak) ** 2, np.ones(len(a))
    for s in range(scales):
        ma, mb = _blur(a), _blur(b)
        va, vb, cov = _blur(a * a) - ma * ma, _blur(b * b) - mb * mb, _blur(a * b) - ma * mb
        cs = ((2 * cov + c2) / (va + vb + c2)).mean((1, 2))
        if s == scales - 1:
            cs = (((2 * ma * mb + c1) / (ma * ma + mb * mb + c1)) * ((2 * cov + c2) / (va + vb + c2))).mean((1, 2))
        out *= np.maximum(cs, 0) ** weight[s]
        h, w = a.shape[1] // 2 * 2, a.shape[2] // 2 * 2
        a, b = (x[:, :h, :w].reshape(len(x), h // 2, 2, w // 2, 2).mean((2, 4)) for x in (a, b))
    return out


def train_images(rows: DataFrame, enc: ImageEncoder, steps: int, lr: float = 3e-3, share: float = 1.0) -> tuple[dict[str, np.ndarray], list[float]]:
    w = enc.weights()
    return w, train.fit(rows, "id", w, enc.objective, steps, lr, "cosine", share)
