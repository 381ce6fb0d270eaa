"""Reverse-mode differentiation over numpy arrays."""

from __future__ import annotations

import numpy as np


def _fit(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Undo broadcasting: sum ``g`` down to ``shape``."""
    while g.ndim > len(shape):
        g = g.sum(0)
    for k, n in enumerate(shape):
        if n == 1 and g.shape[k] != 1:
            g = g.sum(k, keepdims=True)
    return g


class Tensor:
    def __init__(self, data, parents=(), back=None):
        self.data = np.asarray(data, np.float64)
        self.grad: np.ndarray | None = None
        self.parents, self.back = parents, back

    @property
    def shape(self):
        return self.data.shape

    def _make(self, data, parents, back):
        return Tensor(data, parents, back)

    def __add__(self, other):
        o = other if isinstance(other, Tensor) else Tensor(other)
        return Tensor(self.data + o.data, (self, o), lambda g: (_fit(g, self.shape), _fit(g, o.shape)))

    def __mul__(self, other):
        o = other if isinstance(other, Tensor) else Tensor(other)
        return Tensor(self.data * o.data, (self, o), lambda g: (_fit(g * o.data, self.shape), _fit(g * self.data, o.shape)))

    def __sub__(self, other):
        return self + (other if isinstance(other, Tensor) else Tensor(other)) * -1.0

    __radd__, __rmul__ = __add__, __mul__

    def power(self, p: float):
        return Tensor(self.data**p, (self,), lambda g: (g * p * self.data ** (p - 1),))

    def __matmul__(self, o: Tensor):
        def back(g):
            return _fit(g @ np.swapaxes(o.data, -1, -2), self.shape), _fit(np.swapaxes(self.data, -1, -2) @ g, o.shape)

        return Tensor(self.data @ o.data, (self, o), back)

    def relu(self):
        return Tensor(np.maximum(self.data, 0), (self,), lambda g: (g * (self.data > 0),))

    def tanh(self):
        y = np.tanh(self.data)
        return Tensor(y, (self,), lambda g: (g * (1 - y * y),))

    def sigmoid(self):
        y = 1 / (1 + np.exp(-np.clip(self.data, -60, 60)))
        return Tensor(y, (self,), lambda g: (g * y * (1 - y),))

    def log(self):
        return Tensor(np.log(self.data), (self,), lambda g: (g / self.data,))

    def softmax(self):
        e = np.exp(self.data - self.data.max(-1, keepdims=True))
        y = e / e.sum(-1, keepdims=True)
        return Tensor(y, (self,), lambda g: (y * (g - (g * y).sum(-1, keepdims=True)),))

    def sum(self, axis=None, keepdims=False):
        def back(g):
            if axis is not None and not keepdims:
                g = np.expand_dims(g, axis)
            return (np.broadcast_to(g, self.shape).copy(),)

        return Tensor(self.data.sum(axis, keepdims=keepdims), (self,), back)

    def mean(self, axis=None, keepdims=False):
        n = self.data.size if axis is None else np.prod([self.shape[a] for a in np.atleast_1d(axis)])
        return self.sum(axis, keepdims) * (1.0 / n)

    def reshape(self, *shape):
        return Tensor(self.data.reshape(shape), (self,), lambda g: (g.reshape(self.shape),))

    def swap(self, a: int, b: int):
        return Tensor(np.swapaxes(self.data, a, b), (self,), lambda g: (np.swapaxes(g, a, b),))

    def __getitem__(self, key):
        def back(g):
            out = np.zeros_like(self.data)
            np.add.at(out, key, g)
            return (out,)

        return Tensor(self.data[key], (self,), back)

    def norm(self, eps: float = 1e-5):
        """Zero mean and unit variance along the last axis."""
        c = self - self.mean(-1, True)
        return c * ((c * c).mean(-1, True) + eps).power(-0.5)

    def backward(self) -> None:
        order, seen = [], set()

        def visit(t):
            stack = [(t, False)]
            while stack:
                node, done = stack.pop()
                if done:
                    order.append(node)
                elif id(node) not in seen:
                    seen.add(id(node))
                    stack.append((node, True))
                    stack += [(p, False) for p in node.parents]

        visit(self)
        self.grad = np.ones_like(self.data)
        for t in reversed(order):
            if t.back:
                for p, g in zip(t.parents, t.back(t.grad), strict=True):
                    p.grad = g if p.grad is None else p.grad + g


def concat(parts: list[Tensor], axis: int = -1) -> Tensor:
    cuts = np.cumsum([p.shape[axis] for p in parts])[:-1]
    return Tensor(np.concatenate([p.data for p in parts], axis), tuple(parts), lambda g: tuple(np.split(g, cuts, axis)))


def cross_entropy(logits: Tensor, target: np.ndarray) -> Tensor:
    """Sum over rows of -log softmax at the target."""
    z = logits.data - logits.data.max(-1, keepdims=True)
    logp = z - np.log(np.exp(z).sum(-1, keepdims=True))
    rows = np.arange(len(target))

    def back(g):
        p = np.exp(logp)
        p[rows, target] -= 1
        return (g * p,)

    return Tensor(-logp[rows, target].sum(), (logits,), back)


def binary_loss(z: Tensor, target: np.ndarray, weight: np.ndarray | float = 1.0) -> Tensor:
    """Sum of weighted log losses of logits."""
    p = 1 / (1 + np.exp(-np.clip(z.data, -60, 60)))
    value = -(weight * (target * np.log(p + 1e-12) + (1 - target) * np.log(1 - p + 1e-12))).sum()
    return Tensor(value, (z,), lambda g: (g * weight * (p - target),))


def conv1d(x: Tensor, w: Tensor) -> Tensor:
    """Same-length convolution over axis 1: x (batch, n, c), w (k * c, out), k odd."""
    b, n, c = x.shape
    k = w.shape[0] // c
    pad = Tensor(np.zeros((b, k // 2, c)))
    long = concat([pad, x, pad], 1)
    return concat([long[:, i : i + n] for i in range(k)], 2) @ w


def _windows(side: int, stride: int) -> np.ndarray:
    """For each output of a 3 x 3 convolution with edges repeated: the nine input places (rows of a flattened square)."""
    at = np.arange(0, side, stride)
    r, c = np.meshgrid(at, at, indexing="ij")
    near = [np.clip(r + i, 0, side - 1) * side + np.clip(c + j, 0, side - 1) for i in (-1, 0, 1) for j in (-1, 0, 1)]
    return np.stack([x.ravel() for x in near], 1)


def conv2d(x: Tensor, w: Tensor, stride: int = 1) -> Tensor:
    """3 x 3 convolution of square images x (batch, side * side, c) with w (9 * c, out)."""
    b, n, c = x.shape
    at = _windows(int(n**0.5), stride)
    return x[:, at].reshape(b, len(at), 9 * c) @ w


def doubled(x: Tensor) -> Tensor:
    """Square images (batch, side * side, c) with every pixel repeated twice each way."""
    side = int(x.shape[1] ** 0.5)
    at = np.arange(2 * side) // 2
    return x[:, (at[:, None] * side + at[None, :]).ravel()]
