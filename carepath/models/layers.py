"""Layers in numpy, each with its backward pass. Parameters and gradients are held by name, inputs of the last call inside."""

from __future__ import annotations

import numpy as np


class Layer:
    def __init__(self):
        self.params: dict[str, np.ndarray] = {}
        self.grads: dict[str, np.ndarray] = {}

    def parts(self) -> list[Layer]:
        return []

    def all(self) -> list[Layer]:
        return [self, *(x for p in self.parts() for x in p.all())]


def glorot(rng: np.random.Generator, rows: int, cols: int) -> np.ndarray:
    edge = (6 / (rows + cols)) ** 0.5
    return rng.uniform(-edge, edge, (rows, cols))


class Linear(Layer):
    def __init__(self, rng, rows: int, cols: int):
        super().__init__()
        self.params = {"w": glorot(rng, rows, cols), "b": np.zeros(cols)}

    def forward(self, x, rng=None):
        self.x = x
        return x @ self.params["w"] + self.params["b"]

    def backward(self, d):
        self.grads = {"w": self.x.T @ d, "b": d.sum(axis=0)}
        return d @ self.params["w"].T


class LayerNorm(Layer):
    """Over the last axis."""

    def __init__(self, width: int, epsilon: float = 1e-5):
        super().__init__()
        self.params, self.epsilon = {"g": np.ones(width), "b": np.zeros(width)}, epsilon

    def forward(self, x, rng=None):
        self.s = np.sqrt(x.var(axis=-1, keepdims=True) + self.epsilon)
        self.n = (x - x.mean(axis=-1, keepdims=True)) / self.s
        return self.n * self.params["g"] + self.params["b"]

    def backward(self, d):
        over = tuple(range(d.ndim - 1))
        self.grads = {"g": (d * self.n).sum(axis=over), "b": d.sum(axis=over)}
        d = d * self.params["g"]
        return (d - d.mean(axis=-1, keepdims=True) - self.n * (d * self.n).mean(axis=-1, keepdims=True)) / self.s


class Mish(Layer):
    def forward(self, x, rng=None):
        self.x, self.t = x, np.tanh(np.logaddexp(0, x))
        return x * self.t

    def backward(self, d):
        return d * (self.t + self.x * (1 - self.t**2) * sigmoid(self.x))


class Dropout(Layer):
    """Without a generator (scoring, gradient checks) it lets all through."""

    def __init__(self, rate: float):
        super().__init__()
        self.rate = rate

    def forward(self, x, rng=None):
        self.mask = None if rng is None or not self.rate else (rng.random(x.shape) >= self.rate) / (1 - self.rate)
        return x if self.mask is None else x * self.mask

    def backward(self, d):
        return d if self.mask is None else d * self.mask


class Chain(Layer):
    def __init__(self, *layers: Layer):
        super().__init__()
        self.layers = layers

    def parts(self):
        return list(self.layers)

    def forward(self, x, rng=None):
        for layer in self.layers:
            x = layer.forward(x, rng)
        return x

    def backward(self, d):
        for layer in reversed(self.layers):
            d = layer.backward(d)
        return d


def dense_block(rng, rows: int, width: int, dropout: float) -> Chain:
    """A temporal feature's block."""
    return Chain(Linear(rng, rows, width), LayerNorm(width), Mish(), Dropout(dropout))


class CodeBlock(Layer):
    """Vectors of a visit's codes to one: norm, dropout, flatten, bottleneck. The vectors themselves are frozen."""

    def __init__(self, rng, size: int, d: int, dropout: float):
        super().__init__()
        self.size, self.d = size, d
        self.first = Chain(LayerNorm(d), Dropout(dropout))
        self.bottleneck = dense_block(rng, size * d, d, dropout)

    def parts(self):
        return [self.first, self.bottleneck]

    def forward(self, x, rng=None):
        return self.bottleneck.forward(self.first.forward(x, rng).reshape(len(x), -1), rng)

    def of_codes(self, table, ids):
        """``forward`` of ``table[ids]`` without dropout: each of the table's vectors is normed once, not each code. No backward pass follows."""
        return self.bottleneck.forward(self.first.forward(table)[ids].reshape(len(ids), -1))

    def backward(self, d):
        return self.first.backward(self.bottleneck.backward(d).reshape(len(d), self.size, self.d))


def sigmoid(x):
    e = np.exp(-np.abs(x))
    return np.where(x >= 0, 1 / (1 + e), e / (1 + e))


def softmax(x):
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def bce(z, y):
    """Mean over cells, and its gradient by the logits."""
    loss = np.maximum(z, 0) - z * y + np.log1p(np.exp(-np.abs(z)))
    return float(loss.mean()), (sigmoid(z) - y) / z.size


def ce(z, y):
    """Exclusive classes, several true ones sharing the mass; mean over samples, and its gradient."""
    t = y / np.maximum(y.sum(axis=-1, keepdims=True), 1)
    p = softmax(z)
    has = (y.sum(axis=-1, keepdims=True) > 0).astype(float)
    return float(-(t * np.log(np.maximum(p, 1e-15))).sum() / len(z)), (p * has - t) / len(z)
