"""The two architectures: a visit's features to one vector and N sigmoids; windows of visits through recurrent layers."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from carepath.models import layers as L
from carepath.models.recurrent import Recurrent

TEMPORAL, CODES = ("stay", "gap"), ("dx", "proc", "med")


@dataclass(frozen=True)
class FeatureSpec:
    """Any non-empty subset of a visit's features; only what is named is ever joined or read."""

    text: bool = False
    stay: bool = False
    gap: bool = False
    dx: bool = False
    proc: bool = False
    med: bool = False

    def __post_init__(self):
        if not self.names:
            raise ValueError("a model needs a feature")

    @property
    def names(self) -> tuple[str, ...]:
        return tuple(n for n in ("text", *TEMPORAL, *CODES) if getattr(self, n))

    def width(self, d: int, temporal_width: int) -> int:
        return sum(temporal_width if n in TEMPORAL else d for n in self.names)

    @classmethod
    def of(cls, names: str) -> FeatureSpec:
        """From names joined by +."""
        return cls(**dict.fromkeys(names.split("+"), True))


@dataclass
class Batch:
    """Arrays by feature name, labels, and for windows the mask."""

    x: dict[str, np.ndarray]
    y: np.ndarray
    mask: np.ndarray | None = None

    def __len__(self) -> int:
        return len(self.y)

    def take(self, rows: np.ndarray) -> Batch:
        return Batch({k: v[rows] for k, v in self.x.items()}, self.y[rows], None if self.mask is None else self.mask[rows])


class Model:
    """Weights as one flat vector, for broadcasting and averaging."""

    def layers(self) -> list[L.Layer]:
        return [x for p in self.parts() for x in p.all()]

    def _each(self):
        for layer in self.layers():
            for name in layer.params:
                yield layer, name

    def get(self) -> np.ndarray:
        return np.concatenate([layer.params[n].ravel() for layer, n in self._each()])

    def set(self, flat: np.ndarray) -> None:
        at = 0
        for layer, n in self._each():
            v = layer.params[n]
            layer.params[n] = flat[at : at + v.size].reshape(v.shape).copy()
            at += v.size

    def gradient(self) -> np.ndarray:
        return np.concatenate([layer.grads[n].ravel() for layer, n in self._each()])

    def loss(self, batch: Batch, rng=None) -> float:
        """The batch's loss; its gradients are then in the layers."""
        z = self.logits(batch, rng)
        value, d = (L.ce if self.head == "softmax" else L.bce)(z, batch.y)
        self.backward(d)
        return value

    def value(self, batch: Batch) -> float:
        """The batch's loss alone."""
        return (L.ce if self.head == "softmax" else L.bce)(self.scored_logits(batch), batch.y)[0]

    def scored_logits(self, batch: Batch) -> np.ndarray:
        """``logits`` where no backward pass follows."""
        return self.logits(batch)

    def probabilities(self, batch: Batch) -> np.ndarray:
        z = self.scored_logits(batch)
        return L.softmax(z) if self.head == "softmax" else L.sigmoid(z)


@dataclass
class VisitModel(Model):
    """``tables``: frozen vectors of the codes, row 0 for padding; ``sizes``: codes of a visit at most, by kind."""

    spec: FeatureSpec
    n_classes: int
    tables: dict[str, np.ndarray] = field(default_factory=dict)
    sizes: dict[str, int] = field(default_factory=dict)
    d: int = 64
    temporal_width: int = 50
    dropout: float = 0.1
    head: str = "sigmoid"
    seed: int = 0

    def __post_init__(self):
        rng = np.random.default_rng(self.seed)
        self.blocks = {n: L.dense_block(rng, 1, self.temporal_width, self.dropout) if n in TEMPORAL else L.CodeBlock(rng, self.sizes[n], self.d, self.dropout) for n in self.spec.names if n != "text"}
        self.out = L.Linear(rng, self.spec.width(self.d, self.temporal_width), self.n_classes)

    def parts(self):
        return [*self.blocks.values(), self.out]

    def scored_vector(self, batch: Batch) -> np.ndarray:
        """``visit_vector`` without dropout, where no backward pass follows."""
        made = []
        for n in self.spec.names:
            x = batch.x[n]
            if n in TEMPORAL:  # days, of which there are few different ones
                values, at = np.unique(x, return_inverse=True)
                made.append(self.blocks[n].forward(values.reshape(-1, 1))[at])
            elif n == "text":
                made.append(x)
            else:
                made.append(self.blocks[n].of_codes(self.tables[n], x) if self.tables[n].shape[0] <= x.size else self.blocks[n].forward(self.tables[n][x]))
        return np.concatenate(made, axis=1)

    def scored_logits(self, batch: Batch) -> np.ndarray:
        return self.out.forward(self.scored_vector(batch))

    def visit_vector(self, batch: Batch, rng=None) -> np.ndarray:
        """The fused vector: the features' blocks side by side."""
        made = []
        for n in self.spec.names:
            x = batch.x[n]
            if n == "text":
                made.append(x)
            else:
                made.append(self.blocks[n].forward(x.reshape(-1, 1) if n in TEMPORAL else self.tables[n][x], rng))
        self.widths = [m.shape[1] for m in made]
        return np.concatenate(made, axis=1)

    def logits(self, batch: Batch, rng=None) -> np.ndarray:
        return self.out.forward(self.visit_vector(batch, rng), rng)

    def backward(self, d):
        d = self.out.backward(d)
        self.input_gradient = d
        for n, part in zip(self.spec.names, np.split(d, np.cumsum(self.widths)[:-1], axis=1), strict=True):
            if n != "text":
                self.blocks[n].backward(part)
        return d

    def backward_from_vector(self, d):
        """Continue a gradient by the fused vector into the blocks, for training through both architectures."""
        for n, part in zip(self.spec.names, np.split(d, np.cumsum(self.widths)[:-1], axis=1), strict=True):
            if n != "text":
                self.blocks[n].backward(part)


@dataclass
class TrajectoryModel(Model):
    """Windows of k visits, as fused vectors or sparse codes made multi-hot here, to the codes of the next visit."""

    rows: int
    n_classes: int
    cell: str = "gru"
    hidden: int = 64
    layers_: int = 1
    bidirectional: bool = False
    dropout: float = 0.2
    head: str = "sigmoid"
    seed: int = 0

    def __post_init__(self):
        rng = np.random.default_rng(self.seed)
        self.net = Recurrent(rng, self.cell, self.rows, self.hidden, self.layers_, self.bidirectional, self.dropout)
        self.out = L.Linear(rng, self.net.width, self.n_classes)

    def parts(self):
        return [self.net, self.out]

    def logits(self, batch: Batch, rng=None) -> np.ndarray:
        return self.out.forward(self.net.forward(batch.x["window"], batch.mask, rng), rng)

    def backward(self, d):
        self.input_gradient = self.net.backward(self.out.backward(d))
        return self.input_gradient


@dataclass
class EndToEnd(Model):
    """Both architectures in one: the visit model's blocks are trained through the window. Inputs are (batch, step, …)."""

    visit: VisitModel
    trajectory: TrajectoryModel

    @property
    def head(self):
        return self.trajectory.head

    def parts(self):
        return [*self.visit.blocks.values(), *self.trajectory.parts()]

    def logits(self, batch: Batch, rng=None) -> np.ndarray:
        n, k = batch.mask.shape
        flat = Batch({name: v.reshape(n * k, *v.shape[2:]) for name, v in batch.x.items()}, np.zeros((n * k, 1)))
        h = self.visit.visit_vector(flat, rng).reshape(n, k, -1)
        return self.trajectory.logits(Batch({"window": h}, batch.y, batch.mask), rng)

    def backward(self, d):
        g = self.trajectory.backward(d)
        self.visit.backward_from_vector(g.reshape(-1, g.shape[2]))
