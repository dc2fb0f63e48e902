"""Samples as tasks hold them: short arrays of what a row names. Only the rows of a mini-batch become dense.

A builder makes ``Held`` of a table; called, it gives all rows of a table as one batch. Each rotation sees the same rows, with its own
bounds of the time features, its own text vectors and its own visit model below (``Held.turned``).
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass, field, replace
from functools import lru_cache

import numpy as np
import pyarrow as pa

from carepath.models.nets import Batch, VisitModel

TIMES = ("gap", "stay")


def minmax(x: np.ndarray, low: float, high: float) -> np.ndarray:
    """As ``temporal.apply_minmax``: clipped to [0, 1], and a column without a range becomes 0."""
    return np.clip((x - low) / (high - low), 0, 1) if high > low else np.zeros(x.shape)


def whole(column: pa.ChunkedArray | pa.Array) -> pa.Array:
    return column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column


@dataclass
class Lists:
    """Lists of any length as one flat array and where each begins."""

    flat: np.ndarray | None
    at: np.ndarray

    @classmethod
    def of(cls, lists: pa.Array) -> Lists:
        at = lists.offsets.to_numpy().astype(np.int64)
        return cls(lists.flatten().to_numpy(zero_copy_only=False) if pa.types.is_primitive(lists.type.value_type) else None, at - at[0])

    def __len__(self) -> int:
        return len(self.at) - 1

    def sizes(self, rows: np.ndarray) -> np.ndarray:
        return self.at[rows + 1] - self.at[rows]

    def inside(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For every element of the lists ``rows``: which of them it is in, its place there, and its place in the flat array."""
        n = self.sizes(rows)
        place = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return np.repeat(np.arange(len(rows)), n), place, np.repeat(self.at[rows], n) + place


def dense_labels(y: Lists, rows: np.ndarray, n_classes: int, first: int) -> np.ndarray:
    out = np.zeros((len(rows), n_classes))
    owner, _, at = y.inside(rows)
    v = y.flat[at] - first
    ok = (v >= 0) & (v < n_classes)
    out[owner[ok], v[ok]] = 1
    return out


def columns_of(table, names: tuple[str, ...], n: int) -> dict[str, np.ndarray]:
    """Time features as numbers, the others as a row of equal length each."""
    x = {}
    for name in names:
        c = whole(table.column(name) if isinstance(table, pa.Table) else table.field(name))
        x[name] = c.to_numpy(zero_copy_only=False).astype(float) if name in TIMES else c.flatten().to_numpy(zero_copy_only=False).reshape(n, -1)
    return x


@dataclass
class Turn:
    """What a rotation has of its own: bounds of time features, its place among the rotations where texts have a vector for each, and the visit model below."""

    bounds: dict[str, tuple[float, float]] = field(default_factory=dict)
    place: int | None = None
    below: bytes | None = None


@dataclass
class Held:
    builder: Builder
    x: object
    y: Lists
    turn: Turn = field(default_factory=Turn)
    rows: np.ndarray | None = None

    def __len__(self) -> int:
        return len(self.y) if self.rows is None else len(self.rows)

    def only(self, rows: np.ndarray) -> Held:
        return replace(self, rows=rows if self.rows is None else self.rows[rows])

    def turned(self, turn: Turn) -> Held:
        return replace(self, turn=turn)

    def made(self) -> Held:
        """With what its rotation makes of the rows made once, where they are taken in many small batches."""
        return replace(self, x=self.builder.made(self.x, self.turn))

    def steps(self) -> np.ndarray:
        """Steps of each row, one where there are none."""
        return self.builder.steps_of(self.x, np.arange(len(self)) if self.rows is None else self.rows)

    def take(self, rows: np.ndarray) -> Batch:
        at = np.asarray(rows) if self.rows is None else self.rows[rows]
        x, mask = self.builder.dense(self.x, at, self.turn)
        return Batch(x, dense_labels(self.y, at, self.builder.n_classes, self.builder.first), mask)


class Builder:
    n_classes: int
    first: int
    #: What each rotation has of its own, where it was known before training.
    turns: list[Turn] | None = None

    def __call__(self, table: pa.Table) -> Batch:
        held = self.hold(table)
        return held.take(np.arange(len(held)))

    def hold(self, table: pa.Table) -> Held:
        return Held(self, self.short(table), Lists.of(whole(table.column("y"))))

    def steps_of(self, x, rows: np.ndarray) -> np.ndarray:
        return np.ones(len(rows), np.int64)

    def made(self, x, turn: Turn):
        return x


def scaled(x: dict[str, np.ndarray], turn: Turn, d: int | None) -> dict[str, np.ndarray]:
    x = {k: minmax(v, *turn.bounds[k]) if k in turn.bounds else v for k, v in x.items()}
    if d and turn.place is not None and "text" in x:
        x["text"] = x["text"][:, turn.place * d : (turn.place + 1) * d]
    return x


@dataclass
class Visits(Builder):
    """Features of single visits. ``own_text``: the width of a rotation's text vectors, which then stand side by side in the column."""

    features: tuple[str, ...]
    n_classes: int
    first: int
    own_text: int | None = None

    def short(self, table):
        return columns_of(table, self.features, len(table))

    def dense(self, x, at, turn):
        return scaled({k: v[at] for k, v in x.items()}, turn, self.own_text), None


#: Visits whose vectors are made at once.
VISITS_AT_ONCE = 8192


@lru_cache(maxsize=16)
def _below(packed: bytes) -> VisitModel:
    return pickle.loads(packed)


@dataclass
class Windows(Builder):
    """Windows of sparse ids made multi-hot, of vectors, or of visits whose vectors a rotation's visit model makes here.

    Columns: ``steps`` (array per visit, null where padded), mask and y. Without ``k``, histories of any length are padded on the left to
    the longest of the rows taken; masked steps keep the state.
    """

    n_classes: int
    first: int
    width: int
    k: int | None
    #: ids, vectors, or the names of a visit's features.
    steps: str | tuple[str, ...]
    first_id: int = 0

    def short(self, table):
        steps, mask = whole(table.column("steps")), whole(table.column("mask"))
        outer, inner = Lists.of(steps), steps.flatten()
        given = inner.is_valid().to_numpy(zero_copy_only=False)
        if self.steps == "ids":
            visits = Lists.of(inner)
        elif self.steps == "vectors":
            visits = inner.flatten().to_numpy(zero_copy_only=False).reshape(-1, self.width)
        else:
            # A visit is in several windows: its features are held, and its vector made, once.
            some = inner.drop_null()
            _, first, number = np.unique(some.field("visit_id").to_numpy(), return_index=True, return_inverse=True)
            at = np.zeros(len(given), np.int64)
            at[given] = number
            return outer, Lists.of(mask), given, at, columns_of(some.take(pa.array(first)), self.steps, len(first))
        return outer, Lists.of(mask), given, np.cumsum(given) - 1, visits

    def steps_of(self, x, rows):
        return x[0].sizes(rows) if self.k is None else np.full(len(rows), self.k)

    def vectors(self, visits: dict[str, np.ndarray], rows: np.ndarray, turn: Turn) -> np.ndarray:
        own = scaled({n: v[rows] for n, v in visits.items()}, turn, None)
        return _below(turn.below).scored_vector(Batch(own, np.zeros((len(rows), 1)))).astype(np.float32)

    def made(self, x, turn):
        *rest, visits = x
        if not isinstance(visits, dict) or not (n := len(next(iter(visits.values())))):
            return x
        return *rest, np.concatenate([self.vectors(visits, np.arange(i, min(i + VISITS_AT_ONCE, n)), turn) for i in range(0, n, VISITS_AT_ONCE)])

    def dense(self, x, at, turn):
        outer, on, given, number, visits = x
        long = self.k or int(outer.sizes(at).max(initial=1))
        out, mask = np.zeros((len(at), long, self.width)), np.zeros((len(at), long))
        owner, place, i = on.inside(at)
        mask[owner, long - on.sizes(at)[owner] + place] = on.flat[i]
        owner, place, i = outer.inside(at)
        place = long - outer.sizes(at)[owner] + place
        if self.steps == "ids":
            step, _, j = visits.inside(i)
            v = visits.flat[j] - self.first_id
            ok = v >= 0
            out[owner[step[ok]], place[step[ok]], v[ok]] = 1
        else:
            some = given[i]
            owner, place, i = owner[some], place[some], number[i[some]]
            if not isinstance(visits, dict):
                out[owner, place] = visits[i]
            elif len(i):
                seen, back = np.unique(i, return_inverse=True)
                out[owner, place] = self.vectors(visits, seen, turn)[back]
        return {"window": out}, mask


@dataclass
class At(Builder):
    """A builder for one rotation."""

    inner: Builder
    turn: Turn

    def hold(self, table: pa.Table) -> Held:
        return self.inner.hold(table).turned(self.turn)


def held_by(build, table: pa.Table):
    """A builder's rows, or those of a plain function from a table to a batch."""
    return build.hold(table) if isinstance(build, Builder) else build(table)


def turned(rows, turn: Turn):
    return rows.turned(turn) if isinstance(rows, Held) else rows


def some_of(rows, at: np.ndarray):
    return rows.only(at) if isinstance(rows, Held) else rows.take(at)


def made_once(rows):
    return rows.made() if isinstance(rows, Held) else rows


#: Numbers of dense inputs made at once where no backward pass follows.
DENSE_CELLS = 1 << 20


def at_once(rows, most: int) -> int:
    """How many rows are made dense at once: ``most``, or what ``DENSE_CELLS`` allows of the longest."""
    if not isinstance(rows, Held) or not len(rows):
        return most
    return max(1, min(most, DENSE_CELLS // max(1, int(rows.steps().max()) * getattr(rows.builder, "width", 1))))


def by_length(rows):
    """The rows in order of their steps, so that those made dense together need little padding."""
    if not isinstance(rows, Held):
        return rows
    steps = rows.steps()
    return rows if not len(steps) or steps.min() == steps.max() else rows.only(np.argsort(steps, kind="stable"))
