"""Training: on the driver for samples under a cap, or in tasks with gradients or weights summed."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from carepath.models.nets import Batch, Model
from carepath.models.optim import LookaheadRAdam
from carepath.models.packed import Held, Turn, at_once, by_length, held_by, made_once, minmax, some_of, turned


@dataclass(frozen=True)
class TrainSpec:
    batch: int = 64
    epochs: int = 100
    rate: float = 1e-3
    #: Updates without a better validation loss before training ends; checked every ``eval_every``.
    patience: int = 200
    eval_every: int = 50
    mode: str = "driver"
    #: Most rows that driver mode takes in.
    driver_rows: int = 200_000
    #: Updates of a task between two averages, in local mode.
    local_steps: int = 16
    seed: int = 0


@dataclass
class EarlyStop:
    """Keeps the best weights; ``over`` once no better loss has come for ``patience`` updates."""

    patience: int
    best: float = float("inf")
    weights: np.ndarray | None = None
    at: int = 0

    def seen(self, step: int, loss: float, weights: np.ndarray) -> None:
        if loss < self.best:
            self.best, self.weights, self.at = loss, weights.copy(), step

    def over(self, step: int) -> bool:
        return step - self.at >= self.patience


@dataclass
class Fitted:
    model: Model
    steps: int
    history: list[tuple[int, float, float]] = field(default_factory=list)  # step, training loss, validation loss


#: Makes a batch of a table of rows; it runs on the driver or in tasks.
ToBatch = Callable[[pa.Table], Batch]


def collected(df: DataFrame, to_batch: ToBatch, cap: int) -> Batch:
    """All rows of a frame that has no more than ``cap``."""
    rows = df.limit(cap + 1).toArrow()
    if len(rows) > cap:
        raise ValueError(f"more than {cap} rows; train in tasks (mode sync or local)")
    return to_batch(rows)


def fit(model: Model, train: DataFrame, validation: DataFrame, to_batch: ToBatch, spec: TrainSpec = TrainSpec()) -> Fitted:
    return {"driver": _on_driver, "sync": _summed, "local": _averaged}[spec.mode](model, train, validation, to_batch, spec)


def fit_batches(model: Model, train: Batch | Held, validation: Batch | Held, spec: TrainSpec) -> Fitted:
    """Mini-batches in a seeded order; the best weights by validation loss are set at the end."""
    rng = np.random.default_rng(spec.seed)
    optimiser, stop, out, step = LookaheadRAdam(spec.rate), EarlyStop(spec.patience), Fitted(model, 0), 0
    w = model.get()
    for _ in range(spec.epochs):
        order = rng.permutation(len(train))
        for i in range(0, len(order), spec.batch):
            loss = model.loss(train.take(order[i : i + spec.batch]), rng)
            w = optimiser.step(w, model.gradient())
            model.set(w)
            step += 1
            if step % spec.eval_every == 0:
                held = mean_loss(model, validation)
                stop.seen(step, held, w)
                out.history.append((step, loss, held))
                if stop.over(step):
                    break
        if stop.over(step) and stop.weights is not None:
            break
    held = mean_loss(model, validation)
    stop.seen(step, held, w)
    model.set(stop.weights if stop.weights is not None else w)
    out.steps = step
    return out


def mean_loss(model: Model, rows: Batch | Held, size: int = 4096) -> float:
    if not len(rows):
        return float("inf")
    size = at_once(rows, size)
    parts = [(model.value(rows.take(np.arange(i, min(i + size, len(rows))))), min(size, len(rows) - i)) for i in range(0, len(rows), size)]
    return sum(v * n for v, n in parts) / len(rows)


def scored(model: Model, rows: Batch | Held, size: int = 4096) -> Iterator[tuple[int, Batch, np.ndarray]]:
    """Where each block of rows begins, the block, and the model's scores of it."""
    size = at_once(rows, size)
    for i in range(0, len(rows), size):
        block = rows.take(np.arange(i, min(i + size, len(rows))))
        yield i, block, model.probabilities(block)


def _on_driver(model, train, validation, to_batch, spec) -> Fitted:
    return fit_batches(model, collected(train, to_batch, spec.driver_rows), collected(validation, to_batch, spec.driver_rows), spec)


#: Vectors that come to the driver at most; more are summed in tasks first, as many at a time.
FAN = 8


def _per_task(df: DataFrame, model: Model, weights: np.ndarray, to_batch: ToBatch, work: Callable[[Model, Batch], tuple[float, np.ndarray]], whole: bool = False) -> tuple[float, np.ndarray, int]:
    """Sums over tasks of loss and vector, each times its rows, and the rows.

    A task works on a batch at a time, or with ``whole`` on all its rows. Vectors are summed in tasks ``FAN`` at a time, so what comes
    to the driver does not grow with the partitions.
    """
    shared = df.sparkSession.sparkContext.broadcast((pickle.dumps(model), weights))
    schema = "loss double, v binary, n long"

    def row(loss: float, vector: np.ndarray, n: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([loss]), pa.array([vector.tobytes()], pa.binary()), pa.array([n], pa.int64())], names=["loss", "v", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, loss, vector, n = None, 0.0, None, 0
        parts = (pa.Table.from_batches([b]) for b in batches if b.num_rows)
        if whole:
            every = list(parts)
            parts = iter([pa.concat_tables(every)] if every else [])
        for part in parts:
            own = own or pickle.loads(shared.value[0])
            own.set(shared.value[1])
            rows = to_batch(part)
            more, v = work(own, rows)
            loss, n = loss + more * len(rows), n + len(rows)
            vector = v * len(rows) if vector is None else vector + v * len(rows)
        if n:
            yield row(loss, vector, n)

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        loss, vector, n = 0.0, None, 0
        for batch in batches:
            for more, v, m in zip(*(batch.column(i) for i in range(3)), strict=True):
                v = np.frombuffer(v.as_buffer())
                loss, n, vector = loss + more.as_py(), n + m.as_py(), v.copy() if vector is None else vector + v
        if n:
            yield row(loss, vector, n)

    got, parts = df.mapInArrow(run, schema), df.rdd.getNumPartitions()
    while parts > FAN:
        # Each step deals the vectors of ``FAN`` tasks to one.
        group, parts = F.floor(F.spark_partition_id() / FAN), -(-parts // FAN)
        got = got.repartition(parts, group).mapInArrow(summed, schema)
    got = got.collect()
    n = sum(r["n"] for r in got)
    shared.unpersist()
    if not n:
        return float("inf"), np.zeros_like(weights), 0
    return sum(r["loss"] for r in got) / n, sum(np.frombuffer(r["v"]) for r in got) / n, n


def _gradient(model: Model, rows: Batch) -> tuple[float, np.ndarray]:
    loss = model.loss(rows)
    return loss, model.gradient()


def _loss_only(model: Model, rows: Batch) -> tuple[float, np.ndarray]:
    return mean_loss(model, rows), np.zeros(1)


def _summed(model, train, validation, to_batch, spec) -> Fitted:
    """One job per update: the gradient of a global mini-batch, summed over tasks. Dropout is off, so partitions don't matter."""
    total = train.count()
    parts = max(1, -(-total // spec.batch))
    rows = train.withColumn("_part", F.pmod(F.xxhash64("sample_id"), F.lit(parts))).persist()
    optimiser, stop, out, step = LookaheadRAdam(spec.rate), EarlyStop(spec.patience), Fitted(model, 0), 0
    w = model.get()
    for _ in range(spec.epochs):
        for part in range(parts):
            loss, g, n = _per_task(rows.filter(F.col("_part") == part).drop("_part"), model, w, to_batch, _gradient)
            if n:
                w = optimiser.step(w, g)
                step += 1
        held, _, _ = _per_task(validation, model, w, to_batch, _loss_only)
        stop.seen(step, held, w)
        out.history.append((step, loss, held))
        if stop.over(step):
            break
    rows.unpersist()
    model.set(stop.weights if stop.weights is not None else w)
    out.steps = step
    return out


def _averaged(model, train, validation, to_batch, spec) -> Fitted:
    """Each task makes ``local_steps`` updates on its own rows; weights are averaged by rows. A job per round, not per update."""
    stop, out, step = EarlyStop(spec.patience), Fitted(model, 0), 0
    w = model.get()
    train = train.persist()

    def work(own: Model, rows: Batch, seed: int) -> tuple[float, np.ndarray]:
        rng, optimiser, v, loss = np.random.default_rng(seed), LookaheadRAdam(spec.rate), own.get(), 0.0
        for _ in range(spec.local_steps):
            loss = own.loss(rows.take(rng.integers(0, len(rows), spec.batch)), rng)
            v = optimiser.step(v, own.gradient())
            own.set(v)
        return loss, v

    for epoch in range(spec.epochs):
        loss, mean, n = _per_task(train, model, w, to_batch, lambda m, r, e=epoch: work(m, r, spec.seed + e), whole=True)
        w = mean if n else w
        step += spec.local_steps
        held, _, _ = _per_task(validation, model, w, to_batch, _loss_only)
        stop.seen(step, held, w)
        out.history.append((step, loss, held))
        if stop.over(step):
            break
    train.unpersist()
    model.set(stop.weights if stop.weights is not None else w)
    out.steps = step
    return out


_TOLD = "train_rows long, steps int, history array<struct<step:int,training:double,held:double>>, weights binary, low array<double>, high array<double>"
_CELLS = f"rotation int, sample_id long, class_id int, y int, p double, {_TOLD}"
_ARRAYS = f"rotation int, sample_id long, y array<int>, p array<double>, {_TOLD}"


def fit_groups(model: Model, rows: DataFrame, to_batch: ToBatch, spec: TrainSpec, held: str = "validation", scaled: tuple[str, ...] = (), turns: dict[int, Turn] | None = None, arrays: bool = False) -> DataFrame:
    """A model for each rotation, trained side by side in tasks, each on its rotation's rows (at most ``driver_rows``, as counted by the caller).

    ``rows``: rotation, role, sample_id and the batch's columns; ``scaled`` ones are brought to 0..1 by the training part.
    Returns scores of the test part, (rotation, sample_id, class_id, y, p) or with ``arrays`` a row for each of its rows with the true
    classes and all scores; and a row more for each rotation, without sample, that tells what was trained: rows, steps, loss
    curve, weights, and the range of the scaled columns.
    """
    packed, turns = pickle.dumps(model), turns or {}

    def train_one(key, table):  # without annotations, which Spark would read as the kind of function
        own, rotation = pickle.loads(packed), key[0].as_py()
        # Rows come in any order; mini-batches are drawn from a defined one.
        table = table.sort_by([(c, "ascending") for c in ("sample_id", "chunk_no") if c in table.column_names])
        role = table.column("role").to_numpy(zero_copy_only=False)
        low, high = [], []
        for name in scaled:
            x = table.column(name).to_numpy().astype(float)
            seen = x[role == "train"]
            lo, hi = (float(seen.min()), float(seen.max())) if len(seen) else (0.0, 0.0)
            low, high = [*low, lo], [*high, hi]
            table = table.set_column(table.schema.get_field_index(name), name, pa.array(minmax(x, lo, hi)))
        ids = table.column("sample_id").to_numpy()
        every = turned(held_by(to_batch, table), turns.get(rotation, Turn()))
        part = lambda name: some_of(every, np.flatnonzero(role == name))
        train, test = part("train"), part("test")
        ids = ids[role == "test"]
        fitted = fit_batches(own, train, part(held), spec)
        kinds = {f.name: f.type for f in (_ARRAY_TYPES if arrays else _CELL_TYPES)}
        for i, data, p in scored(own, test):
            at, classes = ids[i : i + len(p)], p.shape[1]
            if arrays:
                given = {"sample_id": at, "y": _true_classes(data.y), "p": pa.FixedSizeListArray.from_arrays(pa.array(p.ravel()), classes).cast(pa.list_(pa.float64()))}
            else:
                given = {"sample_id": np.repeat(at, classes), "class_id": np.tile(np.arange(classes, dtype=np.int32), len(at)), "y": data.y.ravel().astype(np.int32), "p": p.ravel()}
            yield _filled(kinds, rotation, given)
        yield _filled(kinds, rotation, {
            "train_rows": [len(train)], "steps": [fitted.steps], "history": [_curve(fitted.history)], "weights": [own.get().tobytes()], "low": [low], "high": [high],
        })

    # More parts than rotations: a task for nearly each; a count that is asked for is not coalesced.
    dealt = rows.repartition(64, "rotation").groupBy("rotation")

    def run(key, table):
        made = list(train_one(key, table))
        return pa.Table.from_batches(made, made[0].schema)

    return dealt.applyInArrow(run, _ARRAYS if arrays else _CELLS)


_HISTORY = pa.list_(pa.struct([("step", pa.int32()), ("training", pa.float64()), ("held", pa.float64())]))
_TOLD_TYPES = [("train_rows", pa.int64()), ("steps", pa.int32()), ("history", _HISTORY), ("weights", pa.binary()), ("low", pa.list_(pa.float64())), ("high", pa.list_(pa.float64()))]
_CELL_TYPES = pa.schema([("rotation", pa.int32()), ("sample_id", pa.int64()), ("class_id", pa.int32()), ("y", pa.int32()), ("p", pa.float64()), *_TOLD_TYPES])
_ARRAY_TYPES = pa.schema([("rotation", pa.int32()), ("sample_id", pa.int64()), ("y", pa.list_(pa.int32())), ("p", pa.list_(pa.float64())), *_TOLD_TYPES])


def _filled(kinds: dict[str, pa.DataType], rotation: int, given: dict) -> pa.RecordBatch:
    """Rows of a rotation, null in all columns that are not given."""
    n = len(next(iter(given.values())))
    given = {"rotation": np.full(n, rotation, np.int32)} | given
    return pa.RecordBatch.from_arrays([(v if isinstance(v := given[c], pa.Array) else pa.array(v, kind)) if c in given else pa.nulls(n, kind) for c, kind in kinds.items()], names=list(kinds))


def _curve(history: list[tuple[int, float, float]]) -> list[dict]:
    return [{"step": int(s), "training": float(t), "held": float(h)} for s, t, h in history]


def _true_classes(y: np.ndarray) -> pa.Array:
    """The class numbers of each row, from labels by class."""
    row, at = np.nonzero(y)
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(y)))]).astype(np.int32)), pa.array(at.astype(np.int32)))


# ---------------------------------------------------------------- all rotations at once

#: Parts of a sample in a rotation, as the column ``parts`` has them for each rotation; -1: none.
TRAIN, VALIDATION, TEST = 0, 1, 2


#: Bytes of rows that a task holds at once. A task with more works on them as several smaller tasks would, one after the other.
HELD_BYTES = 1 << 25


def slices(batches: Iterator[pa.RecordBatch], most: int | None = None) -> Iterator[pa.Table]:
    """The rows of a task, ``most`` bytes of them (``HELD_BYTES``) or a batch at a time."""
    most = HELD_BYTES if most is None else most
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        if held and size + b.nbytes > most:
            yield pa.Table.from_batches(held)
            held, size = [], 0
        if b.num_rows:
            held.append(b)
            size += b.nbytes
    if held:
        yield pa.Table.from_batches(held)


#: Rows of a block, about. A block is what one task trains on between two averages, at every size of the input and on every cluster.
BLOCK_ROWS = 1 << 14


def in_blocks(rows: DataFrame, most: int | None = None) -> DataFrame:
    """``rows`` with ``block``, to be written: a block in a partition, in a defined order. Blocks follow from the rows alone, not from how they were dealt."""
    n = max(1, -(-rows.count() // (most or BLOCK_ROWS)))
    order = [c for c in ("sample_id", "chunk_no") if c in rows.columns]
    return rows.withColumn("block", F.pmod(F.xxhash64("sample_id"), F.lit(n)).cast("int")).repartitionById(n, "block").sortWithinPartitions(*order)


def by_block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows of a task a block at a time; those of a block follow each other."""
    held: list[pa.RecordBatch] = []
    now = None
    for b in batches:
        if not b.num_rows:
            continue
        block = b.column(b.schema.get_field_index("block")).to_numpy()
        edges = [0, *(np.flatnonzero(np.diff(block)) + 1), b.num_rows]
        for i, j in zip(edges, edges[1:], strict=False):
            if held and block[i] != now:
                yield pa.Table.from_batches(held)
                held = []
            now = block[i]
            held.append(b.slice(i, j - i))
    if held:
        yield pa.Table.from_batches(held)


def _by_turn(df: DataFrame, to_batch: ToBatch, turns: list[Turn], model: Model, weights: list[np.ndarray | None], part: int, work: Callable[[Model, Held, int], tuple[float, np.ndarray]]) -> list[tuple[float, np.ndarray | None, int]]:
    """For each rotation with weights: sums over tasks of loss and vector, each times its rows, and the rows. A task reads its rows once for all rotations.

    ``work`` gets the rows of a block, or of a slice where rows are in no blocks, so that what a task holds does not grow with it.
    """
    parted = by_block if "block" in df.columns else slices
    shared = df.sparkSession.sparkContext.broadcast((pickle.dumps(model), weights, turns))
    schema, names = "turn int, loss double, v binary, n long", ["turn", "loss", "v", "n"]

    def row(turn: int, loss: float, vector: np.ndarray, n: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([turn], pa.int32()), pa.array([loss]), pa.array([vector.tobytes()], pa.binary()), pa.array([n], pa.int64())], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed, own_weights, own_turns = shared.value
        got: dict[int, list] = {}
        for table in parted(batches):
            every, parts = held_by(to_batch, table), parts_of(table, len(own_turns))
            for i, w in enumerate(own_weights):
                at = np.flatnonzero(parts[:, i] == part)
                if w is None or not len(at):
                    continue
                own = pickle.loads(packed)
                own.set(w)
                loss, v = work(own, some_of(turned(every, own_turns[i]), at), i)
                more(got, i, loss * len(at), v * len(at), len(at))
        yield from rows_of(got)

    def more(got: dict[int, list], turn: int, loss: float, v: np.ndarray, n: int) -> None:
        old = got.get(turn)
        got[turn] = [loss, v.copy(), n] if old is None else [old[0] + loss, old[1] + v, old[2] + n]

    def rows_of(got: dict[int, list]) -> Iterator[pa.RecordBatch]:
        for turn, (loss, v, n) in sorted(got.items()):
            yield row(turn, loss, v, n)

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got: dict[int, list] = {}
        for batch in batches:
            for turn, loss, v, n in zip(*(batch.column(i) for i in range(4)), strict=True):
                more(got, turn.as_py(), loss.as_py(), np.frombuffer(v.as_buffer()), n.as_py())
        yield from rows_of(got)

    got, tasks = df.mapInArrow(run, schema), df.rdd.getNumPartitions()
    while tasks > 1:  # one vector of each rotation comes to the driver, whatever the tasks
        group, tasks = F.floor(F.spark_partition_id() / FAN), -(-tasks // FAN)
        got = got.repartition(tasks, group).mapInArrow(summed, schema)
    out: list[tuple[float, np.ndarray | None, int]] = [(float("inf"), None, 0)] * len(turns)
    for r in got.toArrow().to_pylist():
        out[r["turn"]] = (r["loss"] / r["n"], np.frombuffer(r["v"]) / r["n"], r["n"])
    shared.destroy()
    return out


def parts_of(table: pa.Table, turns: int) -> np.ndarray:
    return table.column("parts").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, turns)


def fit_turns(model: Model, rows: DataFrame, to_batch: ToBatch, spec: TrainSpec, turns: list[Turn], held: int = VALIDATION, blocks: int | None = None) -> tuple[list[np.ndarray], list[Fitted]]:
    """The weights of every rotation, all of them in the same two jobs an epoch; weights are averaged by rows.

    ``rows``: ``parts`` (array with the part in each rotation) and what a batch takes. With ``blocks``, the number of ``in_blocks``, an
    epoch takes every training row once: each block's in mini-batches of a seeded order, from the weights of the last average. Else
    each task makes ``local_steps`` updates of every rotation's weights on its own rows, as in ``local`` mode.
    """
    w = [model.get() for _ in turns]
    stops, out, live = [EarlyStop(spec.patience) for _ in turns], [Fitted(model, 0) for _ in turns], [True] * len(turns)

    def drawn(rng: np.random.Generator, n: int) -> Iterator[np.ndarray]:
        if blocks:
            order = rng.permutation(n)
            yield from (order[i : i + spec.batch] for i in range(0, n, spec.batch))
        else:
            yield from (rng.integers(0, n, spec.batch) for _ in range(spec.local_steps))

    def work(own: Model, part: Held, epoch: int) -> tuple[float, np.ndarray]:
        rng, optimiser, v, loss = np.random.default_rng(spec.seed + epoch), LookaheadRAdam(spec.rate), own.get(), 0.0
        part = made_once(part)
        for at in drawn(rng, len(part)):
            loss = own.loss(part.take(at), rng)
            v = optimiser.step(v, own.gradient())
            own.set(v)
        return loss, v

    for epoch in range(spec.epochs):
        going = [x if on else None for x, on in zip(w, live, strict=True)]
        made = _by_turn(rows, to_batch, turns, model, going, TRAIN, lambda m, r, _, e=epoch: work(m, r, e))
        w = [v if on and n else x for x, (_, v, n), on in zip(w, made, live, strict=True)]
        going = [x if on else None for x, on in zip(w, live, strict=True)]
        seen = _by_turn(rows, to_batch, turns, model, going, held, lambda m, r, _: (mean_loss(m, by_length(r)), np.zeros(1)))
        for i, on in enumerate(live):
            if on:
                # Updates of a block, on average.
                out[i].steps += -(-made[i][2] // (spec.batch * blocks)) if blocks else spec.local_steps
                stops[i].seen(out[i].steps, seen[i][0], w[i])
                out[i].history.append((out[i].steps, made[i][0], seen[i][0]))
                live[i] = not stops[i].over(out[i].steps)
    return [x if s.weights is None else s.weights for x, s in zip(w, stops, strict=True)], out


def score_turns(model: Model, rows: DataFrame, to_batch: ToBatch, turns: list[Turn], rotations: tuple[int, ...], weights: list[np.ndarray]) -> DataFrame:
    """(rotation, sample_id, y, p) of each rotation's test part: the true classes and all scores. Rows are read once for all rotations."""
    shared = rows.sparkSession.sparkContext.broadcast((pickle.dumps(model), weights, turns))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed, own_weights, own_turns = shared.value
        own = pickle.loads(packed)
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            every, parts, ids = held_by(to_batch, table), parts_of(table, len(own_turns)), table.column("sample_id").to_numpy()
            for i, w in enumerate(own_weights):
                test = by_length(some_of(every, np.flatnonzero(parts[:, i] == TEST)))
                at = np.arange(len(test)) if test.rows is None else test.rows
                own.set(w)
                for first, data, p in scored(own, turned(test, own_turns[i])):
                    of = at[first : first + len(p)]
                    p = pa.FixedSizeListArray.from_arrays(pa.array(p.ravel()), p.shape[1]).cast(pa.list_(pa.float64()))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(of), rotations[i], np.int32)), pa.array(ids[of]), _true_classes(data.y), p], names=["rotation", "sample_id", "y", "p"])

    return rows.mapInArrow(run, "rotation int, sample_id long, y array<int>, p array<double>")


def score(model: Model, rows: DataFrame, to_batch: ToBatch, key: str = "sample_id", classes: bool = True) -> DataFrame:
    """(key, class_id, y, p) for every row and class, or one row with an array of scores per sample."""
    shared = rows.sparkSession.sparkContext.broadcast(pickle.dumps(model))
    n = model.n_classes if hasattr(model, "n_classes") else model.trajectory.n_classes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pickle.loads(shared.value)
        for batch in batches:
            if not batch.num_rows:
                continue
            data = to_batch(pa.Table.from_batches([batch]))
            p = own.probabilities(data)
            ids = batch.column(batch.schema.get_field_index(key))
            if classes:
                columns = [ids.take(pa.array(np.repeat(np.arange(len(p)), n))), pa.array(np.tile(np.arange(n, dtype=np.int32), len(p))), pa.array(data.y.ravel().astype(np.int32)), pa.array(p.ravel())]
                yield pa.RecordBatch.from_arrays(columns, names=[key, "class_id", "y", "p"])
            else:
                yield pa.RecordBatch.from_arrays([ids, pa.array(list(p), pa.list_(pa.float64())), pa.array([np.flatnonzero(v).astype(np.int32) for v in data.y], pa.list_(pa.int32()))], names=[key, "p", "y"])

    schema = f"{key} long, class_id int, y int, p double" if classes else f"{key} long, p array<double>, y array<int>"
    return rows.mapInArrow(run, schema)


def extract(model, rows: DataFrame, to_batch: ToBatch, model_id: str, key: str = "visit_id") -> DataFrame:
    """(visit_id, model_id, h): fused vectors of a visit model, to be stored and windowed."""
    shared = rows.sparkSession.sparkContext.broadcast(pickle.dumps(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pickle.loads(shared.value)
        for batch in batches:
            if batch.num_rows:
                h = own.visit_vector(to_batch(pa.Table.from_batches([batch]))).astype(np.float32)
                yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(key)), pa.array([model_id] * len(h)), pa.array(list(h), pa.list_(pa.float32()))], names=[key, "model_id", "h"])

    return rows.mapInArrow(run, f"{key} long, model_id string, h array<float>")
