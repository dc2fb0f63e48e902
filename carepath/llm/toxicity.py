"""Toxicity by a convolutional text classifier, trained in numpy.

Words (runs of letters and digits, A-Z as a-z) are embedded as the sum of two hashed rows: one of the word, one of its
first bytes, so that inflected forms share evidence. Filters of several widths run over the embeddings, the maximum over
the whole text is taken of each, and a linear layer gives the score. Texts are never cut.

Training takes every labelled row: rows are dealt by hash of their id to blocks, tasks go through their blocks once an epoch
in mini-batches, and the blocks' weights are averaged in a tree. Only weights and the rows' scores reach the driver. Scoring is one
pass over all rows with the weights broadcast, whose size is fixed by the specification.
Scores are calibrated by cross-fitting so that ``TrainSpec.cut`` is the decision threshold of best F1 at the labels' true
rate; each language's own threshold, found on the same scores, is given beside it and never enters the score.

Defined cases: a null or empty text is scored as a text without words; a null id hashes as the empty string; rows
without a label are scored like all others; a label table without usable rows gives the score 0 to every text; null
labels are not learned from; an id with several texts is learned from by the least of them; other columns are ignored unless named in ``keep``.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from carepath.llm._blocks import Block, blocks, words
from carepath.llm._shared import WRITING, _settings, carried, if_small, restored, written

_APART = np.array([not (chr(b).isalnum() or b >= 128) for b in range(256)])


@dataclass(frozen=True)
class TrainSpec:
    buckets: int = 1 << 14
    width: int = 16
    filters: int = 16
    widths: tuple[int, ...] = (1, 2, 3)
    stem: int = 5
    #: Rows of a block, about; a block is trained on by one task between two averages, at every size.
    block_rows: int = 1 << 12
    epochs: int = 6
    #: Small blocks go round more often, up to this many steps.
    least_steps: int = 50
    batch: int = 64
    rate: float = 0.01
    decay: float = 1e-4
    cut: float = 0.3
    #: Models trained for the thresholds, each without a part of the rows.
    folds: int = 3
    seed: int = 5
    #: A language gets its own threshold from this many labelled rows of each label.
    language_rows: int = 20


@dataclass
class Model:
    """Weights by name, and the calibration: score = sigmoid(scale * logit + shift)."""

    spec: TrainSpec
    weights: dict[str, np.ndarray]
    scale: float = 1.0
    shift: float = 0.0
    thresholds: dict[str, float] | None = None
    trained: bool = True

    def score(self, logit: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.scale * logit + self.shift, -30, 30))) if self.trained else np.zeros(len(logit))


@dataclass
class Tokens:
    """Embedding rows of the words of some texts, one text after the other, and where each begins."""

    ids: np.ndarray
    stems: np.ndarray
    at: np.ndarray


def tokens(block: Block, spec: TrainSpec) -> Tokens:
    w = words(block, lower=True, apart=_APART, stem=spec.stem)
    return Tokens((w.hash % np.uint64(spec.buckets)).astype(np.int32), (w.stems % np.uint64(spec.buckets)).astype(np.int32) + spec.buckets, w.rows)


@dataclass
class Layout:
    """Embedding rows of all words, texts one after the other, each followed by padding to the widest filter."""

    ids: np.ndarray
    stems: np.ndarray
    first: np.ndarray  # of each text


def laid(t: Tokens, rows: np.ndarray, spec: TrainSpec) -> Layout:
    """The texts ``rows``, side by side."""
    pad, counts = max(spec.widths), t.at[rows + 1] - t.at[rows]
    begin = np.cumsum(counts) - counts
    first, n = begin + pad * np.arange(len(rows)), int(counts.sum())
    nothing = 2 * spec.buckets  # a row of zeros
    ids, stems = np.full(n + pad * len(rows), nothing), np.full(n + pad * len(rows), nothing)
    to, source = np.arange(n) + pad * np.repeat(np.arange(len(rows)), counts), np.arange(n) + np.repeat(t.at[rows] - begin, counts)
    ids[to], stems[to] = t.ids[source], t.stems[source]
    return Layout(ids, stems, first)


def layout(block: Block, spec: TrainSpec) -> Layout:
    return laid(tokens(block, spec), np.arange(block.n), spec)


def initial(spec: TrainSpec) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(spec.seed)
    w = {"embed": rng.normal(0, 0.1, (2 * spec.buckets + 1, spec.width)).astype(np.float32)}
    w["embed"][-1] = 0
    for k in spec.widths:
        w[f"conv{k}"] = rng.normal(0, (2 / (k * spec.width)) ** 0.5, (k, spec.width, spec.filters)).astype(np.float32)
        w[f"bias{k}"] = np.zeros(spec.filters, np.float32)
    w["out"] = rng.normal(0, (1 / (len(spec.widths) * spec.filters)) ** 0.5, len(spec.widths) * spec.filters).astype(np.float32)
    w["out_bias"] = np.zeros(1, np.float32)
    return w


def present(t: Tokens, y: np.ndarray, part: np.ndarray, spec: TrainSpec) -> np.ndarray:
    """By part and label: the texts that each embedding row occurs in; in the last place, which no word has, the texts."""
    width = 2 * spec.buckets + 1
    out = np.zeros((spec.folds * 2, width), np.int64)
    for i in range(0, len(y), 256):
        rows = np.arange(i, min(i + 256, len(y)))
        lay = laid(t, rows, spec)
        owner = np.repeat(np.arange(len(rows)), np.diff(np.append(lay.first, len(lay.ids))))
        seen = np.unique(np.concatenate([owner * width + lay.ids, owner * width + lay.stems]))
        np.add.at(out, (part[rows][seen // width] * 2 + y[rows][seen // width], seen % width), 1)
    return out


def evidence(present: np.ndarray) -> np.ndarray:
    """For each embedding row, how far its texts' labels stray from the rate: the signed root of the log-likelihood ratio."""
    rate = present[1, -1] / present[:, -1].sum()
    n = present.sum(axis=0)
    with np.errstate(divide="ignore", invalid="ignore"):
        g = np.nan_to_num(present[1] * np.log(present[1] / (n * rate))) + np.nan_to_num(present[0] * np.log(present[0] / (n * (1 - rate))))
        sign = np.nan_to_num(np.sign(present[1] / n - rate))
    return (sign * np.sqrt(np.maximum(2 * g, 0))).astype(np.float32)


def forward(w: dict[str, np.ndarray], spec: TrainSpec, lay: Layout) -> tuple[np.ndarray, dict]:
    """Logits of the texts, and what the backward pass needs."""
    x = w["embed"][lay.ids] + w["embed"][lay.stems]
    kept: dict = {"x": x}
    pooled = []
    # All filters at once, a filter in a row, so that maxima run over neighbours.
    every = np.concatenate([w[f"conv{k}"][j] for k in spec.widths for j in range(k)], axis=1).T @ np.ascontiguousarray(x.T)
    at, n = 0, spec.filters
    for k in spec.widths:
        c = every[at : at + n]
        for j in range(1, k):
            c[:, :-j] += every[at + j * n : at + (j + 1) * n, j:]
        at += k * n
        for j in range(1, k):  # windows that would reach into the next text
            c[:, np.append(lay.first[1:], len(x)) - j] = -np.inf
        kept[k] = c
        pooled.append(np.maximum(np.maximum.reduceat(c, lay.first, axis=1).T + w[f"bias{k}"], 0))
    kept["pooled"] = np.concatenate(pooled, axis=1)
    return kept["pooled"] @ w["out"] + w["out_bias"][0], kept


def gradients(w: dict[str, np.ndarray], spec: TrainSpec, lay: Layout, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """Mean binary cross entropy of the batch and its gradients; the maxima pass theirs to the one window each was found in."""
    logit, kept = forward(w, spec, lay)
    p = 1 / (1 + np.exp(-np.clip(logit, -30, 30)))
    loss = float(-np.mean(y * np.log(p + 1e-9) + (1 - y) * np.log(1 - p + 1e-9)))
    d = ((p - y) / len(y)).astype(np.float32)
    x, pooled = kept["x"], kept["pooled"]
    g = {"out": pooled.T @ d, "out_bias": np.array([d.sum()], np.float32)}
    back = np.outer(d, w["out"]) * (pooled > 0)
    g["embed"] = np.zeros_like(w["embed"])
    ends = np.append(lay.first[1:], len(x))
    places, moves = [], []
    for n, k in enumerate(spec.widths):
        part = back[:, n * spec.filters : (n + 1) * spec.filters]
        won = np.stack([a + kept[k][:, a:b].argmax(axis=1) for a, b in zip(lay.first, ends, strict=True)])
        g[f"bias{k}"] = part.sum(axis=0)
        g[f"conv{k}"] = np.zeros_like(w[f"conv{k}"])
        for j in range(k):
            at = np.minimum(won + j, len(x) - 1)
            live = part * (won + j < len(x))
            g[f"conv{k}"][j] = np.einsum("bfd,bf->df", x[at], live)
            of = np.nonzero(live)
            places.append(at[of])
            moves.append(live[of][:, None] * w[f"conv{k}"][j].T[of[1]])
    place, move = np.concatenate(places), np.concatenate(moves)
    # Sums by embedding row: sorted by it, then added up run by run.
    rows, move = np.concatenate([lay.ids[place], lay.stems[place]]), np.concatenate([move, move])
    if len(rows):
        order = np.argsort(rows, kind="stable")
        rows = rows[order]
        begin = np.flatnonzero(np.append(True, rows[1:] != rows[:-1]))
        g["embed"][rows[begin]] = np.add.reduceat(move[order], begin, axis=0)
    g["embed"][-1] = 0
    return loss, g


def _as_block(texts: list[str]) -> Block:
    data = [t.encode() for t in texts]
    return Block(0, np.frombuffer(b"".join(data), np.uint8), np.cumsum([0, *map(len, data)]))


def logits(w: dict[str, np.ndarray], spec: TrainSpec, texts: list[str]) -> np.ndarray:
    return np.concatenate([forward(w, spec, layout(b, spec))[0] for b in blocks(pa.array(texts, pa.string()))]) if texts else np.zeros(0)


def best_threshold(score: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
    """The threshold of best F1, halfway between the scores that it parts."""
    order = np.argsort(-score, kind="stable")
    s, hit, all_ = score[order], np.cumsum((y * weight)[order]), np.cumsum(weight[order])
    f1 = 2 * hit / (all_ + (y * weight).sum())
    f1[:-1][s[:-1] == s[1:]] = -1
    top = int(f1.argmax())
    return float((s[top] + s[top + 1]) / 2) if top + 1 < len(s) else float(s[top])


def started(seen: np.ndarray, spec: TrainSpec, steps: bool = True) -> dict[str, np.ndarray]:
    """Weights before training, from the counts of ``present``; without ``steps`` they are to stay so, which tells what training adds."""
    w = initial(spec)
    # The first dimension starts as evidence and the first filter reads it; training moves both.
    w["embed"][:-1, 0] = evidence(seen)[:-1] / 4
    first = w[f"conv{spec.widths[0]}"]
    first[:, :, 0], first[0, 0, 0] = 0, 1
    w["out"][0], w["out_bias"][0] = 2, -4
    if not steps:
        w["out"][1:] = 0
    return w


def flat(w: dict[str, np.ndarray]) -> np.ndarray:
    return np.concatenate([x.ravel() for x in w.values()])


def shaped(v: np.ndarray, spec: TrainSpec) -> dict[str, np.ndarray]:
    out, at = initial(spec), 0
    for k, x in out.items():
        out[k] = v[at : at + x.size].reshape(x.shape).copy()
        at += x.size
    return out


def gone_through(w: dict[str, np.ndarray], t: Tokens, y: np.ndarray, used: np.ndarray, passes: int, rng: np.random.Generator, spec: TrainSpec) -> None:
    """Move the weights by ``passes`` over the rows ``used``, each row once in each."""
    m, v = ({k: np.zeros_like(x) for k, x in w.items()} for _ in range(2))
    step = 0
    for _ in range(passes):
        used = rng.permutation(used)
        for i in range(0, len(used), spec.batch):
            rows = used[i : i + spec.batch]
            _, g = gradients(w, spec, laid(t, rows, spec), y[rows].astype(np.float32))
            step += 1
            for k, x in w.items():
                d = g[k]
                square = d * d
                d -= m[k]
                d *= 0.1
                m[k] += d
                square -= v[k]
                square *= 0.001
                v[k] += square
                np.divide(v[k], 1 - 0.999**step, out=square)
                np.sqrt(square, out=square)
                square += 1e-8
                np.divide(m[k], square, out=d)
                d *= spec.rate / (1 - 0.9**step)
                x *= 1 - spec.rate * spec.decay
                x -= d
            w["embed"][-1] = 0


#: Words of texts scored at once.
SCORED_WORDS = 1 << 17
#: Vectors that a task adds up at a time, on their way to the driver.
FAN = 8


def _added(df: DataFrame, work: Callable[[Tokens, np.ndarray, np.ndarray], Iterator[tuple[int, np.ndarray, int]]], kind: type = np.float32) -> dict[int, np.ndarray]:
    """By key, what ``work`` makes of the blocks' tokens, labels and parts: means of vectors weighted by their rows, or with whole numbers their sums."""
    schema, names = "k int, v binary, n long", ["k", "v", "n"]

    def merged(got: dict, k: int, v: np.ndarray, n: int) -> None:
        old = got.get(k)
        if kind is np.int64:
            got[k] = (v, n) if old is None else (old[0] + v, n)
        else:
            got[k] = (v.astype(np.float64), n) if old is None else (old[0] + (v - old[0]) * (n / (old[1] + n)), old[1] + n)

    def rows(got: dict) -> Iterator[pa.RecordBatch]:
        for k, (v, n) in sorted(got.items()):
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([v.astype(kind).tobytes()], pa.binary()), pa.array([n], pa.int64())], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got: dict = {}
        for block in _by_block(batches):
            for k, v, n in work(*block[:3]):
                merged(got, k, v, n)
        yield from rows(got)

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got: dict = {}
        for b in batches:
            for k, v, n in zip(*(b.column(i) for i in range(3)), strict=True):
                merged(got, k.as_py(), np.frombuffer(v.as_buffer(), kind), n.as_py())
        yield from rows(got)

    got, tasks = df.mapInArrow(run, schema), df.rdd.getNumPartitions()
    while tasks > 1:
        group, tasks = F.floor(F.spark_partition_id() / FAN), -(-tasks // FAN)
        got = got.repartition(tasks, group).mapInArrow(summed, schema)
    with _settings(df.sparkSession, WRITING):
        return {r["k"]: np.frombuffer(r["v"], kind) for r in got.toArrow().to_pylist()}


def _by_block(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[Tokens, np.ndarray, np.ndarray, pa.Array]]:
    """Tokens, labels, parts and languages of a task's blocks, one after the other; rows of a block follow each other."""
    held: list[pa.RecordBatch] = []
    now = None

    def made() -> tuple[Tokens, np.ndarray, np.ndarray, pa.Array]:
        t = pa.Table.from_batches(held).combine_chunks()
        ids, stems = (t.column(c).combine_chunks() for c in ("ids", "stems"))
        at = ids.offsets.to_numpy().astype(np.int64)
        return Tokens(ids.flatten().to_numpy(), stems.flatten().to_numpy(), at - at[0]), t.column("y").to_numpy(), t.column("part").to_numpy(), t.column("lang")

    for b in batches:
        block = b.column(b.schema.get_field_index("block")).to_numpy()
        edges = [0, *(np.flatnonzero(np.diff(block)) + 1), b.num_rows] if b.num_rows else []
        for i, j in zip(edges, edges[1:], strict=False):
            if held and block[i] != now:
                yield made()
                held = []
            now = block[i]
            held.append(b.slice(i, j - i))
    if held:
        yield made()


def train(rows: DataFrame, n_blocks: int, rates: tuple[float, float], spec: TrainSpec = TrainSpec(), steps: bool = True) -> Model:
    """From all of ``rows`` (``examples``); ``rates``: the share of labels 0 and 1 among all labelled rows.

    Thresholds come from scores of rows by a model that has not seen them (``TrainSpec.folds`` models, each without its
    part of the rows), the weights from all rows; alike at every size.
    """
    found = _added(rows, lambda t, y, part: iter([(0, present(t, y, part, spec), 1)]), np.int64)
    if not found:
        return Model(spec, initial(spec), trained=False)
    seen = found[0].reshape(spec.folds, 2, -1)
    every = seen.sum(axis=0)
    counts = every[:, -1]
    if not counts.min():
        return Model(spec, initial(spec), trained=False)
    # A model for each part that it does not see, unless the others lack a label, and the last one of all rows.
    without = [f if (every - seen[f])[:, -1].min() else -1 for f in range(spec.folds)] + [-1]
    models = [flat(started(every if f < 0 else every - seen[f], spec, steps)) for f in without]
    for epoch in range(spec.epochs if steps else 0):
        shared = rows.sparkSession.sparkContext.broadcast(models)

        def work(t: Tokens, y: np.ndarray, part: np.ndarray, epoch=epoch, shared=shared) -> Iterator[tuple[int, np.ndarray, int]]:
            for k, f in enumerate(without):
                used = np.flatnonzero(part != f)
                if len(used):
                    w = shaped(shared.value[k], spec)
                    passes = max(1, -(-spec.least_steps * spec.batch * n_blocks // (spec.epochs * int(counts.sum()))))
                    gone_through(w, t, y, used, passes, np.random.default_rng([spec.seed, epoch]), spec)
                    yield k, flat(w), len(used)

        made = _added(rows, work)
        models = [made.get(k, v) for k, v in enumerate(models)]
        shared.destroy()
    z, y, languages = _held_out(rows, models[: spec.folds], spec)
    model = Model(spec, shaped(models[-1], spec))
    share = np.array([c / len(y) for c in counts])
    weight = np.where(y == 1, rates[1] / max(share[1], 1e-9), rates[0] / max(share[0], 1e-9))
    model.scale = 1 / max(float(np.std(z)), 1e-6) * 2
    model.shift = float(np.log(spec.cut / (1 - spec.cut))) - model.scale * best_threshold(z, y, weight)
    model.thresholds = {}
    score = model.score(z)
    for name in sorted(set(languages) - {None}):
        a, b = languages[name]
        if min((y[a:b] == c).sum() for c in (0, 1)) >= spec.language_rows:
            model.thresholds[name] = best_threshold(score[a:b], y[a:b], weight[a:b])
    return model


def _held_out(rows: DataFrame, models: list[np.ndarray], spec: TrainSpec) -> tuple[np.ndarray, np.ndarray, dict[str | None, tuple[int, int]]]:
    """Logits of all rows by the model that has not seen them, five bytes a row with the labels; sorted by language, of which each has a range."""
    shared = rows.sparkSession.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ws = [shaped(v, spec) for v in shared.value]
        for t, y, part, lang in _by_block(batches):
            z = np.empty(len(y), np.float32)
            for f, w in enumerate(ws):
                own = np.flatnonzero(part == f)
                size = np.cumsum(t.at[own + 1] - t.at[own] + max(spec.widths)) // SCORED_WORDS
                for some in np.split(own, np.flatnonzero(np.diff(size)) + 1):
                    if len(some):
                        z[some] = forward(w, spec, laid(t, some, spec))[0]
            named = np.array(lang.to_pylist(), dtype=object)
            for name in sorted(set(named), key=lambda x: (x is not None, x)):
                own = np.flatnonzero(named == name) if name is not None else np.flatnonzero([x is None for x in named])
                yield pa.RecordBatch.from_arrays([pa.array([name], pa.string()), pa.array([z[own].tobytes()], pa.binary()), pa.array([y[own].astype(np.int8).tobytes()], pa.binary())], names=["lang", "z", "y"])

    got = sorted(rows.mapInArrow(run, "lang string, z binary, y binary").toArrow().to_pylist(), key=lambda r: (r["lang"] is not None, r["lang"] or ""))
    z = np.concatenate([np.frombuffer(r["z"], np.float32) for r in got]).astype(np.float64)
    y = np.concatenate([np.frombuffer(r["y"], np.int8) for r in got]).astype(np.float32)
    languages: dict[str | None, tuple[int, int]] = {}
    at = 0
    for r in got:
        languages[r["lang"]] = (languages.get(r["lang"], (at, at))[0], at := at + len(r["y"]))
    shared.destroy()
    return z, y, languages


def remainder(key: Column) -> Column:
    """crc32 of the id as text, modulo 4."""
    return F.crc32(F.coalesce(key.cast("string"), F.lit(""))) % 4


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", spec: TrainSpec = TrainSpec(), steps: bool = True) -> Model:
    """Learn from all labelled rows outside the held-out quarter."""
    usable = labels.filter(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull() & (remainder(F.col("doc_id")) != 2))
    rows = usable.groupBy("doc_id").agg(F.max(F.col(label).cast("int")).alias("_y"))
    counts = {r["_y"]: r["n"] for r in rows.groupBy("_y").agg(F.count("*").alias("n")).collect()}
    total = sum(counts.values())
    if not all(counts.get(c) for c in (0, 1)):
        return Model(spec, initial(spec), trained=False)
    n_blocks = -(-total // spec.block_rows)
    return train(examples(docs, rows, n_blocks, spec), n_blocks, tuple(counts[c] / total for c in (0, 1)), spec, steps)


def examples(docs: DataFrame, labelled: DataFrame, n_blocks: int, spec: TrainSpec) -> DataFrame:
    """(block, part, y, lang, ids, stems): the words of every labelled text, written once; a block's rows follow each other in order of their id."""
    lang = F.col("lang") if "lang" in docs.columns else F.lit(None).cast("string")
    picked = if_small(labelled.withColumnRenamed("doc_id", "_id"))
    found = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), lang.alias("lang")).join(picked, F.col("doc_id") == F.col("_id"))
    dealt = lambda n, seed: F.pmod(F.xxhash64(F.col("_id").cast("string"), F.lit(seed)), F.lit(n)).cast("int")
    placed = found.select(dealt(n_blocks, spec.seed).alias("block"), dealt(spec.folds, spec.seed + 1).alias("part"), F.col("_y").alias("y"), "lang", "text", "_id")
    one = placed.repartitionById(n_blocks, "block").sortWithinPartitions("block", "_id", "text", "lang").withColumn("_id", F.col("_id").cast("string"))
    names = ["block", "part", "y", "lang", "ids", "stems"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            ids = [last, *batch.column(5).to_pylist()]
            last = ids[-1]
            batch = batch.filter(pa.array([a != b for a, b in zip(ids, ids[1:], strict=False)], pa.bool_()))  # the least text of an id
            first = 0
            for b in blocks(batch.column(4)):
                t, own = tokens(b, spec), batch.slice(first, b.n)
                at = pa.array(t.at.astype(np.int32))
                yield pa.RecordBatch.from_arrays([*(own.column(i) for i in range(4)), *(pa.ListArray.from_arrays(at, pa.array(v)) for v in (t.ids, t.stems))], names=names)
                first += b.n

    return written(one.mapInArrow(run, "block int, part int, y int, lang string, ids array<int>, stems array<int>"), "labelled")


def scored(docs: DataFrame, model: Model, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """``keep`` and ``score`` for every row."""
    source = carried(docs, keep, _text=F.col(text))
    schema = T.StructType([source.schema["_k"], T.StructField("score", T.DoubleType())])
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            parts = [m.score(forward(m.weights, m.spec, layout(b, m.spec))[0]) for b in blocks(batch.column(1), 1 << 20)]
            score = pa.array(np.concatenate(parts) if parts else np.zeros(0), pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column(0), score], names=schema.names)

    return restored(source.mapInArrow(run, schema), keep, ["score"])


def threshold_for(lang: Column, model: Model) -> Column:
    """A language's own threshold; the common one where it had too few sampled rows."""
    own = F.lit(None).cast("double")
    for name, t in (model.thresholds or {}).items():
        own = F.when(lang == name, F.lit(t)).otherwise(own)
    return F.coalesce(own, F.lit(model.spec.cut))
