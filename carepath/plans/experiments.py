"""Experiment configurations and their runs: one configuration is one row of a results table.

A run builds the visits with the features it names and nothing else, deals folds, balances, trains one model per rotation, scores
the test part, merges chunks, and measures. Encounters, code lists, chunk vectors, concept vectors, windows and folds are each
made once, written, and read by every configuration and rotation (``Prepared``). Folds are dealt once from all encounters, so that a
visit encoder and the sequence model on its vectors see the same parts. ``Scale`` holds what is smaller here than in
production: widths, epochs, rotations.
"""

from __future__ import annotations

import pickle
import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from carepath.functions import scoring
from carepath.functions.vectors import pool
from carepath.measures import metrics
from carepath.models import encoders
from carepath.models import train as TR
from carepath.models.nets import FeatureSpec, TrajectoryModel, VisitModel
from carepath.models.packed import At, Builder, Turn, Visits, Windows
from carepath.operators import codes as C
from carepath.operators import cohorts, folds, notes, sequences, temporal
from carepath.session import give_back
from carepath.sources import retail
from carepath.sources.stores import written


@dataclass(frozen=True)
class Scale:
    d: int = 32
    temporal_width: int = 50
    epochs: int = 3
    rotations: tuple[int, ...] = (0,)
    rate: float = 3e-3
    batch: int = 64
    #: grouped: all rotations in the same tasks, block by block; local: with a few updates a task; else one after the other as in ``models.train``.
    mode: str = "grouped"


@dataclass(frozen=True)
class Config:
    name: str
    task: str = "return"  # or "codes"
    features: str = "gap+stay"
    #: Vocabulary of diagnoses: grp or parent.
    level: str = "grp"
    folds: str = "subject"  # subject, visit, visit5, labels, holdout
    balance: str | None = "iteration"  # iteration, once, None
    encoder: str = "frozen"  # frozen, tuned_train, tuned_all
    target: str = "next"  # or current
    target_kind: str = "D"
    #: Sequence settings; None: a single visit.
    cell: str | None = None
    hidden: int = 25
    layers: int = 1
    bidirectional: bool = False
    window: int = 3
    source: str = "vector"  # or multi_hot, concepts
    samples: str = "sliding"  # or prefixes
    head: str = "sigmoid"
    #: Only visits that end a window of so many visits, for comparison with models on windows.
    targets_of: int | None = None
    scale: Scale = Scale()


# ---------------------------------------------------------------- tables made once


class Prepared:
    """Tables of one input, each made at its first use, written to the shared folder and read from then on."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir
        self._made: dict[tuple, object] = {}
        self._lock = threading.RLock()
        self._locks: dict[tuple, threading.RLock] = {}

    def once(self, key: tuple, make: Callable[[], object]):
        """What ``make`` gave for this key the first time; a frame is written. Other keys can be made meanwhile."""
        with self._lock:
            own = self._locks.setdefault(key, threading.RLock())
        with own:
            if key not in self._made:
                found = make()
                self._made[key] = written(found) if isinstance(found, DataFrame) else found
            return self._made[key]

    def encounters(self) -> DataFrame:
        """subject_id, visit_id, admit_ts, gap, stay, y_return of every visit."""

        def make() -> DataFrame:
            enc = temporal.return_label(temporal.stay_length(temporal.prior_gap(retail.encounters(self.spark, self.sf_dir), first_fill=365)))
            return enc.select("subject_id", "visit_id", "admit_ts", F.col("gap_days").cast("double").alias("gap"), F.col("stay_days").cast("double").alias("stay"), "y_return")

        return self.once(("encounters",), make)

    def codes(self, kind: str, level: str) -> tuple[DataFrame, DataFrame, DataFrame]:
        """(visit_id, codes) at a level, its vocabulary, and (visit_id, ids)."""
        column = "concept" if kind == "M" else level

        def mapped() -> DataFrame:
            events = retail.code_events(self.spark, self.sf_dir, kind)
            if kind == "M":
                events = events.withColumn("code", F.substring_index("code", "-", 1))
            return C.map_codes(events, self.dictionary(kind), column)

        lists = self.once(("codes", kind, column), lambda: C.ordered_list(mapped(), distinct=True))
        vocab = self.once(("vocabulary", kind, column), lambda: C.vocabulary(mapped()))
        return lists, vocab, self.once(("ids", kind, column), lambda: C.ids(lists, vocab))

    def dictionary(self, kind: str) -> DataFrame:
        return retail.code_dict(self.spark, self.sf_dir, "P" if kind == "P" else "D")

    def concepts(self, kind: str, level: str, d: int) -> DataFrame:
        """(code, vec): the store of concept vectors that every configuration of this width looks up."""
        column = "concept" if kind == "M" else level
        named = self.dictionary(kind).groupBy(F.col(column).alias("code")).agg(F.min("description").alias("description"))
        return self.once(("concepts", kind, column, d), lambda: encoders.concept_table(named, encoders.HashedProjection(d)))

    def chunks(self) -> DataFrame:
        return self.once(("chunks",), lambda: chunks(self.spark, self.sf_dir))

    def chunk_vectors(self, d: int) -> DataFrame:
        """(visit_id, chunk_no, text): the frozen encoder's store; text is encoded once, whatever the epochs and rotations."""
        return self.once(("chunk vectors", d), lambda: _vectors(self.chunks(), encoders.HashedProjection(d)))

    def dealt(self, cfg: Config) -> DataFrame:
        """Folds of all encounters: (subject_id, fold), (visit_id, fold), or (visit_id, run, role) where parts are drawn for each rotation."""
        enc = self.encounters()

        def make() -> DataFrame:
            if cfg.folds == "subject":
                return folds.by_subject(enc.groupBy("subject_id").agg(F.max("y_return").alias("y_patient")), 10).select("subject_id", "fold")
            if cfg.folds in ("visit", "visit5"):
                return folds.by_visit(enc, 5 if cfg.folds == "visit5" else 10).select("visit_id", "fold")
            if cfg.folds == "holdout":
                return folds.random_holdout(enc, runs=3).select("visit_id", "run", F.when(F.col("split") == "train", "train").otherwise("test").alias("role"))
            samples = self.codes("D", cfg.level)[0].select(F.col("visit_id").alias("key"), F.col("codes").alias("labels"))
            each = [folds.iterative_label_split(samples, {"train": 8, "validation": 1, "test": 1}, seed=42 + i).select(F.col("key").alias("visit_id"), F.lit(i).alias("run"), F.col("split").alias("role")) for i in range(3)]
            out = each[0]
            for e in each[1:]:
                out = out.unionByName(e)
            return out

        return self.once(("folds", cfg.folds, cfg.level if cfg.folds == "labels" else None), make)


# ---------------------------------------------------------------- rows of features


def visits(prep: Prepared, cfg: Config) -> tuple[DataFrame, dict]:
    """One row per visit: ids, features but text, sparse labels; and concept matrices, sizes and class number."""
    spec, info = FeatureSpec.of(cfg.features), {"tables": {}, "sizes": {}, "n_classes": 1, "first": 0}
    kinds = [(name, kind) for name, kind in (("dx", "D"), ("proc", "P"), ("med", "M")) if getattr(spec, name)]
    for name, kind in kinds:
        lists, vocab, _ = prep.codes(kind, cfg.level)
        column = "concept" if kind == "M" else cfg.level
        info["sizes"][name] = prep.once(("longest", kind, column), lambda lists=lists: lists.agg(F.max("n_codes")).first()[0])
        info["tables"][name] = prep.once(("matrix", kind, column, cfg.scale.d), lambda kind=kind, vocab=vocab: encoders.matrix(prep.concepts(kind, cfg.level, cfg.scale.d), vocab, cfg.scale.d))
    if cfg.task == "codes":
        vocab = prep.codes(cfg.target_kind, cfg.level)[1]
        info["n_classes"], info["first"] = prep.once(("classes", cfg.target_kind, cfg.level), vocab.count), C.FIRST_ID

    def make() -> DataFrame:
        enc = prep.encounters()
        if cfg.targets_of:
            ends = sequences.sliding(enc, cfg.targets_of).select(F.element_at(F.filter("visit_ids", lambda v: v.isNotNull()), -1).alias("visit_id"))
            enc = enc.join(ends, "visit_id", "left_semi")
        if cfg.task == "codes":
            lists, _, ids = prep.codes(cfg.target_kind, cfg.level)
            if cfg.target == "next":
                following = cohorts.next_codes_label(prep.encounters(), lists).select("visit_id", F.col("next_visit").alias("_next"))
                enc = enc.join(following, "visit_id").join(ids.select(F.col("visit_id").alias("_next"), F.col("ids").alias("y")), "_next").drop("_next")
            else:
                enc = enc.join(ids.select("visit_id", F.col("ids").alias("y")), "visit_id")
        else:
            enc = enc.withColumn("y", F.when(F.col("y_return") == 1, F.array(F.lit(0))).otherwise(F.array().cast("array<int>")))
        for name, kind in kinds:
            size = info["sizes"][name]
            sparse = prep.codes(kind, cfg.level)[2].select("visit_id", F.slice(F.concat("ids", F.array_repeat(F.lit(0), size)), 1, size).alias(name))
            enc = enc.join(sparse, "visit_id", "left").withColumn(name, F.coalesce(name, F.array_repeat(F.lit(0), size)))
        return enc

    return prep.once(("visits", cfg.task, cfg.target, cfg.target_kind, cfg.level, tuple(kinds), cfg.targets_of), make), info


def _vectors(chunked: DataFrame, encoder: encoders.HashedProjection) -> DataFrame:
    return encoders.encode_text(chunked, encoder).select("visit_id", "chunk_no", F.col("vec").alias("text"))


def with_text(rows: DataFrame, vectors: DataFrame, d: int) -> DataFrame:
    """A row per chunk of the visit's note; visits without a note have one row with a vector of zeros."""
    zero = F.array_repeat(F.lit(0.0).cast("float"), d)
    return rows.join(vectors, "visit_id", "left").withColumns({"chunk_no": F.coalesce("chunk_no", F.lit(0)), "text": F.coalesce("text", zero)})


def chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return notes.chunk(retail.notes(spark, sf_dir).withColumn("text", notes.clean(F.col("text"))))


def as_batch(features: tuple[str, ...], n_classes: int, first: int, own_text: int | None = None) -> Visits:
    """From rows of visits to arrays; labels become dense in the task, a mini-batch at a time."""
    return Visits(features, n_classes, first, own_text)


# ---------------------------------------------------------------- roles


def turns(cfg: Config) -> int:
    """Rotations that the fold scheme has."""
    return {"visit5": 5, "holdout": 3, "labels": 3}.get(cfg.folds, 10)


def roles(rows: DataFrame, prep: Prepared, cfg: Config) -> DataFrame:
    """``rows`` with rotation and role, once for each of the configuration's rotations; the folds are the same for every table of this input."""
    dealt, wanted = prep.dealt(cfg), F.col("rotation").isin(*cfg.scale.rotations)
    if cfg.folds in ("holdout", "labels"):
        return rows.join(dealt.withColumnRenamed("run", "rotation").filter(wanted), "visit_id")
    turn = folds.rotation(prep.spark, turns(cfg)).withColumnRenamed("iter", "rotation").filter(wanted)
    return rows.join(dealt, "subject_id" if cfg.folds == "subject" else "visit_id").join(F.broadcast(turn), "fold").drop("fold")


def balanced(rows: DataFrame, cfg: Config) -> DataFrame:
    """All positives and as many negatives in each part of a rotation."""
    return folds.balance(rows, by=["rotation", "role"], iteration=F.col("rotation")) if cfg.balance == "iteration" else rows


#: Roles by their number in ``parts``.
ROLES = ("train", "validation", "test")


def parted(rows: DataFrame, prep: Prepared, cfg: Config) -> DataFrame:
    """``rows`` once, with ``parts``: the number of its role in each of the configuration's rotations, -1 where it is in none. Rows in no rotation go.

    What ``roles`` and ``balanced`` give, without a copy of the row for each rotation.
    """
    turn, every = cfg.scale.rotations, turns(cfg)
    number = lambda role: F.array_position(F.array(*map(F.lit, ROLES)), role) - 1
    if cfg.balance != "iteration" and cfg.folds not in ("holdout", "labels"):
        of = {r["fold"]: r["parts"] for r in _of_folds(prep, every, turn)}
        listed = F.array(*(F.array(*(F.lit(v).cast("tinyint") for v in of[i])) for i in range(every)))
        return rows.join(prep.dealt(cfg), "subject_id" if cfg.folds == "subject" else "visit_id").withColumn("parts", F.element_at(listed, F.col("fold") + 1)).drop("fold")

    def make() -> DataFrame:
        if cfg.balance == "iteration":
            long = balanced(roles(rows.select("subject_id", "visit_id", "y_return"), prep, cfg), cfg)
        else:
            long = prep.dealt(cfg).withColumnRenamed("run", "rotation").filter(F.col("rotation").isin(*turn))
        of = lambda i: F.coalesce(F.max(F.when(F.col("rotation") == i, number(F.col("role")))), F.lit(-1)).cast("tinyint")
        return long.groupBy("visit_id").agg(F.array(*map(of, turn)).alias("parts"))

    level = cfg.level if cfg.folds == "labels" else None
    return rows.join(prep.once(("parts", cfg.folds, level, cfg.balance, turn, cfg.targets_of), make), "visit_id")


def _of_folds(prep: Prepared, every: int, turn: tuple[int, ...]) -> list[dict]:
    """The parts of each fold."""
    role = {(r["iter"], r["fold"]): ROLES.index(r["role"]) for r in prep.once(("rotation", every), lambda: folds.rotation(prep.spark, every).collect())}
    return [{"fold": f, "parts": [role[i, f] for i in turn]} for f in range(every)]


def unfolded(rows: DataFrame, turn: tuple[int, ...], own_text: int | None = None) -> DataFrame:
    """A row for each rotation that it has a part in, with rotation and role instead of ``parts``."""
    long = rows.select("*", F.posexplode("parts").alias("_i", "_r")).filter("_r >= 0")
    if own_text:
        long = long.withColumn("text", F.slice("text", F.col("_i") * own_text + 1, own_text))
    listed = lambda values, at: F.element_at(F.array(*map(F.lit, values)), F.col(at) + 1)
    return long.withColumns({"rotation": listed(turn, "_i"), "role": listed(ROLES, "_r")}).drop("parts", "_i", "_r")


# ---------------------------------------------------------------- one configuration


@dataclass
class Trained:
    """What a configuration's rotations gave: (rotation, sample_id, class_id, y, p), the same with a row per sample, and a row of ``told`` for each."""

    scores: DataFrame
    told: DataFrame
    model: VisitModel | TrajectoryModel
    #: (rotation, role, subject_id), and the samples themselves with ``parts``.
    rows: DataFrame
    kept: DataFrame
    build: Builder
    #: (rotation, sample_id, y, p): true classes and scores of all classes; a row of text per chunk is not merged here.
    arrays: DataFrame | None = None


def spec_of(cfg: Config) -> TR.TrainSpec:
    s = cfg.scale
    return TR.TrainSpec(batch=s.batch, epochs=s.epochs, rate=s.rate, mode=s.mode)


def _held(cfg: Config) -> str:
    return "test" if cfg.folds == "holdout" else "validation"


_TOLD = ["rotation", "train_rows", "steps", "history", "weights", "low", "high"]


def trained(cfg: Config, model, rows: DataFrame, build: Builder, scaled: list[str]) -> Trained:
    """Every rotation of ``rows`` (parts, block, subject_id, sample_id and what a batch takes), in the same way at every size."""
    spec, turn = spec_of(cfg), cfg.scale.rotations
    own = rows.drop("subject_id", "visit_id")
    below = build.turns or [Turn(place=i) for i in range(len(turn))]
    seen = unfolded(rows.select("subject_id", "parts"), turn)
    cells = lambda a: a.select("rotation", "sample_id", F.posexplode("p").alias("class_id", "p"), "y").select("rotation", "sample_id", "class_id", F.array_contains("y", F.col("class_id")).cast("int").alias("y"), "p")
    kinds = "rotation int, train_rows long, steps int, history array<struct<step:int,training:double,held:double>>, weights binary, low array<double>, high array<double>"
    within = lambda i, c=None: F.when(F.col("parts")[i] == TR.TRAIN, F.lit(1) if c is None else F.col(c))
    got = rows.agg(*(F.count(within(i)).alias(f"n{i}") for i in range(len(turn))), *(f(within(i, c)).cast("double").alias(f"{f.__name__}{i}_{c}") for i in range(len(turn)) for c in scaled for f in (F.min, F.max)), F.max("block").alias("last")).first()
    low, high = ([[float(got[f"{f}{i}_{c}"] or 0) for c in scaled] for i in range(len(turn))] for f in ("min", "max"))
    sides = [replace(b, bounds={**b.bounds, **{c: (low[i][n], high[i][n]) for n, c in enumerate(scaled)}}) for i, b in enumerate(below)]
    if cfg.scale.mode in ("grouped", "local"):  # all tasks train all rotations
        give_back(rows.sparkSession)  # of the heap that making the rows took; from here on Python workers need the memory
        weights, fitted = TR.fit_turns(model, own, build, spec, sides, TR.TEST if _held(cfg) == "test" else TR.VALIDATION, (got["last"] or 0) + 1 if cfg.scale.mode == "grouped" else None)
    else:
        start, weights, fitted = model.get(), [], []
        for i in range(len(turn)):
            part = lambda n, i=i: own.filter(F.col("parts")[i] == n).drop("parts")
            model.set(start.copy())
            fitted.append(TR.fit(model, part(TR.TRAIN), part(TR.TEST if _held(cfg) == "test" else TR.VALIDATION), At(build, sides[i]), spec))
            weights.append(model.get())
        model.set(start)
    told = [(r, got[f"n{i}"], fitted[i].steps, fitted[i].history, weights[i].tobytes(), low[i], high[i]) for i, r in enumerate(turn)]
    give_back(rows.sparkSession)
    arrays = TR.score_turns(model, own, build, sides, turn, weights)
    return Trained(cells(arrays), rows.sparkSession.createDataFrame(told, kinds), model, seen, rows, build, arrays)


def visit_models(prep: Prepared, cfg: Config) -> Trained:
    """Each rotation's model is trained on its training part; time features are scaled and a tuned text encoder is fitted by that part alone, unless the configuration says otherwise."""
    features = FeatureSpec.of(cfg.features)
    base, info = visits(prep, cfg)
    rows, own_text = parted(folds.balance_once(base) if cfg.balance == "once" else base, prep, cfg), None
    if features.text:
        rows = written(rows)
        if cfg.encoder == "frozen":
            rows = with_text(rows, prep.chunk_vectors(cfg.scale.d), cfg.scale.d)
        else:
            rows, own_text = with_text(rows, _tuned_vectors(rows, prep, cfg), cfg.scale.d * len(cfg.scale.rotations)), cfg.scale.d
    rows = written(TR.in_blocks(rows.withColumn("sample_id", F.col("visit_id")).select("parts", "subject_id", "visit_id", "sample_id", *(["chunk_no"] if features.text else []), *features.names, "y")))
    build = as_batch(features.names, info["n_classes"], info["first"], own_text)
    model = VisitModel(features, info["n_classes"], info["tables"], info["sizes"], cfg.scale.d, cfg.scale.temporal_width, head=cfg.head)
    out = trained(cfg, model, rows, build, [c for c in ("gap", "stay") if c in features.names])
    if features.text:  # a visit has a row per chunk
        out.scores, out.arrays = scoring.merge_chunks(out.scores, per=("rotation",)).drop("n_chunks"), None
    return out


def _tuned_vectors(rows: DataFrame, prep: Prepared, cfg: Config) -> DataFrame:
    """(visit_id, chunk_no, text): the vectors of all rotations' encoders side by side; texts are read twice, however many rotations there are."""
    fit_on = [F.col("parts")[i] >= 0 if cfg.encoder == "tuned_all" else F.col("parts")[i] == TR.TRAIN for i in range(len(cfg.scale.rotations))]

    def make() -> DataFrame:
        labelled = prep.chunks().join(rows.select("visit_id", "y_return", "parts"), "visit_id")
        tuned = encoders.label_tuned_each(labelled, "y_return", fit_on, cfg.scale.d)
        return encoders.encode_each(prep.chunks(), tuned, ("visit_id", "chunk_no")).withColumnRenamed("vec", "text")

    return prep.once(("tuned vectors", cfg.encoder, cfg.folds, cfg.balance, cfg.scale.rotations, cfg.scale.d), make)


def visit_vectors(prep: Prepared, cfg: Config) -> tuple[list[Turn], VisitModel, DataFrame, DataFrame]:
    """What makes the vectors of visits in a rotation's windows, for each rotation; the visit model; the encoder's (rotation, role, subject_id); and its rows with their parts."""
    own = replace(cfg, name="visit vectors", cell=None, hidden=0, layers=1, bidirectional=False, window=0, samples="", balance=None if cfg.task == "codes" else cfg.balance)

    def make() -> tuple[list[Turn], VisitModel, DataFrame, DataFrame]:
        t = visit_models(prep, own)
        columns, told = [c for c in ("gap", "stay") if c in t.model.spec.names], {r["rotation"]: r for r in t.told.select("rotation", "weights", "low", "high").collect()}
        out = []
        for i in cfg.scale.rotations:
            t.model.set(np.frombuffer(told[i]["weights"]).copy())
            bounds = dict(zip(columns, zip(told[i]["low"], told[i]["high"], strict=True), strict=True))
            out.append(Turn(bounds, below=pickle.dumps(t.model)))
        return out, t.model, t.rows, t.kept

    return prep.once(("visit vectors", own), make)


def steps_of_visits(prep: Prepared, cfg: Config) -> DataFrame:
    """All visits with ``step``, the features that a visit model makes a vector of; of a note's chunks the mean, as the vector's text is linear in them."""
    features = FeatureSpec.of(cfg.features)
    every, _ = visits(prep, replace(cfg, task="return", targets_of=None))
    if features.text:
        zero = F.array_repeat(F.lit(0.0), cfg.scale.d)
        mean = prep.once(("mean chunk vectors", cfg.scale.d), lambda: pool(prep.chunk_vectors(cfg.scale.d), "visit_id", "text", "mean"))
        every = every.join(mean, "visit_id", "left").withColumn("text", F.coalesce("text", zero))
    return prep.encounters().join(every.select("visit_id", F.struct("visit_id", *features.names).alias("step")), "visit_id")


def windows(prep: Prepared, cfg: Config, ready: DataFrame) -> DataFrame:
    """(subject_id, sample_id, visit_id, steps, mask, y): samples of visits with ``step``, and their targets."""
    if cfg.samples == "prefixes":
        made = sequences.prefixes(ready, carry=["step"]).withColumn("mask", F.transform("visit_ids", lambda v: F.lit(True)))
    else:
        made = sequences.sliding(ready, cfg.window, carry=["step"], last_visit="keep" if cfg.task == "return" else "drop")
    if cfg.task == "return":
        labels = prep.encounters().select(F.col("visit_id").alias("target_visit"), F.when(F.col("y_return") == 1, F.array(F.lit(0))).otherwise(F.array().cast("array<int>")).alias("y"))
    else:
        labels = prep.codes(cfg.target_kind, cfg.level)[2].select(F.col("visit_id").alias("target_visit"), F.col("ids").alias("y"))
    return made.join(labels, "target_visit").select("subject_id", F.col("target_visit").alias("sample_id"), F.col("target_visit").alias("visit_id"), F.col("step").alias("steps"), "mask", "y")


def sequence_models(prep: Prepared, cfg: Config) -> Trained:
    """Windows over vectors of a visit model of the same rotation, over sums of concept vectors, or over sparse codes; targets as in the task."""
    _, vocab, ids = prep.codes(cfg.target_kind, cfg.level)
    n_vocab = prep.once(("classes", cfg.target_kind, cfg.level), vocab.count)
    n_classes, first = (1, 0) if cfg.task == "return" else (n_vocab, C.FIRST_ID)
    enc = prep.encounters()
    below = None
    if cfg.source == "vector":  # windows are the same for all rotations; their visits become vectors in the tasks
        below, visit_model, _, _ = visit_vectors(prep, cfg)
        width, steps = visit_model.spec.width(cfg.scale.d, cfg.scale.temporal_width), visit_model.spec.names
        made = prep.once(("windows of visits", cfg.task, cfg.target_kind, cfg.level, cfg.window, cfg.samples, steps, cfg.scale.d), lambda: windows(prep, cfg, steps_of_visits(prep, cfg)))
    elif cfg.source == "concepts":  # a visit is the sum of its codes' concept vectors
        width, steps = cfg.scale.d, "vectors"
        summed = prep.once(("summed concepts", cfg.level, width), lambda: encoders.multi_hot_concept(ids, vocab, prep.concepts("D", cfg.level, width)))
        step = summed.select("visit_id", F.col("vec").cast("array<double>").alias("step"))
        made = windows(prep, cfg, enc.join(step, "visit_id", "left").withColumn("step", F.coalesce("step", F.array_repeat(F.lit(0.0), width))))
    else:
        width, steps = n_vocab, "ids"
        made = prep.once(("windows", cfg.task, cfg.target_kind, cfg.level, cfg.window, cfg.samples), lambda: windows(prep, cfg, sequences.attach_multi_hot(enc, ids).withColumnRenamed("x", "step")))
    key = ("windows with parts", cfg.source, cfg.task, cfg.target_kind, cfg.level, cfg.window, cfg.samples, steps, width, cfg.folds, cfg.scale.rotations)
    rows = prep.once(key, lambda: TR.in_blocks(parted(made, prep, replace(cfg, balance=None))))
    build = Windows(n_classes, first, width, None if cfg.samples == "prefixes" else cfg.window, steps, C.FIRST_ID)
    build.turns = below
    net = TrajectoryModel(width, n_classes, cfg.cell, cfg.hidden, cfg.layers, cfg.bidirectional, head=cfg.head)
    return trained(cfg, net, rows, build, [])


def audited(prep: Prepared, cfg: Config, t: Trained) -> DataFrame:
    """(rotation, leaked): test patients that a model of the run was trained or stopped on, the visit encoder below it included; rotations without any are left out.

    A patient is one row, with a bit for each rotation that has seen it and one for each that tests it.
    """
    turn = cfg.scale.rotations

    def bits(rows: DataFrame, tests: bool) -> DataFrame:
        of = lambda hit: sum((F.when(hit(F.col("parts")[i]), F.lit(1 << i)).otherwise(F.lit(0)) for i in range(len(turn))), F.lit(0)).cast("long")
        tested = of(lambda p: p == TR.TEST) if tests else F.lit(0).cast("long")
        return rows.select("subject_id", of(lambda p: (p >= 0) & (p != TR.TEST)).alias("seen"), tested.alias("tested")).groupBy("subject_id").agg(F.bit_or("seen").alias("seen"), F.bit_or("tested").alias("tested"))

    both = bits(t.kept, True)
    if cfg.cell and cfg.source == "vector":
        both = both.unionByName(bits(visit_vectors(prep, cfg)[3], False)).groupBy("subject_id").agg(F.bit_or("seen").alias("seen"), F.bit_or("tested").alias("tested"))
    leaked = both.select(F.col("seen").bitwiseAND(F.col("tested")).alias("b")).filter("b <> 0")
    counts = leaked.agg(*(F.count(F.when(F.col("b").bitwiseAND(F.lit(1 << i)) != 0, 1)).alias(f"n{i}") for i in range(len(turn))))
    each = F.explode(F.array(*(F.struct(F.lit(r).alias("rotation"), F.col(f"n{i}").alias("leaked")) for i, r in enumerate(turn)))).alias("s")
    return counts.select(each).select("s.*").filter("leaked > 0")


#: Configurations run side by side; their Spark jobs interleave.
TURNS = 4


def runs(spark: SparkSession, sf_dir: str, configs: list[Config], prep: Prepared | None = None) -> DataFrame:
    """One row per configuration and rotation: rows and steps of training, the loss curve, the audits, and the task's measures."""
    prep = prep or Prepared(spark, sf_dir)

    def one(cfg: Config) -> DataFrame:
        began = time.time()
        t = (sequence_models if cfg.cell else visit_models)(prep, cfg)
        ks, task = (10, 20, 30) if cfg.level == "parent" else (3, 5, 10), "binary" if cfg.task == "return" else "multilabel"
        if t.arrays is not None:
            measured = metrics.suite_arrays(t.arrays, task, ks)
        else:
            measured = metrics.suite(written(t.scores.select("rotation", "sample_id", "class_id", "y", "p")), task, ks, per=["rotation"])
        measured = written(measured)
        told = t.told.drop("weights", "low", "high").join(audited(prep, cfg, t), "rotation", "left").fillna(0, ["leaked"])
        # An encoder tuned on every row was fitted on all that is tested.
        fitted_on = F.lit(cfg.encoder == "tuned_all" and "text" in cfg.features.split("+"))
        told = told.select(F.lit(cfg.name).alias("config"), "*", fitted_on.alias("encoder_leak"), F.lit(round(time.time() - began, 2)).alias("seconds"))
        return written(told.join(measured, "rotation", "left").select("config", "rotation", *(c for c in told.columns if c not in ("config", "rotation")), *(c for c in measured.columns if c != "rotation")))

    out = None
    for task, level in sorted({(c.task, c.level) for c in configs}):
        with ThreadPoolExecutor(TURNS) as workers:
            for rows in list(workers.map(one, [c for c in configs if (c.task, c.level) == (task, level)])):
                out = rows if out is None else out.unionByName(rows, allowMissingColumns=True)
    return out


def run_all(spark: SparkSession, sf_dir: str, configs: list[Config], prep: Prepared | None = None, log: Tracker | None = None) -> DataFrame:
    """A results table: one row per configuration with means and deviations over its rotations, and the audits' sums. ``log`` keeps the rotations."""
    each = written(runs(spark, sf_dir, configs, prep))
    if log is not None:
        log.add(each)
    told = each.groupBy("config").agg(F.sum("leaked").alias("leaked"), F.max("encoder_leak").alias("encoder_leak"), F.sum("train_rows").alias("train_rows"))
    return metrics.over_folds(each, "config", measures_of(each)).join(told, "config")


def measures_of(each: DataFrame) -> list[str]:
    return [c for c in each.columns if c in ("precision", "recall", "f1", "rp", "aupr", "auc") or c.startswith("recall_")]


def in_full(configs: list[Config]) -> list[Config]:
    """Configurations with every rotation of their folds: ten, five of ``visit5``, three of holdouts and of splits by labels."""
    return [replace(c, scale=replace(c.scale, rotations=tuple(range(turns(c))))) for c in configs]


def width_sweep(spark: SparkSession, sf_dir: str, widths: tuple[int, ...] = (1, 2, 5, 10, 20, 50, 100, 200, 500), scale: Scale = Scale()) -> DataFrame:
    return run_all(spark, sf_dir, [Config(f"width {w}", scale=replace(scale, temporal_width=w)) for w in widths])


def compared(spark: SparkSession, sf_dir: str, configs: list[Config]) -> DataFrame:
    """Each configuration's means against those of the first: differences in points and per cent."""
    each = written(runs(spark, sf_dir, configs))
    measures = measures_of(each)
    means = written(metrics.over_folds(each, "config", measures).select("config", *(F.col(f"{m}_mean").alias(m) for m in measures)))
    return metrics.compare(means, "config", configs[0].name, measures)


def cost_report(spark: SparkSession, sf_dir: str, epochs: int) -> DataFrame:
    """(how, encoder_passes): a frozen encoder's vectors stored once against encoding in every epoch."""
    n = chunks(spark, sf_dir).agg(F.count("*").alias("c"))
    stack = F.explode(F.array(F.struct(F.lit("stored").alias("how"), F.col("c").alias("encoder_passes")), F.struct(F.lit("recomputed").alias("how"), (F.col("c") * epochs).alias("encoder_passes"))))
    return n.select(stack.alias("s")).select("s.*")


class Tracker:
    """An append-only log of runs in Parquet."""

    def __init__(self, path: str):
        self.path = path

    def add(self, rows: DataFrame) -> None:
        rows.write.mode("append").parquet(self.path)

    def best(self, spark: SparkSession, measure: str) -> DataFrame:
        return spark.read.parquet(self.path).orderBy(F.desc(measure), "config").limit(1)
