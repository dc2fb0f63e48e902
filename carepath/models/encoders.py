"""Text and concept encoders, their vector tables, and what is pooled from them.

No pretrained weights are at hand, so the frozen encoder is signed feature hashing; the interface (fit nowhere, encode
everywhere) is that of any frozen model. The label-tuned encoder weighs words by their evidence for a label and is a source
of leakage wherever it is fitted on rows that are tested.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from carepath.operators import codes as C
from carepath.sources.stores import written


def _hash(word: str, seed: int) -> int:
    return int.from_bytes(hashlib.blake2b(word.encode(), digest_size=8, key=str(seed).encode()).digest(), "little")


def _place(word: str, d: int, seed: int) -> tuple[int, float]:
    h = _hash(word, seed)
    return h % d, 1.0 if h >> 63 else -1.0


@dataclass
class HashedProjection:
    """Frozen: the same vector for the same text, whatever the labels. Vectors have length 1, or 0 without words."""

    d: int = 64
    seed: int = 3
    weights: dict[str, float] = field(default_factory=dict)
    #: Weights as a table (w, o), where there are too many to bring to tasks.
    table: DataFrame | None = field(default=None, repr=False)
    _known: dict[str, tuple[int, float]] = field(default_factory=dict, repr=False)

    def encode(self, texts: list[str]) -> np.ndarray:
        out = np.zeros((len(texts), self.d), np.float32)
        for row, text in zip(out, texts, strict=True):
            for w in (text or "").split():
                at = self._known.get(w)
                if at is None:
                    if len(self._known) > 200_000:
                        self._known.clear()
                    at = self._known[w] = _place(w, self.d, self.seed)
                row[at[0]] += at[1] * (self.weights.get(w, 0.05) if self.weights else 1.0)
        return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9) * (np.abs(out).sum(axis=1, keepdims=True) > 0)


#: Weights of words that are brought to tasks; beyond it all of them stay a table that is joined.
TUNED_WORDS = 50_000


def label_tuned(texts: DataFrame, label: str, d: int = 64, seed: int = 3) -> HashedProjection:
    """An encoder that weighs words by the size of their log odds among the rows it is fitted on (text, label)."""
    totals = texts.agg(F.sum(label).alias("p"), F.count("*").alias("n")).first()
    pos, neg = float(totals["p"] or 0), float((totals["n"] or 0) - (totals["p"] or 0))
    words = texts.select(label, F.explode(F.array_distinct(F.split("text", r"\s+"))).alias("w")).filter("w <> ''")
    counts = words.groupBy("w").agg(F.sum(label).alias("p"), F.count("*").alias("n")).filter("n >= 3")
    odds = F.abs(F.ln((F.col("p") + 0.5) / (pos + 1.0)) - F.ln((F.col("n") - F.col("p") + 0.5) / (neg + 1.0)))
    weights = counts.select("w", odds.alias("o"))
    few = weights.limit(TUNED_WORDS + 1).collect()
    if len(few) > TUNED_WORDS:
        return HashedProjection(d, seed, table=written(weights))
    return HashedProjection(d, seed, {r["w"]: float(r["o"]) for r in few})


@dataclass
class Tuned:
    """Encoders of several rotations: a word's place is the same in all, its weight is not.

    ``hashes`` are those of the words in order, ``weights`` a row for each with its weight by rotation; ``blank`` is that of other words.
    ``table``: (w, o), where there are too many words to bring to tasks.
    """

    d: int
    seed: int
    turns: int
    blank: tuple[float, ...]
    hashes: np.ndarray | None = None
    weights: np.ndarray | None = None
    table: DataFrame | None = None

    def of(self, word: str) -> tuple[int, np.ndarray]:
        """A word's place and its signed weights."""
        h = _hash(word, self.seed)
        at = int(np.searchsorted(self.hashes, np.uint64(h)))
        found = self.weights[at] if at < len(self.hashes) and int(self.hashes[at]) == h else np.array(self.blank)
        return h % self.d, (1.0 if h >> 63 else -1.0) * found


#: Bytes of hashes and weights that are brought to tasks; beyond it, or if two words have one hash, weights stay a table that is joined.
TUNED_BYTES = 64 << 20


#: The weight of a word that an encoder has not seen often enough; it never saw any word where it has no weights at all.
UNSEEN = 0.05


def label_tuned_each(texts: DataFrame, label: str, fit_on: list, d: int = 64, seed: int = 3) -> Tuned:
    """``label_tuned`` for each condition of ``fit_on``, with the words of the texts counted once for all."""
    n = range(len(fit_on))
    sums = lambda f: [f(F.when(c, v)).alias(f"{name}{i}") for i, c in enumerate(fit_on) for name, v in (("p", F.col(label)), ("n", F.lit(1)))]
    inside = texts.select("text", F.col(label).cast("int").alias("_y"), *(c.alias(f"_c{i}") for i, c in enumerate(fit_on)))
    totals = texts.agg(*sums(F.sum)).first()
    words = inside.select(F.explode(F.array_distinct(F.split("text", r"\s+"))).alias("w"), "_y", *(f"_c{i}" for i in n)).filter("w <> ''")
    counts = words.groupBy("w").agg(*(F.count(F.when(F.col(f"_c{i}") & (F.col("_y") == 1), 1)).alias(f"p{i}") for i in n), *(F.count(F.when(F.col(f"_c{i}"), 1)).alias(f"n{i}") for i in n))

    def odds(i: int):
        pos = float(totals[f"p{i}"] or 0)
        neg = float(totals[f"n{i}"] or 0) - pos
        p, every = F.col(f"p{i}"), F.col(f"n{i}")
        return F.when(every >= 3, F.abs(F.ln((p + 0.5) / (pos + 1.0)) - F.ln((every - p + 0.5) / (neg + 1.0))))

    weights = counts.filter(" OR ".join(f"n{i} >= 3" for i in n)).select("w", F.array(*map(odds, n)).alias("o"))
    # An encoder that has no weight for any word takes all words as equal.
    weights = written(weights)
    some = weights.agg(*(F.count(F.col("o")[i]).alias(f"s{i}") for i in n)).first()
    weights = weights.select("w", F.array(*(F.coalesce(F.col("o")[i], F.lit(UNSEEN if some[i] else 1.0)) for i in n)).alias("o"))
    blank = tuple(UNSEEN if some[i] else 1.0 for i in n)
    most = TUNED_BYTES // (8 * (len(fit_on) + 1))
    few = weights.limit(most + 1).toArrow()
    hashes = np.array([_hash(w, seed) for w in few.column("w").to_pylist()] if len(few) <= most else [], np.uint64)
    order = np.argsort(hashes)
    if len(few) > most or (np.diff(hashes[order]) == 0).any():
        return Tuned(d, seed, len(fit_on), blank, table=weights)
    return Tuned(d, seed, len(fit_on), blank, hashes[order], few.column("o").combine_chunks().flatten().to_numpy().reshape(len(few), -1)[order])


def encode_each(chunks: DataFrame, tuned: Tuned, keep: tuple[str, ...]) -> DataFrame:
    """``keep`` and ``vec``: the vectors of all rotations side by side."""
    d, turns = tuned.d, tuned.turns
    if tuned.table is not None:
        return _encode_each_joined(chunks, tuned, keep)
    shared = chunks.sparkSession.sparkContext.broadcast(tuned)
    names = [*keep, "vec"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Words by number in the order met, with place and weights in arrays: a text is a sum over its words' numbers.
        known: dict[str, int] = {}
        place, weight = np.zeros(1 << 10, np.int64), np.zeros((1 << 10, turns))
        for batch in batches:
            out = np.zeros((batch.num_rows, d, turns))
            for row, text in zip(out, batch.column(len(keep)).to_pylist(), strict=True):
                listed = (text or "").split()
                if len(known) > 200_000:
                    known.clear()
                for w in listed:
                    if w not in known:
                        n = known[w] = len(known)
                        if n >= len(place):
                            place, weight = np.concatenate([place, place]), np.concatenate([weight, weight])
                        place[n], weight[n] = shared.value.of(w)
                at = np.fromiter(map(known.__getitem__, listed), np.int64, len(listed))
                for i in range(turns):
                    row[:, i] = np.bincount(place[at], weights=weight[at, i], minlength=d)
            out = out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)
            flat = np.ascontiguousarray(out.transpose(0, 2, 1)).reshape(len(out), -1).astype(np.float32)
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(keep))), pa.FixedSizeListArray.from_arrays(pa.array(flat.ravel()), d * turns).cast(pa.list_(pa.float32()))], names=names)

    rows = chunks.select(*keep, "text")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.drop("text").schema) + ", vec array<float>"
    return rows.mapInArrow(run, schema)


def _encode_each_joined(chunks: DataFrame, tuned: Tuned, keep: tuple[str, ...]) -> DataFrame:
    """``encode_each`` with weights joined: the place of each distinct word, and sums per text, place by place, of all rotations at once."""
    d, seed, n = tuned.d, tuned.seed, range(tuned.turns)
    words = chunks.select(*keep, F.explode(F.split("text", r"\s+")).alias("w")).filter("w <> ''").groupBy(*keep, "w").agg(F.count("*").alias("n"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = [_place(w, d, seed) for w in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([a for a, _ in at], pa.int32()), pa.array([s for _, s in at], pa.float64()), batch.column(1)], names=["w", "at", "s", "o"])

    blank = F.array(*map(F.lit, tuned.blank))
    weights = words.select("w").distinct().join(tuned.table, "w", "left").select("w", F.coalesce("o", blank).alias("o")).mapInArrow(place, "w string, at int, s double, o array<double>")
    sums = words.join(weights, "w").groupBy(*keep, "at").agg(*(F.sum(F.col("n") * F.col("s") * F.col("o")[i]).alias(f"v{i}") for i in n))
    sums = sums.groupBy(*keep).agg(*(F.map_from_entries(F.collect_list(F.struct("at", f"v{i}"))).alias(f"m{i}") for i in n), *(F.sqrt(F.sum(F.col(f"v{i}") * F.col(f"v{i}"))).alias(f"norm{i}") for i in n))
    of = lambda i: F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.coalesce(F.element_at(f"m{i}", j) / F.greatest(f"norm{i}", F.lit(1e-9)), F.lit(0.0)).cast("float"))
    zero = F.array_repeat(F.lit(0.0).cast("float"), d * tuned.turns)
    return chunks.select(*keep).join(sums.select(*keep, F.concat(*map(of, n)).alias("vec")), list(keep), "left").withColumn("vec", F.coalesce("vec", zero))


def _encode_joined(rows: DataFrame, encoder: HashedProjection) -> DataFrame:
    """``encode`` with weights joined: the place of each distinct word, and sums per text, place by place."""
    texts = rows.select("content", "text").dropDuplicates(["content"])
    words = texts.select("content", F.explode(F.split("text", r"\s+")).alias("w")).filter("w <> ''").groupBy("content", "w").agg(F.count("*").alias("n"))
    d, seed = encoder.d, encoder.seed

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = [_place(w, d, seed) for w in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([a for a, _ in at], pa.int32()), pa.array([s * o for (_, s), o in zip(at, batch.column(1).to_pylist(), strict=True)], pa.float64())], names=["w", "at", "v"])

    weights = words.select("w").distinct().join(encoder.table, "w", "left").select("w", F.coalesce("o", F.lit(0.05)).alias("o")).mapInArrow(place, "w string, at int, v double")
    sums = words.join(weights, "w").groupBy("content", "at").agg(F.sum(F.col("n") * F.col("v")).alias("v")).groupBy("content").agg(F.map_from_entries(F.collect_list(F.struct("at", "v"))).alias("m"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    vec = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.element_at("m", i) / F.greatest("norm", F.lit(1e-9)), F.lit(0.0)).cast("float"))
    zero = F.array_repeat(F.lit(0.0).cast("float"), d)
    return rows.join(sums.select("content", vec.alias("vec")), "content", "left").select(*rows.drop("text").columns, F.coalesce("vec", zero).alias("vec"))


def encode_text(chunks: DataFrame, encoder: HashedProjection, keep: tuple[str, ...] = ("visit_id", "chunk_no", "n_chunks")) -> DataFrame:
    """``keep``, the chunk's content key, and ``vec``. Equal texts have equal keys, so a store need only take in what is new."""
    rows = chunks.select(*keep, F.sha2("text", 256).alias("content"), "text")
    if encoder.table is not None:
        return _encode_joined(rows, encoder)
    shared = chunks.sparkSession.sparkContext.broadcast(encoder)
    names = [*rows.columns[:-1], "vec"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vectors = shared.value.encode(batch.column(len(names) - 1).to_pylist())
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(names) - 1)), pa.array(list(vectors), pa.list_(pa.float32()))], names=names)

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.drop("text").schema) + ", vec array<float>"
    return rows.mapInArrow(run, schema)


def word2vec(chunks: DataFrame, d: int = 64, least: int = 5):
    """MLlib's word vectors, fitted on the given rows only; returns a model whose transform adds ``vec``."""
    from pyspark.ml.feature import Word2Vec

    words = chunks.withColumn("_words", F.split("text", r"\s+"))
    return Word2Vec(vectorSize=d, minCount=least, seed=3, maxIter=1, inputCol="_words", outputCol="vec").fit(words)


def concept_table(dictionary: DataFrame, encoder: HashedProjection) -> DataFrame:
    """(code, vec): each code's description encoded once."""
    return encode_text(C.describe(dictionary), encoder, ("code",)).select("code", "vec")


#: Bytes of a matrix that is brought to tasks; a code standard of 20,000 concepts at width 768 takes 123 MB.
MOST_BYTES = 512 << 20


def matrix(table: DataFrame, vocab: DataFrame, d: int) -> np.ndarray:
    """Vectors by vocabulary id, zeros for padding and unknown codes; refuses what is beyond ``MOST_BYTES``. Rows come as Arrow."""
    most = MOST_BYTES // (8 * d)
    rows = vocab.select("code", "id").join(table, "code").select("id", F.col("vec").cast("array<double>").alias("vec")).limit(most + 1).toArrow()
    if len(rows) > most:
        raise ValueError("too many codes for one matrix")
    ids = rows.column("id").to_numpy()
    out = np.zeros((int(ids.max(initial=C.UNKNOWN)) + 1, d))
    if len(rows):
        out[ids] = rows.column("vec").combine_chunks().flatten().to_numpy().reshape(-1, d)
    return out


def multi_hot_concept(sparse: DataFrame, vocab: DataFrame, table: DataFrame, key: str = "visit_id") -> DataFrame:
    """(key, vec): the sum of the vectors of a visit's codes, the product of its multi-hot row with the concept table."""
    from carepath.functions.vectors import pool

    long = sparse.select(key, F.explode("ids").alias("id")).join(vocab.select("id", "code"), "id").join(table, "code")
    return pool(long, key, "vec", "sum")


def leaks(fit_keys: DataFrame, test_keys: DataFrame, key: str = "visit_id") -> int:
    """Rows that an encoder was tuned on and is tested on."""
    return fit_keys.select(key).distinct().join(test_keys.select(key), key, "left_semi").count()
