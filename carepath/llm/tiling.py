"""Benchmark decontamination by greedy string tiling.

Benchmark items are a query set that is asked against every document. Seeds (hashes of ``least`` words in a row) of the
items are joined with those of each document; an item is looked at further only if the words its seeds cover could reach
the threshold. Then the longest common run of words not yet marked is marked again and again, found by running
Karp-Rabin: rolling hashes over the unmarked words at a search length that falls from long to ``least``. As tiles
may lie anywhere in the document, passages whose parts were put in another order are still covered.

Items go to the executors in blocks of at most ``BLOCK_WORDS`` words, one pass over the documents for each block, so that
what is broadcast has a fixed bound whatever the benchmark's size.

Defined cases: null and empty texts share nothing; items of fewer words than ``least`` are never reported, as they can't be
told from ordinary phrases; repeated rows are reported alike, repeated items with equal id once by their longest text
in code point order; empty tables give an empty result; other columns are ignored. Words are runs of letters and digits,
A-Z as a-z.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from carepath.llm._blocks import Block, blocks, grams, row_of_word, words
from carepath.llm._shared import if_small, written
from carepath.llm.toxicity import _APART

BLOCK_WORDS = 2_000_000
_BASE, _PRIME = 1_000_003, (1 << 61) - 1


@dataclass(frozen=True)
class TileSpec:
    #: Shortest tile, in words.
    least: int = 5
    #: Share of an item's words in tiles from which a document holds the item.
    coverage: float = 0.8
    #: First search length of the tiling.
    search: int = 20


def _runs(free: np.ndarray, length: int) -> list[tuple[int, int]]:
    """Starts and ends of unmarked runs of at least ``length``."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], free.astype(np.int8), [0]])))
    return [(int(a), int(b)) for a, b in zip(edge[::2], edge[1::2], strict=True) if b - a >= length]


def _rolling(tokens: list[int], free: np.ndarray, length: int) -> Iterator[tuple[int, int]]:
    """(hash, start) of every window of ``length`` unmarked words, by a rolling hash."""
    drop = pow(_BASE, length - 1, _PRIME)
    for a, b in _runs(free, length):
        h = 0
        for x in tokens[a : a + length]:
            h = (h * _BASE + x) % _PRIME
        yield h, a
        for i in range(a + 1, b - length + 1):
            h = ((h - tokens[i - 1] * drop) * _BASE + tokens[i + length - 1]) % _PRIME
            yield h, i


def greedy_tiles(item: list[int], text: list[int], spec: TileSpec = TileSpec(), allowed: np.ndarray | None = None) -> list[tuple[int, int, int]]:
    """Tiles (start in item, start in text, length), longest first; no word of either side lies in two tiles.

    ``allowed`` leaves out words of the text that lie in no shared run of ``least`` words.
    """
    free_item, free_text = np.ones(len(item), bool), np.ones(len(text), bool) if allowed is None else allowed.copy()
    tiles: list[tuple[int, int, int]] = []
    search = max(spec.least, min(spec.search, len(item)))
    while True:
        at = defaultdict(list)
        for h, i in _rolling(item, free_item, search):
            at[h].append(i)
        found, longest = [], 0
        for h, j in _rolling(text, free_text, search):
            for i in at.get(h, ()):
                k = 0
                while i + k < len(item) and j + k < len(text) and free_item[i + k] and free_text[j + k] and item[i + k] == text[j + k]:
                    k += 1
                if k >= search:
                    found.append((k, i, j))
                    longest = max(longest, k)
        if longest > 2 * search:
            search = longest
            continue
        found.sort(key=lambda m: (-m[0], m[1], m[2]))
        late = []
        for k, i, j in found:
            if free_item[i : i + k].all() and free_text[j : j + k].all():
                free_item[i : i + k] = free_text[j : j + k] = False
                tiles.append((i, j, k))
            else:
                late.append((i, j))
        if any(free_item[i : i + search].all() and free_text[j : j + search].all() for i, j in late):
            continue  # what is left of a longer match may still be as long as the search
        if search == spec.least:
            return sorted(tiles, key=lambda t: (-t[2], t[0], t[1]))
        search = max(spec.least, search // 2)


class Items:
    """A block of benchmark items: word hashes, and their seeds sorted for the join."""

    def __init__(self, ids: list, texts: list[str], spec: TileSpec):
        data = [t.encode() for t in texts]
        block = Block(0, np.frombuffer(b"".join(data), np.uint8), np.cumsum([0, *map(len, data)]))
        w = words(block, lower=True, apart=_APART)
        g, whole = grams(w, spec.least)
        at = np.flatnonzero(whole)
        order = np.argsort(g[at], kind="stable")
        self.spec, self.ids, self.w = spec, ids, w
        self.seeds, self.seed_at = g[at][order], at[order]
        self.item_of = row_of_word(w)
        self.maybe = np.zeros(1 << 22, bool)
        self.maybe[(self.seeds & np.uint64((1 << 22) - 1)).astype(np.int64)] = True

    def hits(self, g: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(position in the block, position in the items) of every shared seed."""
        at = at[self.maybe[(g[at] & np.uint64((1 << 22) - 1)).astype(np.int64)]]
        low, high = (np.searchsorted(self.seeds, g[at], side) for side in ("left", "right"))
        n = high - low
        flat = np.repeat(low - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum()) if len(n) else np.zeros(0, np.int64)
        return np.repeat(at, n), self.seed_at[flat]

    def search(self, block: Block) -> Iterator[tuple[int, int, list[tuple[int, int, int]], int]]:
        """(row, item number, tiles, words of the item) for each pair at or above the threshold."""
        w = words(block, lower=True, apart=_APART)
        g, whole = grams(w, self.spec.least)
        at, q = self.hits(g, np.flatnonzero(whole))
        if not len(at):
            return
        row, item = row_of_word(w)[at], self.item_of[q]
        order = np.lexsort((at, item, row))
        at, q, row, item = at[order], q[order], row[order], item[order]
        cuts = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (item[1:] != item[:-1])]))
        k = self.spec.least
        for a, b in zip(cuts, np.append(cuts[1:], len(row)), strict=True):
            r, i = int(row[a]), int(item[a])
            first, last = int(self.w.rows[i]), int(self.w.rows[i + 1])
            covered = np.zeros(last - first + 1, np.int64)
            np.add.at(covered, q[a:b] - first, 1)
            reach = np.convolve(covered[:-1] > 0, np.ones(k))[: last - first] > 0
            if reach.sum() < self.spec.coverage * (last - first):
                continue
            # Only words of the text that lie in a shared seed can be tiled.
            low, high = int(at[a:b].min()), int(at[a:b].max()) + k
            allowed = np.zeros(high - low + 1, np.int64)
            np.add.at(allowed, at[a:b] - low, 1)
            np.add.at(allowed, np.minimum(at[a:b] - low + k, high - low), -1)
            names: dict[int, int] = {}
            code = lambda x: [names.setdefault(int(h), len(names) + 1) for h in x]
            tiles = greedy_tiles(code(self.w.hash[first:last]), code(w.hash[low:high]), self.spec, np.cumsum(allowed)[:-1] > 0)
            if sum(t[2] for t in tiles) >= self.spec.coverage * (last - first):
                yield r, i, [(x, y + low - int(w.rows[r]), n) for x, y, n in tiles], last - first


def _blocks_of(benchmark: DataFrame, spec: TileSpec) -> Iterator[Items]:
    """The items in blocks of bounded size."""
    own = benchmark.filter(F.col("text").isNotNull() & F.col("item_id").isNotNull()).groupBy("item_id").agg(F.max(F.struct(F.length("text").alias("n"), "text")).alias("t")).select("item_id", F.col("t.text").alias("text"), (F.col("t.n") + 1).alias("n"))
    size = own.agg(F.sum("n")).first()[0] or 0
    parts = -(-size // (2 * BLOCK_WORDS))  # a word and what parts it from the next are two characters at least
    for part in range(parts):
        rows = own.filter(F.pmod(F.xxhash64("item_id"), F.lit(parts)) == part).select("item_id", "text").toArrow().sort_by("item_id").to_pydict()
        if rows["item_id"]:
            yield Items(rows["item_id"], rows["text"], spec)


def tiled(docs: DataFrame, benchmark: DataFrame, spec: TileSpec = TileSpec(), text: str = "text") -> DataFrame:
    """(doc_id, item_id, n_words, covered, n_tiles, coverage, tiles) for every document that holds an item.

    ``tiles``: start in the item, start in the document and length, in words, as a:b:n joined by commas.
    """
    source = docs.select("doc_id", F.col(text).alias("_text"))
    schema = T.StructType([source.schema[0], benchmark.schema["item_id"], *(T.StructField(n, T.LongType()) for n in ("n_words", "covered", "n_tiles")), T.StructField("coverage", T.DoubleType()), T.StructField("tiles", T.StringType())])
    item_type = _arrow(benchmark.schema["item_id"].dataType)
    out = None
    for items in _blocks_of(benchmark, spec):
        shared = docs.sparkSession.sparkContext.broadcast(items)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            asked = shared.value
            for batch in batches:
                found = [(b.first + r, i, t, n) for b in blocks(batch.column(1)) for r, i, t, n in asked.search(b)]
                covered = [sum(x[2] for x in t) for _, _, t, _ in found]
                columns = [
                    batch.column(0).take(pa.array([f[0] for f in found], pa.int64())),
                    pa.array([asked.ids[f[1]] for f in found], item_type),
                    pa.array([f[3] for f in found], pa.int64()), pa.array(covered, pa.int64()), pa.array([len(f[2]) for f in found], pa.int64()),
                    pa.array([c / f[3] for c, f in zip(covered, found, strict=True)], pa.float64()),
                    pa.array([",".join(f"{a}:{b}:{n}" for a, b, n in f[2]) for f in found], pa.string()),
                ]
                yield pa.RecordBatch.from_arrays(columns, names=schema.names)

        part = source.mapInArrow(run, schema)
        out = part if out is None else out.unionByName(part)
    return out if out is not None else docs.sparkSession.createDataFrame([], schema)


def _arrow(kind: T.DataType) -> pa.DataType:
    from pyspark.sql.pandas.types import to_arrow_type

    return to_arrow_type(kind)


def without_benchmark(docs: DataFrame, benchmark: DataFrame, spec: TileSpec = TileSpec()) -> DataFrame:
    """The rows of ``docs`` whose text holds no item; columns unchanged. A row is judged by its own text, whatever its id."""
    text_hash = F.xxhash64(F.coalesce("text", F.lit("")))
    found = written(tiled(docs.select(text_hash.alias("doc_id"), "text"), benchmark, spec).select(F.col("doc_id").alias("_bad")).distinct(), "tiles-found")
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_k"), text_hash.alias("_th"))
    kept = rows.join(if_small(found), F.col("_th") == F.col("_bad"), "left_anti")
    return kept.select(*(F.col(f"_k.`{c}`").alias(c) for c in docs.columns))
