"""N-gram Jaccard join over size-banded tiles with hashed bitmap signatures.

Rows with the same set of word shingles are one class, and only classes go on. Links are found in two passes.

1. One tile per set and round: the classes that share their least shingle, under one order of hashes and then under another. Each set
   meets the leaders of its tile, those that passed no bound with an earlier leader, and asks for one exact check, of the
   likeliest. Groups of near copies, however large, become components here, at a check for each set; after a
   round only one set of a component goes on.
2. Tiles of prefixes: sets above the threshold share one of their first shingles in any order common to all, as many as two such sets
   can't all miss. The order is by hash, but shingles that many texts have there come last, which keeps tiles small. A tile is in order of set size, so that only a band of sizes can meet, and only sets of two components do: tiles that lie in one component, and
   rows without another component in their band, are dropped before any signature is attached. The many tiles of a few sets
   are taken as distinct pairs.

Within a band, bit counts of hashed bitmaps bound the overlap from above; pairs that pass the bound are decided by
intersecting the exact sorted arrays. What the bound rules out is final and every pair of two components that passes it is looked at
until they are one, so no link between components is lost. A set asks for a few checks in a tile; a tile that has more to ask is decided
as a whole, on the exact arrays of its sets, and gives only the links that join its components. Tiles with more than ``CROWDED`` sets are parted by a second
shared shingle of prefixes one longer, which all pairs above the threshold have; what is still crowded then is cut into fragments
that meet two by two.

Defined cases: a null or empty text, or one without words, has the empty set and is linked with nothing; texts of fewer
words than a shingle have their whole sequence as one; repeated rows are one class; rows with an equal id and different texts
are apart, each linked by its own text; rows without an id join the component of the rows with their set, if one of these has an
id, and else are alone; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from carepath.llm import _graph
from carepath.llm._blocks import _ODD, Block, _spread, blocks, grams, words
from carepath.llm._shared import if_small, written

CROWDED = 4096
#: Tiles of up to so many sets are taken as their pairs in a band of size at once, each pair once however many tiles it is in.
SMALL = 32
#: Bits of a signature at least: short sets differ in few elements, which then seldom share a bit.
LEAST_BITS = 512
#: And at most, so that a tile's memory is bounded; longer sets have a weaker bound and more exact checks.
MOST_BITS = 1 << 16
#: Shingles that more texts than this have in their prefix by hash are put last in the order of prefixes.
FREQUENT = 16
#: The most frequent ones, up to so many, which tasks hold (8 bytes each). The order of shingles bears on costs, never on results.
MOST_FREQUENT = 1_000_000
#: In the first look at a tile, a set asks for this many checks at most; tiles that have more to ask are then decided as a whole, within a task.
FIRST_CHECKS = 2
#: Shingles (8 bytes each) of the sets of a tile decided as a whole; tiles with more are cut into fragments that meet two by two.
TILE_SHINGLES = 2_000_000


@dataclass(frozen=True)
class JoinSpec:
    shingle: int = 5
    #: Sets link when 100 * intersection >= percent * union.
    percent: int = 80

    def prefix(self, n: np.ndarray) -> np.ndarray:
        return n - -(-n * self.percent // 100) + 1


def shingle_sets(block: Block, spec: JoinSpec) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text, one after the other, and n + 1 offsets."""
    w = words(block, lower=True)
    g, whole = grams(w, spec.shingle)
    counts = np.diff(w.rows)
    short = np.flatnonzero((counts > 0) & (counts < spec.shingle))
    own = np.maximum(counts - spec.shingle + 1, 0)
    own[short] = 1
    at = np.concatenate([[0], np.cumsum(own)])
    keys = np.empty(at[-1], np.uint64)
    of_words = np.ones(len(keys), bool)
    of_words[at[short]] = False
    keys[of_words] = g[whole]
    with np.errstate(over="ignore"):
        for i in short:
            keys[at[i]] = np.bitwise_xor.reduce(_spread(w.hash[w.rows[i] : w.rows[i + 1]] + np.arange(1, counts[i] + 1, dtype=np.uint64) * _ODD))
    for i, j in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        keys[i:j].sort()
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    new[at[:-1][own > 0]] = True
    return keys[new], np.concatenate([[0], np.cumsum(new)])[at]


def bits_for(n: int) -> int:
    return min(max(LEAST_BITS, 1 << (2 * int(n) - 1).bit_length()), MOST_BITS)


def signature(keys: np.ndarray) -> np.ndarray:
    """A bitmap of a power of two of bits, twice the set's size or more up to ``MOST_BITS``; halves can be folded onto each other."""
    bits = bits_for(len(keys))
    at = (keys >> np.uint64(20)) & np.uint64(bits - 1)
    out = np.zeros(bits, bool)
    out[at.astype(np.int64)] = True
    return np.packbits(out, bitorder="little").view(np.uint64)


def fold(sig: np.ndarray) -> np.ndarray:
    return sig[..., : sig.shape[-1] // 2] | sig[..., sig.shape[-1] // 2 :]


def bound(n: np.ndarray | int, sig: np.ndarray, others: np.ndarray, others_n: np.ndarray) -> np.ndarray:
    """The most elements that the sets can share. A bit that only one has is an element the other lacks."""
    mine = n - np.bitwise_count(sig & ~others).sum(axis=1, dtype=np.int64)
    theirs = others_n - np.bitwise_count(others & ~sig).sum(axis=1, dtype=np.int64)
    return np.minimum(mine, theirs)


def _level(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both signatures folded to the shorter one's length."""
    while a.shape[-1] > b.shape[-1]:
        a = fold(a)
    while b.shape[-1] > a.shape[-1]:
        b = fold(b)
    return a, b


def _matrix(sigs: pa.Array, length: int) -> np.ndarray:
    """Signatures of one length, a row each."""
    return np.frombuffer(b"".join(sigs.to_pylist()), np.uint64).reshape(-1, length)


class Tile:
    """Sets of one tile in a given order, with their signatures by length."""

    def __init__(self, n: np.ndarray, sigs: list[bytes], percent: int):
        self.n, self.percent = n, percent
        self.length = np.array([len(s) // 8 for s in sigs])
        self.matrix = {int(k): np.frombuffer(b"".join(sigs[i] for i in np.flatnonzero(self.length == k)), np.uint64).reshape(-1, int(k)) for k in np.unique(self.length)}
        self.place = np.zeros(len(n), np.int64)
        for k in self.matrix:
            own = self.length == k
            self.place[own] = np.arange(own.sum())

    def meets(self, i: int, earlier: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Those of ``earlier`` in the band of i's size that the bound lets pass with i, and the likely similarities."""
        n = self.n[i]
        other = self.n[earlier]
        earlier = earlier[(100 * other >= self.percent * n) & (100 * n >= self.percent * other)]
        if not len(earlier):
            return earlier, np.zeros(0)
        found, shares = [], []
        k = int(self.length[i])
        sig = self.matrix[k][self.place[i]]
        for length in np.unique(self.length[earlier]):
            same = earlier[self.length[earlier] == length]
            most = bound(int(n), *_level(sig, self.matrix[int(length)][self.place[same]]), self.n[same])
            union = n + self.n[same] - most
            ok = 100 * most >= self.percent * union
            found.append(same[ok])
            shares.append(most[ok] / union[ok])
        return np.concatenate(found), np.concatenate(shares)

    def stars(self) -> Iterator[tuple[int, int]]:
        """(leader, set): one check for each set that passes a bound with a leader, with the likeliest."""
        leaders = np.zeros(len(self.n), np.int64)
        many = 0
        for i in range(len(self.n)):
            met, share = self.meets(i, leaders[:many])
            if len(met):
                yield int(met[share.argmax()]), i
            else:
                leaders[many] = i
                many += 1

    def _bands(self, component: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """Each set with the earlier ones of other components that the bound lets pass, likeliest first; ``component`` may change meanwhile.

        The sets are in order of size, so that those in a set's band lie side by side.
        """
        low = np.searchsorted(self.n, -(-self.n * self.percent // 100))
        for i in range(1, len(self.n)):
            met, share = self.meets(i, low[i] + np.flatnonzero(component[low[i] : i] != component[i]))
            if len(met):
                yield i, met, np.argsort(-share, kind="stable")

    def between(self, component: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
        """Up to ``most`` pairs of a set in two components, the likeliest; (-1, i) tells that some were left out."""
        for i, met, order in self._bands(component):
            for j in met[order[:most]]:
                yield int(j), i
            if len(met) > most:
                yield -1, i

    def links(self, component: np.ndarray, keys: list[np.ndarray]) -> Iterator[tuple[int, int]]:
        """Pairs above the threshold that join all components of the tile which are linked, one less than there are of them."""
        label = np.unique(component, return_inverse=True)[1]
        at = np.concatenate([[0], np.cumsum([len(k) for k in keys])])
        ids = np.unique(np.concatenate(keys), return_inverse=True)[1]
        mine = np.zeros(len(ids), bool)
        for i, met, order in self._bands(label):
            met = met[order]
            own = ids[at[i] : at[i + 1]]
            mine[own] = True
            size = self.n[met]
            where = np.cumsum(size) - size
            common = np.add.reduceat(mine[ids[np.arange(size.sum()) + np.repeat(at[met] - where, size)]], where, dtype=np.int64)
            mine[own] = False
            for j in met[100 * common >= self.percent * (self.n[i] + size - common)]:
                if label[j] != label[i]:
                    yield int(j), i
                    label[label == label[j]] = label[i]


def _frequent(docs: DataFrame, spec: JoinSpec) -> np.ndarray:
    """Sorted hashes of the shingles that come last in the order of prefixes; counted over all texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column(0)):
                keys, at = shingle_sets(block, spec)
                n = np.diff(at)
                take = np.where(n > 0, spec.prefix(n), 0)
                pick = np.arange(take.sum()) - np.repeat(np.cumsum(take) - take - at[:-1], take)
                h, count = np.unique(keys[pick], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(count.astype(np.int32))], names=["h", "c"])

    counts = docs.select(F.col("text").alias("_text")).mapInArrow(run, "h long, c int").groupBy("h").agg(F.sum("c").alias("c"))
    found = counts.filter(F.col("c") > FREQUENT).orderBy(F.desc("c"), "h").limit(MOST_FREQUENT).select("h").toArrow()
    return np.sort(found.column("h").to_numpy().view(np.uint64))


class Order:
    """The order of shingles that prefixes follow: by hash, frequent ones last."""

    def __init__(self, frequent: np.ndarray):
        self.frequent = frequent
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[(frequent & np.uint64((1 << 20) - 1)).astype(np.int64)] = True

    def late(self, keys: np.ndarray) -> np.ndarray:
        out = np.zeros(len(keys), bool)
        some = np.flatnonzero(self.maybe[(keys & np.uint64((1 << 20) - 1)).astype(np.int64)])
        if len(some):
            at = np.minimum(np.searchsorted(self.frequent, keys[some]), len(self.frequent) - 1)
            out[some] = self.frequent[at] == keys[some]
        return out


def _sets(docs: DataFrame, spec: JoinSpec) -> DataFrame:
    """doc_id, th (hash of the text), n, k1, k2 (the set's 128-bit key), two least hashes, prefix (one longer than needed) and sig of every row."""
    names = ["doc_id", "th", "n", "k1", "k2", "m1", "m2", "prefix", "sig"]
    schema = "doc_id long, th long, n long, k1 long, k2 long, m1 long, m2 long, prefix array<long>, sig binary"
    shared = docs.sparkSession.sparkContext.broadcast(_frequent(docs, spec))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = Order(shared.value)
        for batch in batches:
            for block in blocks(batch.column(2)):
                keys, at = shingle_sets(block, spec)
                n = np.diff(at)
                full = np.flatnonzero(n > 0)
                m1, m2 = np.zeros(block.n, np.int64), np.zeros(block.n, np.int64)
                with np.errstate(over="ignore"):
                    mixed = [_spread(keys ^ np.uint64(salt)) for salt in (1, 2)]
                    sums = [np.concatenate([[np.uint64(0)], np.cumsum(x)]) for x in mixed]
                    k1, k2 = ((s[at[1:]] - s[at[:-1]]).view(np.int64) for s in sums)
                if len(full):
                    m1[full] = keys[at[:-1][full]].view(np.int64)
                    m2[full] = np.minimum.reduceat(mixed[0], at[:-1][full]).view(np.int64)
                take = np.minimum(np.where(n > 0, spec.prefix(n) + 1, 0), n)
                where = np.concatenate([[0], np.cumsum(take)])
                pick = np.arange(where[-1]) - np.repeat(where[:-1] - at[:-1], take)
                ordered = np.argsort(np.repeat(np.arange(block.n) * 2, n) + order.late(keys), kind="stable")
                prefix = pa.ListArray.from_arrays(pa.array(where, pa.int32()), pa.array(keys[ordered[pick]].view(np.int64)))
                sig = pa.array([signature(keys[a:b]).tobytes() for a, b in zip(at[:-1], at[1:], strict=True)], pa.binary())
                ids, th = (batch.column(i).slice(block.first, block.n) for i in (0, 1))
                yield pa.RecordBatch.from_arrays([ids, th, *(pa.array(x) for x in (n, k1, k2, m1, m2)), prefix, sig], names=names)

    return _own(docs).mapInArrow(run, schema)


def _own(docs: DataFrame) -> DataFrame:
    """doc_id, th and text of the rows."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("th"), text.alias("_text"))


def _runs(batches: Iterator[pa.RecordBatch], keys: tuple[int, ...] = (0,)) -> Iterator[pa.Table]:
    """The rows of each key, from batches sorted by it; a key's rows may lie in several batches."""
    held: list[pa.RecordBatch] = []
    last: tuple = ()
    for batch in batches:
        if not len(batch):
            continue
        columns = [batch.column(i).to_numpy(zero_copy_only=False) for i in keys]
        new = np.zeros(len(batch) - 1, bool)
        for k in columns:
            new |= k[1:] != k[:-1]
        cuts = [0, *(np.flatnonzero(new) + 1).tolist(), len(batch)]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            now = tuple(k[a] for k in columns)
            if held and now != last:
                yield pa.Table.from_batches(held)
                held = []
            last = now
            held.append(batch.slice(a, b - a))
    if held:
        yield pa.Table.from_batches(held)


# ---------------------------------------------------------------- first pass: a tile per set


def _stars(classes: DataFrame, least: str, spec: JoinSpec) -> DataFrame:
    """(a, b): for each class, the likeliest leader of its tile, if any. Large tiles are dealt out in parts."""
    hot = classes.groupBy(least).agg(F.count("*").alias("c")).filter(F.col("c") > CROWDED).select(F.col(least).alias("_m"), F.ceil(F.col("c") / CROWDED).alias("parts"))
    rows = classes.join(if_small(hot), F.col(least) == F.col("_m"), "left")
    part = F.coalesce(F.pmod(F.xxhash64("node"), F.col("parts")), F.lit(0)).cast("int")
    rows = rows.select(F.col(least).alias("m"), part.alias("part"), "node", "n", "sig")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for tile in _runs(batches, (0, 1)):
            if len(tile) < 2:
                continue
            node = tile.column("node").to_numpy()
            found = list(Tile(tile.column("n").to_numpy(), tile.column("sig").to_pylist(), spec.percent).stars())
            if found:
                i, j = np.array(found).T
                yield pa.RecordBatch.from_arrays([pa.array(node[i]), pa.array(node[j])], names=["a", "b"])

    return rows.repartition("m", "part").sortWithinPartitions("m", "part", "node").mapInArrow(run, "a long, b long")


# ---------------------------------------------------------------- second pass: tiles of prefixes


def _shared(tiles: DataFrame, percent: int) -> DataFrame:
    """Rows of (h, node, n, component), dealt by h, that meet another component of near size in their tile; and the tile's count of them.

    Tiles of up to ``SMALL`` rows are given as their pairs of near size and two components at once: node and other.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None  # the last tile of a batch may go on in the next
        for batch in batches:
            table = pa.Table.from_batches([batch]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([batch])])
            h = table.column(0).to_numpy()
            start = int(np.searchsorted(h, h[-1], "left")) if len(h) else 0
            yield from near(table.slice(0, start))
            rest = table.slice(start)
        if rest is not None:
            yield from near(rest)

    def near(table: pa.Table) -> Iterator[pa.RecordBatch]:
        h, node, n, component = (table.column(i).to_numpy() for i in range(4))
        if len(h) < 2:
            return
        # For each row, the nearest row before it that has another component, and the nearest behind it.
        change = np.concatenate([[True], (h[1:] != h[:-1]) | (component[1:] != component[:-1]), [True]])
        place = np.arange(len(h))
        before = np.maximum.accumulate(np.where(change[:-1], place, 0)) - 1
        behind = np.minimum.accumulate(np.where(change[1:], place, len(h))[::-1])[::-1] + 1
        keep = (before >= 0) & (h[before] == h) & (100 * n[before] >= percent * n)
        other = np.minimum(behind, len(h) - 1)
        keep |= (behind < len(h)) & (h[other] == h) & (100 * n >= percent * n[other])
        if not keep.any():
            return
        h, node, n, component = h[keep], node[keep], n[keep], component[keep]
        cuts = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1], [True]]))
        count = np.repeat(np.diff(cuts), np.diff(cuts))
        big = count > SMALL
        out = [(h[big], node[big], n[big], component[big], count[big], np.zeros(big.sum(), np.int64))]
        for d in range(1, SMALL):
            i = np.flatnonzero(~big[d:] & (h[d:] == h[:-d]) & (component[d:] != component[:-d]) & (100 * n[:-d] >= percent * n[d:]))
            a, b = np.minimum(node[i], node[i + d]), np.maximum(node[i], node[i + d])
            out.append((h[i], a, n[i], component[i], count[i], b))
        columns = [np.concatenate(c) for c in zip(*out, strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["h", "node", "n", "component", "count", "other"])

    return tiles.select("h", "node", "n", "component").repartition("h").sortWithinPartitions("h", "n", "node").mapInArrow(run, "h long, node long, n long, component long, count long, other long")


def _bounded(pairs: DataFrame, sigs: DataFrame, percent: int) -> DataFrame:
    """The distinct pairs (a, b) that the bound lets pass."""
    side = lambda x: sigs.select(F.col("node").alias(x), F.col("n").alias(f"n_{x}"), F.col("sig").alias(f"sig_{x}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [batch.column(i).to_numpy() for i in (2, 4)]
            sizes = [pc.binary_length(batch.column(i)).to_numpy() // 8 for i in (3, 5)]
            keep = np.zeros(len(batch), bool)
            for kind in np.unique(np.stack(sizes, axis=1), axis=0):
                pick = np.flatnonzero((sizes[0] == kind[0]) & (sizes[1] == kind[1]))
                mine, theirs = (_matrix(batch.column(i).take(pa.array(pick)), int(k)) for i, k in zip((3, 5), kind, strict=True))
                most = bound(n[0][pick], *_level(mine, theirs), n[1][pick])
                keep[pick] = 100 * most >= percent * (n[0][pick] + n[1][pick] - most)
            yield batch.select(["a", "b"]).filter(pa.array(keep))

    both = pairs.distinct().join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "sig_a", "n_b", "sig_b")
    return both.mapInArrow(run, "a long, b long")


def _fragments(rows: DataFrame, parts: Column) -> DataFrame:
    """Tiles as fragments, ``parts`` of each, which meet two by two in tiles of their own."""
    parts = parts.cast("int")
    rows = rows.withColumn("g", F.pmod(F.xxhash64("node"), parts).cast("int")).select("*", F.explode(F.sequence(F.lit(0), parts - 1)).alias("o"))
    return rows.select(F.xxhash64("h", F.least("g", "o"), F.greatest("g", "o")).alias("h"), "node", "n", "component")


def _tiles(classes: DataFrame, groups: DataFrame, spec: JoinSpec) -> tuple[DataFrame, DataFrame]:
    """(h, node, n) of tiles of several sets, none crowded; and the distinct pairs (a, b) of small ones. Both only of two components."""
    needed = (F.col("n") - F.ceil(F.col("n") * spec.percent / 100) + 1).cast("int")
    own = classes.select("node", "n", "prefix").join(if_small(groups), "node", "left").withColumn("component", F.coalesce("component", "node"))
    shared = written(_shared(own.select(F.explode(F.slice("prefix", F.lit(1), needed)).alias("h"), "node", "n", "component"), spec.percent), "join-tiles")
    small = lambda df: df.filter(F.col("count") <= SMALL).select(F.col("node").alias("a"), F.col("other").alias("b"))
    large = lambda df: df.filter((F.col("count") > SMALL) & (F.col("count") <= CROWDED)).select("h", "node", "n")
    tiles, pairs = large(shared), small(shared)
    crowded = shared.filter(F.col("count") > CROWDED)
    if not crowded.isEmpty():
        second = crowded.select("h", "node", "n", "component").join(classes.select("node", "prefix"), "node").select(F.explode("prefix").alias("h2"), "h", "node", "n", "component").filter("h <> h2")
        parted = written(_shared(second.select(F.xxhash64(F.least("h", "h2"), F.greatest("h", "h2")).alias("h"), "node", "n", "component").distinct(), spec.percent), "join-parted")
        tiles, pairs = tiles.unionByName(large(parted)), pairs.unionByName(small(parted))
        still = parted.filter(F.col("count") > CROWDED)
        if not still.isEmpty():
            tiles = tiles.unionByName(_fragments(still, F.ceil(F.col("count") * 2 / CROWDED)).select("h", "node", "n"))
    return tiles, pairs


def _open(tiles: DataFrame, groups: DataFrame) -> DataFrame:
    """The rows (h, node, n, component) of tiles that still lie in two components."""
    light = tiles.join(if_small(groups), "node", "left").withColumn("component", F.coalesce("component", "node"))
    mixed = light.groupBy("h").agg(F.min("component").alias("x"), F.max("component").alias("y")).filter("x < y").select("h")
    return light.join(if_small(mixed), "h", "left_semi").select("h", "node", "n", "component")


def _pairs(tiles: DataFrame, sigs: DataFrame, percent: int, most: int) -> DataFrame:
    """(h, a, b), up to ``most`` of a set and tile, to be checked exactly, from rows (h, node, n, component); a row with h alone for each tile of which pairs were left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: set[tuple[int | None, int | None, int | None]] = set()  # the same pair may come from several tiles of a task
        out = lambda: pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (zip(*found, strict=True) if found else ((), (), ()))], names=["h", "a", "b"])
        for tile in _runs(batches):
            node, component = tile.column("node").to_numpy(), tile.column("component").to_numpy()
            t = Tile(tile.column("n").to_numpy(), tile.column("sig").to_pylist(), percent)
            for i, j in t.between(component, most):
                found.add((None, int(node[i]), int(node[j])) if i >= 0 else (int(tile.column("h")[0].as_py()), None, None))
                if len(found) > 50_000:
                    yield out()
                    found.clear()
        yield out()

    rows = tiles.join(sigs.select("node", "sig"), "node").select("h", "node", "n", "sig", "component")
    return rows.repartition("h").sortWithinPartitions("h", "n", "node").mapInArrow(run, "h long, a long, b long").distinct()


# ---------------------------------------------------------------- exact checks


def _wanted(nodes: DataFrame, classes: DataFrame) -> DataFrame:
    """``nodes`` with the id and text hash of a row that has the set."""
    return nodes.join(classes.select("node", "rid", F.col("th").alias("_th")), "node")


def _texts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    return _own(docs).join(wanted, (F.col("doc_id") == F.col("rid")) & (F.col("th") == F.col("_th")))


def _decided(tiles: DataFrame, docs: DataFrame, classes: DataFrame, spec: JoinSpec) -> DataFrame:
    """The links (a, b) that join what is linked in each tile (h, node, n, component), decided on the exact arrays within a task.

    Rows made are fewer than rows read, however many pairs a tile has.
    """
    heavy = tiles.groupBy("h").agg(F.sum("n").alias("w")).filter(F.col("w") > TILE_SHINGLES).select("h", F.ceil(F.col("w") * 2 / TILE_SHINGLES).alias("parts"))
    rows = tiles.join(if_small(heavy), "h", "left")
    rows = _fragments(rows.drop("parts"), F.lit(1)) if heavy.isEmpty() else _fragments(rows, F.coalesce("parts", F.lit(1)))
    wanted = written(_wanted(tiles.select("node").distinct(), classes), "join-decided")

    def arrays(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column(1)):
                keys, at = shingle_sets(block, spec)
                sets = pa.array([keys[a:b].tobytes() for a, b in zip(at[:-1], at[1:], strict=True)], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(block.first, block.n), sets], names=["node", "keys"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for tile in _runs(batches):
            node, component = tile.column("node").to_numpy(), tile.column("component").to_numpy()
            keys = [np.frombuffer(k.as_buffer(), np.uint64) for k in tile.column("keys").combine_chunks()]
            t = Tile(tile.column("n").to_numpy(), [signature(k).tobytes() for k in keys], spec.percent)
            found = list(t.links(component, keys))
            if found:
                i, j = np.array(found).T
                yield pa.RecordBatch.from_arrays([pa.array(node[i]), pa.array(node[j])], names=["a", "b"])

    sets = _texts(docs, if_small(wanted)).select("node", F.col("_text")).mapInArrow(arrays, "node long, keys binary").dropDuplicates(["node"])
    dealt = rows.join(sets, "node").select("h", "node", "n", "keys", "component").repartition("h").sortWithinPartitions("h", "n", "node")
    return dealt.mapInArrow(run, "a long, b long").distinct()


def _verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame, spec: JoinSpec) -> DataFrame:
    """The pairs (a, b) whose exact sets are above the threshold. Arrays are sent once for each pair, to the task of its a."""
    to = pairs.unionByName(pairs.select("a", F.col("a").alias("b"))).distinct().groupBy(F.col("b").alias("node")).agg(F.collect_list("a").alias("to"))
    wanted = written(_wanted(to, classes), "join-wanted")
    rows = _texts(docs, if_small(wanted, weight=F.size("to") + 1)).select("node", "to", "_text")

    def arrays(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column(2)):
                keys, at = shingle_sets(block, spec)
                to = batch.column(1).slice(block.first, block.n)
                counts = np.diff(to.offsets.to_numpy())
                row = np.repeat(np.arange(block.n), counts)
                sets = [keys[a:b].tobytes() for a, b in zip(at[:-1], at[1:], strict=True)]
                b = batch.column(0).slice(block.first, block.n).to_numpy()[row]
                for i in range(0, len(row), 4096):
                    yield pa.RecordBatch.from_arrays([to.flatten().slice(i, 4096), pa.array(b[i : i + 4096]), pa.array([sets[r] for r in row[i : i + 4096]], pa.binary())], names=["a", "b", "keys"])

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, own = None, np.zeros(0, np.uint64)
        for batch in batches:
            keep = []
            for a, b, keys in zip(*(batch.column(i) for i in (1, 2, 3)), strict=True):
                a, b, x = a.as_py(), b.as_py(), np.frombuffer(keys.as_buffer(), np.uint64)
                if a == b:
                    now, own = a, x.copy()
                common = len(np.intersect1d(own, x, assume_unique=True)) if a != b and a == now else 0
                keep.append(a != b and a == now and 100 * common >= spec.percent * (len(own) + len(x) - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    sent = rows.mapInArrow(arrays, "a long, b long, keys binary").withColumn("first", F.col("a") != F.col("b"))
    return sent.select("first", "a", "b", "keys").repartition("a").sortWithinPartitions("a", "first", "b").mapInArrow(check, "a long, b long").distinct()


# ---------------------------------------------------------------- the join


def _classes(sets: DataFrame) -> DataFrame:
    """One row per set: its key, rid (smallest id), th, node (rid, or a hash where two sets have the same rid), and what the passes need."""
    key = ["k1", "k2", "n"]
    first = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "th", "m1", "m2", "prefix", "sig")))
    found = written(sets.filter("n > 0").groupBy(*key).agg(first.alias("f")).filter("f IS NOT NULL").select(*key, F.col("f.doc_id").alias("rid"), *(F.col(f"f.{c}") for c in ("th", "m1", "m2", "prefix", "sig"))), "join-classes")
    twice = written(found.groupBy("rid").agg(F.count("*").alias("c")).filter("c > 1").select("rid", F.lit(True).alias("twice")), "join-twice")
    node = F.when(F.col("twice"), F.xxhash64("rid", *key)).otherwise(F.col("rid"))
    return found.join(if_small(twice), "rid", "left").withColumn("node", node).drop("twice")


def _components(classes: DataFrame, docs: DataFrame, spec: JoinSpec) -> DataFrame:
    """(node, component) of all classes that are linked with another."""
    groups = docs.sparkSession.createDataFrame([], "node long, component long")

    def with_links(found: DataFrame | None) -> DataFrame:
        links = None if found is None else written(found, "join-links")
        return groups if links is None or links.isEmpty() else _graph.components(links, groups)

    def checked(pairs: DataFrame) -> DataFrame | None:
        return None if pairs.isEmpty() else _verified(pairs, docs, classes, spec)

    for least in ("m1", "m2"):
        one = classes.select("node", "n", least, "sig").join(if_small(groups.filter("node <> component")), "node", "left_anti")
        groups = with_links(checked(written(_stars(one, least, spec), "join-stars")))
    tiles, few = _tiles(classes, groups, spec)
    sigs = classes.select("node", "n", "sig")
    tried = written(_bounded(few, sigs, spec.percent), "join-pairs")
    groups = with_links(checked(tried))
    found = written(_pairs(_open(tiles, groups), sigs, spec.percent, FIRST_CHECKS), "join-found")
    groups = with_links(checked(written(found.filter("a IS NOT NULL").select("a", "b").join(tried, ["a", "b"], "left_anti"), "join-rest")))
    left_out = found.filter("a IS NULL").select("h")
    if left_out.isEmpty():
        return groups
    rest = written(_open(tiles.join(if_small(left_out), "h", "left_semi"), groups), "join-rest-tiles")
    return with_links(None if rest.isEmpty() else _decided(rest, docs, classes, spec))


def _linked(docs: DataFrame, spec: JoinSpec) -> DataFrame:
    """Every row's doc_id, th and n with class_id (smallest id of its set) and component_id; null where the set is empty or has no id."""
    sets = written(_sets(docs, spec), "join-rows")
    classes = written(_classes(sets), "join-nodes")
    groups = _components(classes, docs, spec)
    named = groups.join(classes.select("node", "rid"), "node").groupBy("component").agg(F.min("rid").alias("component_id"))
    own = classes.select("k1", "k2", "n", "rid", "node").join(if_small(groups), "node", "left").join(if_small(written(named, "join-names")), "component", "left")
    names = own.select("k1", "k2", "n", F.col("rid").alias("class_id"), F.coalesce("component_id", "rid").alias("component_id"))
    return sets.select("doc_id", "th", "n", "k1", "k2").join(names, ["k1", "k2", "n"], "left").drop("k1", "k2")


def joined(docs: DataFrame, spec: JoinSpec = JoinSpec()) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_shingles, class_id (smallest id with the same set), component_id."""
    return _linked(docs, spec).select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("component_id", "doc_id").alias("component_id"))


def one_of_each(docs: DataFrame, spec: JoinSpec = JoinSpec()) -> DataFrame:
    """One row of each component: that of the smallest id, then of the least hash of the text, then the least row; columns unchanged.

    Rows without words stay, and so do rows without an id whose set no row with an id has.
    """
    rows = written(_linked(docs, spec).filter("component_id IS NOT NULL").select("doc_id", "th", "component_id"), "join-linked")
    least = rows.filter("doc_id = component_id").groupBy("component_id").agg(F.min("th").alias("least"), F.max("th").alias("most"), F.count("*").alias("c")).filter("c > 1")
    several = written(least.select("component_id", "least"), "join-several")
    later = rows.filter("doc_id = component_id").join(if_small(several), "component_id").filter("th > least").select("doc_id", "th")
    gone = written(rows.filter("doc_id IS NULL OR doc_id <> component_id").select("doc_id", "th").unionByName(later).distinct(), "join-gone")
    columns, text_hash = docs.columns, F.xxhash64(F.coalesce("text", F.lit("")))
    found = docs.select(F.struct(*(F.col(f"`{c}`") for c in columns)).alias("_k"), F.col("doc_id").cast("long").alias("_id"), text_hash.alias("_th"))
    kept = found.join(if_small(gone.select(F.col("doc_id").alias("_gone"), F.col("th").alias("_gone_th"))), F.col("_id").eqNullSafe(F.col("_gone")) & (F.col("_th") == F.col("_gone_th")), "left_anti")
    if not several.isEmpty():
        repeated = if_small(several.select(F.col("component_id").alias("_id"), F.col("least").alias("_th")))
        once = kept.join(repeated, ["_id", "_th"], "left_semi").groupBy("_id", "_th").agg(F.min_by("_k", F.to_json("_k")).alias("_k"))
        kept = kept.join(repeated, ["_id", "_th"], "left_anti").select("_k").unionByName(once.select("_k"))
    return kept.select(*(F.col(f"_k.`{c}`").alias(c) for c in columns))
