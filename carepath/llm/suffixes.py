"""Exact removal of repeated byte strings by blockwise suffix sorting with a difference cover.

Every byte that lies in a string of ``length`` bytes which also starts in a document with a smaller id is removed. Strings
are whole in one document. The work is dealt out in suffix buckets:

1. Each string of ``length`` bytes has a minimizer, the ``seed``-byte string of least hash in it; equal strings have it at the
   same place. Minimizers that occur in two documents or more are found bucket by bucket (buckets of hashes).
2. For these, the bytes around the minimizer that a string can reach are sent to the minimizer's bucket. There the
   suffixes of the distinct surroundings are sorted one bucket at a time: by their first ``COVER`` bytes, and where these tie, by the
   ranks of the sample suffixes that a difference cover puts at a common distance behind both. Ranks are computed once
   for a block, so a long tie costs a lookup and memory stays that of the block.
3. Neighbours in suffix order that agree in ``length`` bytes form groups; a string is repeated for all documents of its group
   but the one with the smallest id. What is found goes back to the documents as start positions.

Documents with equal texts are first reduced to the one with the smallest id; the others go whole.

Defined cases: a null text is the empty one; texts shorter than ``length`` keep all bytes; rows without an id lose nothing and
take nothing from others; rows with an equal id don't take from each other; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from carepath.llm._blocks import _BYTE_CODE, Block, _inverses, _powers, _spread, blocks
from carepath.llm._shared import written

#: Period of the difference cover, in bytes; a multiple of 8.
COVER = 32
#: Suffixes sorted at once.
BLOCK_SUFFIXES = 1 << 18
#: Bytes of text for each bucket at most, which bounds what a worker unpacks at once, whatever the size of the table.
BUCKET_BYTES = 16 << 20
BROADCAST_IDS = 1_000_000
_CODEC = "zstd"


@dataclass(frozen=True)
class RepeatSpec:
    length: int = 50
    seed: int = 16

    @property
    def reach(self) -> int:
        """Bytes that a string can have on either side of its minimizer."""
        return self.length - self.seed

    @property
    def around(self) -> int:
        return 2 * self.reach + self.seed


# ---------------------------------------------------------------- difference cover and suffix order


def difference_cover(v: int) -> list[int]:
    """Residues mod v such that every distance mod v lies between two of them; grown by the residue that adds most."""
    cover, missing = [0], set(range(1, v))
    while missing:
        gain = lambda x: len({d for y in cover for d in ((x - y) % v, (y - x) % v)} & missing)
        best = max(range(v), key=gain)
        missing -= {d for y in cover for d in ((best - y) % v, (y - best) % v)}
        cover.append(best)
    return sorted(cover)


_RESIDUES = difference_cover(COVER)
_IN_COVER = np.isin(np.arange(COVER), _RESIDUES)
#: For residues a, b: the least shift that takes both into the cover.
_SHIFT = np.array([[next(s for s in range(COVER) if _IN_COVER[(a + s) % COVER] and _IN_COVER[(b + s) % COVER]) for b in range(COVER)] for a in range(COVER)])


def _columns(text: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    """The COVER bytes from each position on, as numbers of 8 bytes, the first one weighing most. ``text`` must go on that far."""
    wide = np.lib.stride_tricks.sliding_window_view(text, 8)
    return [np.ascontiguousarray(wide[at + i]).view(">u8").ravel().astype(np.uint64) for i in range(0, COVER, 8)]


def _names(keys: list[np.ndarray]) -> np.ndarray:
    """Dense ranks of rows of keys, the first key weighing most."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    rank = np.empty(len(order), np.int64)
    rank[order] = np.cumsum(new)
    return rank


def cover_ranks(text: np.ndarray, size: int, depth: int) -> np.ndarray:
    """Ranks, by their first ``depth`` bytes at least, of the suffixes at positions in the cover; -1 elsewhere.

    Names of COVER bytes are doubled along each residue: a position COVER further is in the cover too.
    """
    at = np.flatnonzero(_IN_COVER[np.arange(size) % COVER])
    rank = np.full(size + 1, -1, np.int64)
    rank[at] = _names(_columns(text, at))
    reach = COVER
    while reach < depth and len(at) and rank[at].max() + 1 < len(at):
        beyond = rank[np.minimum(at + reach, size)]
        rank[at] = _names([rank[at], np.where(at + reach < size, beyond, -1)])
        reach *= 2
    return rank


def suffix_order(text: np.ndarray, at: np.ndarray, depth: int) -> np.ndarray:
    """``at`` in the order of its suffixes, as far as ``depth`` bytes; the text is taken to go on with zeros.

    Suffixes are sorted by COVER bytes; runs of ties are resolved by cover ranks at a shift common to them, or, where their
    residues have none, by the bytes that follow.
    """
    size = len(text)
    padded = np.concatenate([text, np.zeros(COVER + 8, np.uint8)])
    name = _names(_columns(padded, at))
    order = np.argsort(name, kind="stable")
    if depth <= COVER:
        return at[order]
    rank = cover_ranks(padded, size, depth)
    at, name = at[order], name[order]
    cuts = np.flatnonzero(np.concatenate([[True], name[1:] != name[:-1], [True]]))
    second = np.zeros(len(at), np.int64)
    residue = at % COVER
    own = _SHIFT[residue, residue]
    second[:] = rank[np.minimum(at + own, size)]
    # A run whose members all have one residue is compared at that residue's shift.
    first_residue = residue[cuts[:-1]][np.cumsum(np.concatenate([[0], name[1:] != name[:-1]]))] if len(at) else residue
    odd = np.zeros(len(cuts), bool)
    np.logical_or.at(odd, np.searchsorted(cuts, np.flatnonzero(residue != first_residue), "right") - 1, True)
    out = at[np.lexsort((second, name))]
    # Members of several residues share no shift: their following bytes are sorted as well.
    mixed = np.flatnonzero(np.repeat(odd[:-1], np.diff(cuts)))
    if len(mixed):
        start = at[mixed]
        further = [k for step in range(COVER, depth, COVER) for k in _columns(padded, np.minimum(start + step, size))]
        out[mixed] = start[np.lexsort((*further[::-1], name[mixed]))]
    return out


def agree(text: np.ndarray, a: np.ndarray, b: np.ndarray, length: int) -> np.ndarray:
    """Whether the ``length`` bytes at a and b are equal."""
    wide = np.lib.stride_tricks.sliding_window_view(text, length)
    return (wide[a] == wide[b]).all(axis=1)


# ---------------------------------------------------------------- minimizers


def _least_over(x: np.ndarray, w: int) -> np.ndarray:
    span = 1
    while span * 2 <= w:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    return np.minimum(x[: len(x) - (w - span)], x[w - span :]) if w > span else x


def seed_hashes(data: np.ndarray, k: int) -> np.ndarray:
    n = len(data)
    with np.errstate(over="ignore"):
        run = np.zeros(n + 1, np.uint64)
        np.cumsum(_BYTE_CODE[data] * _powers(n), out=run[1:])
        return _spread((run[k:] - run[:-k]) * _inverses(n + 1)[: n - k + 1])


def minimizers(block: Block, spec: RepeatSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, row and byte position in the row of each string's minimizers (all of those that tie)."""
    none = np.zeros(0, np.int64)
    if len(block.data) < spec.length:
        return none.astype(np.uint64), none, none
    h = seed_hashes(block.data, spec.seed)
    w = spec.reach + 1
    least = _least_over(h, w)
    end = np.repeat(block.offsets[1:], np.diff(block.offsets))[: len(least)]
    least = np.where(np.arange(len(least)) + spec.length <= end, least, np.uint64(0))
    # A seed is picked if some whole string around it has it as its least; zeros never win, as hashes of 0 don't matter.
    padded = np.concatenate([np.zeros(w - 1, np.uint64), least, np.zeros(w - 1, np.uint64)])
    most = ~_least_over(~padded, w)
    at = np.flatnonzero((most[: len(h)] == h) & (h > 0))
    row = np.searchsorted(block.offsets, at, "right") - 1
    return h[at], row, at - block.offsets[row]


# ---------------------------------------------------------------- packed rows


def _packed(bucket: np.ndarray, columns: list[np.ndarray]) -> Iterator[tuple]:
    """(bucket, compressed bytes of each column's rows in it)."""
    order = np.argsort(bucket, kind="stable")
    b = bucket[order]
    cuts = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1], [True]])) if len(b) else np.zeros(1, np.int64)
    columns = [c[order] for c in columns]
    for i, j in zip(cuts[:-1], cuts[1:], strict=True):
        data = b"".join(np.ascontiguousarray(c[i:j]).tobytes() for c in columns)
        yield int(b[i]), int(j - i), len(data), pa.compress(data, codec=_CODEC, asbytes=True)


_PACK = "bucket int, n long, size long, data binary"
_PACK_NAMES = ["bucket", "n", "size", "data"]
_PACK_TYPES = [pa.int32(), pa.int64(), pa.int64(), pa.binary()]


def _pack_batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [()] * 4, _PACK_TYPES, strict=True)], names=_PACK_NAMES)


def _unpacked(batches: Iterator[pa.RecordBatch], kinds: list[np.dtype]) -> Iterator[list[np.ndarray]]:
    """The columns of each bucket, from batches sorted by bucket."""
    now, held = None, []

    def joined() -> list[np.ndarray]:
        return [np.concatenate([x[i] for x in held]) for i in range(len(kinds))]

    for batch in batches:
        for bucket, n, size, data in zip(*(batch.column(i) for i in range(4)), strict=True):
            if held and bucket.as_py() != now:
                yield joined()
                held = []
            now, n, at, parts = bucket.as_py(), n.as_py(), 0, []
            raw = pa.decompress(data.as_buffer(), decompressed_size=size.as_py(), codec=_CODEC)
            for kind in kinds:
                parts.append(np.frombuffer(raw, kind, n, at))
                at += n * kind.itemsize
            held.append(parts)
    if held:
        yield joined()


# ---------------------------------------------------------------- the stages


#: Of a seed's hash only the upper half is sent, as the lower one chose the bucket: seeds that share it are told apart by their bytes.
_ANCHOR = [np.dtype(np.uint32), np.dtype(np.int64), np.dtype(np.int64), np.dtype(np.uint32)]


def _upper(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(32)).astype(np.uint32)


def _anchors(texts: DataFrame, spec: RepeatSpec, buckets: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rid, key = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for block in blocks(batch.column(2), 4 << 20):
                h, row, at = minimizers(block, spec)
                row = row + block.first
                yield _pack_batch(list(_packed((h % np.uint64(buckets)).astype(np.int64), [_upper(h), rid[row], key[row], at.astype(np.uint32)])))

    return texts.mapInArrow(run, _PACK)


def _shared_anchors(packs: DataFrame) -> DataFrame:
    """(rid, key, at) of the minimizers that two documents or more have."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for h, rid, key, at in _unpacked(batches, _ANCHOR):
            order = np.argsort(h, kind="stable")
            h, rid, key, at = h[order], rid[order], key[order], at[order]
            cuts = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
            several = np.minimum.reduceat(rid, cuts) != np.maximum.reduceat(rid, cuts)
            keep = np.repeat(several, np.diff(np.append(cuts, len(h))))
            for i in range(0, int(keep.sum()), 100_000):
                pick = np.flatnonzero(keep)[i : i + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(rid[pick]), pa.array(key[pick]), pa.array(at[pick].astype(np.int32))], names=["rid", "key", "at"])

    return packs.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, "rid long, key long, at int")


def _context_kinds(spec: RepeatSpec) -> list[np.dtype]:
    return [*_ANCHOR, np.dtype(np.uint8), np.dtype(np.uint8), np.dtype((np.void, spec.around))]


def _contexts(with_at: DataFrame, spec: RepeatSpec, buckets: int) -> DataFrame:
    """From (rid, key, text, at array): the bytes around each minimizer, dealt by its hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rid, key = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            places = batch.column(3)
            for block in blocks(batch.column(2), 4 << 20):
                lists = places.slice(block.first, block.n)
                counts = np.diff(lists.offsets.to_numpy())
                row = np.repeat(np.arange(block.n), counts)
                at = lists.flatten().to_numpy().astype(np.int64) + block.offsets[row]
                left = np.minimum(spec.reach, at - block.offsets[row])
                right = np.minimum(spec.reach, block.offsets[row + 1] - at - spec.seed)
                h = seed_hashes(block.data, spec.seed)[at] if len(at) else np.zeros(0, np.uint64)
                padded = np.concatenate([np.zeros(spec.reach, np.uint8), block.data, np.zeros(spec.reach, np.uint8)])
                out = np.lib.stride_tricks.sliding_window_view(padded, spec.around)[at].copy() if len(at) else np.zeros((0, spec.around), np.uint8)
                # What lies beyond the text is not its own: zeros there.
                column = np.arange(spec.around)
                out[(column < (spec.reach - left)[:, None]) | (column >= (spec.reach + spec.seed + right)[:, None])] = 0
                row = row + block.first
                columns = [_upper(h), rid[row], key[row], (at - block.offsets[row - block.first]).astype(np.uint32), left.astype(np.uint8), right.astype(np.uint8), out.view(np.dtype((np.void, spec.around))).ravel()]
                yield _pack_batch(list(_packed((h % np.uint64(buckets)).astype(np.int64), columns)))

    return with_at.mapInArrow(run, _PACK)


def repeated_starts(h: np.ndarray, rid: np.ndarray, left: np.ndarray, right: np.ndarray, around: np.ndarray, spec: RepeatSpec) -> np.ndarray:
    """For each row of a bucket, a mask of the starts (bit i: i bytes into the surroundings) whose string an earlier document has."""
    order = np.lexsort((rid, right, left, around, h))
    h, rid, left, right, around = h[order], rid[order], left[order], right[order], around[order]
    # Distinct surroundings: rows that differ in none of the four.
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (around[1:] != around[:-1]) | (left[1:] != left[:-1]) | (right[1:] != right[:-1])
    kind = np.cumsum(new) - 1
    first = np.flatnonzero(new)
    least = np.minimum.reduceat(rid, first)
    starts = spec.reach + 1
    bit = np.arange(starts)
    whole = (bit >= (spec.reach - left[first].astype(np.int64))[:, None]) & (bit + spec.length <= (spec.reach + spec.seed + right[first].astype(np.int64))[:, None])
    best = np.where(whole, least[:, None], np.iinfo(np.int64).max)
    # Only hashes with two different surroundings or more need their suffixes sorted.
    hash_of = h[first]
    cut = np.flatnonzero(np.concatenate([[True], hash_of[1:] != hash_of[:-1], [True]]))
    sizes = np.diff(cut)
    step = -(-spec.around // COVER) * COVER  # surroundings begin at equal residues, so that their ties share one
    a = 0
    while a < len(sizes):
        b = a + 1
        while b < len(sizes) and (cut[b + 1] - cut[a]) * starts <= BLOCK_SUFFIXES:
            b += 1
        group = np.flatnonzero(np.repeat(sizes[a:b] > 1, sizes[a:b])) + cut[a]
        if len(group):
            text = np.zeros((len(group), step), np.uint8)
            text[:, : spec.around] = np.frombuffer(around[first[group]].tobytes(), np.uint8).reshape(-1, spec.around)
            text = text.ravel()
            i, j = np.nonzero(whole[group])
            at = suffix_order(text, i * step + j, spec.length)
            same = agree(text, at[1:], at[:-1], spec.length)
            name = np.concatenate([[0], np.cumsum(~same)])
            value = least[group[at // step]]
            lowest = np.full(name[-1] + 1, np.iinfo(np.int64).max)
            np.minimum.at(lowest, name, value)
            best[group[at // step], at % step] = lowest[name]
        a = b
    earlier = best[kind] < rid[:, None]
    mask = np.zeros(len(h), np.uint64)
    mask[order] = (earlier.astype(np.uint64) << bit.astype(np.uint64)).sum(axis=1, dtype=np.uint64)
    return mask


def _repeats(packs: DataFrame, spec: RepeatSpec) -> DataFrame:
    """(rid, key, at, mask) of the surroundings that hold a repeated string."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for h, rid, key, at, left, right, around in _unpacked(batches, _context_kinds(spec)):
            mask = repeated_starts(h, rid, left, right, around, spec)
            pick = np.flatnonzero(mask)
            yield pa.RecordBatch.from_arrays([pa.array(rid[pick]), pa.array(key[pick]), pa.array(at[pick].astype(np.int32)), pa.array(mask[pick].view(np.int64))], names=["rid", "key", "at", "mask"])

    return packs.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, "rid long, key long, at int, mask long")


def removed_bytes(n: int, at: np.ndarray, mask: np.ndarray, spec: RepeatSpec) -> np.ndarray:
    """Which of n bytes lie in a repeated string."""
    hit = (mask.view(np.uint64)[:, None] >> np.arange(spec.reach + 1, dtype=np.uint64)) & np.uint64(1) > 0
    i, j = np.nonzero(hit)
    edge = np.zeros(n + 1, np.int64)
    start = np.unique(at[i].astype(np.int64) - spec.reach + j)
    edge[start] += 1
    np.add.at(edge, start + spec.length, -1)
    return np.cumsum(edge)[:-1] > 0


def deduplicated(docs: DataFrame, spec: RepeatSpec = RepeatSpec(), keep_text: bool = False) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256; with ``keep_text`` also spans (start:end in bytes) and kept (binary)."""
    spark = docs.sparkSession
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(2 * int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // BUCKET_BYTES))
    every = docs.select(F.col("doc_id").cast("long").alias("rid"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("key"), F.coalesce("text", F.lit("")).alias("text"))
    light = every.select("rid", "key", F.md5("text").alias("m"), F.octet_length("text").alias("n")).filter("rid IS NOT NULL")
    least = light.filter(F.col("n") >= spec.length).groupBy("m", "n").agg(F.min("rid").alias("least"), F.max("rid").alias("most")).filter("least < most")
    copies = written(light.join(least, ["m", "n"]).filter("rid > least").select("rid", "key").distinct(), "repeat-copies")
    few = copies.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    copies = F.broadcast(copies) if few else copies
    texts = every.filter(F.col("rid").isNotNull() & (F.octet_length("text") >= spec.length)).join(copies, ["rid", "key"], "left_anti")
    shared = written(_shared_anchors(_anchors(texts, spec, buckets)), "repeat-anchors")
    with_at = texts.join(shared.groupBy("rid", "key").agg(F.collect_set("at").alias("at")), ["rid", "key"]).select("rid", "key", "text", "at")
    found = written(_repeats(_contexts(with_at, spec, buckets), spec), "repeat-starts")
    whole = copies.select("rid", "key", F.lit(True).alias("copy"))
    marks = found.groupBy("rid", "key").agg(F.collect_list("at").alias("at"), F.collect_list("mask").alias("mask"))
    rows = every.join(F.broadcast(whole) if few else whole, ["rid", "key"], "left").join(marks, ["rid", "key"], "left").select("rid", "text", "copy", "at", "mask")
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", spans string, kept binary" * keep_text

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(6)]
            for block in blocks(batch.column(1)):
                for i in range(block.n):
                    data = block.data[block.offsets[i] : block.offsets[i + 1]]
                    at = batch.column(3)[block.first + i]
                    if batch.column(2)[block.first + i].as_py():
                        gone = np.ones(len(data), bool)
                    elif at.is_valid:
                        gone = removed_bytes(len(data), at.values.to_numpy(), batch.column(4)[block.first + i].values.to_numpy(), spec)
                    else:
                        gone = np.zeros(len(data), bool)
                    edge = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(np.int8), [0]])))
                    kept = data[~gone].tobytes()
                    for x, v in zip(out, (len(data), int(gone.sum()), len(edge) // 2, sha256(kept).hexdigest(), ",".join(f"{a}:{b}" for a, b in zip(edge[::2], edge[1::2], strict=True)), kept), strict=True):
                        x.append(v)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()]
            columns = [batch.column(0), *(pa.array(x, k) for x, k in zip(out, kinds, strict=True))]
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"]
            yield pa.RecordBatch.from_arrays(columns[: 7 if keep_text else 5], names=names[: 7 if keep_text else 5])

    return rows.mapInArrow(run, schema)
