"""Arrow batches as blocks of bounded bytes, and words of a whole block at once in numpy.

A block holds the texts of some rows as one byte array with offsets. Words are maximal runs of bytes other than white
space; as no byte of a longer UTF-8 sequence is below 0x80, that is the same as on code points.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Bytes of text worked on at once; bounds what a Python worker holds besides Spark's own batch. One longer text makes a block of its own.
BLOCK_BYTES = 1 << 19

_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def _spread(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that mixes all bits (the splitmix finalizer)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_ODD = np.uint64(0x9E3779B97F4A7C15)
_BYTE_CODE = _spread(np.arange(1, 257, dtype=np.uint64) * _ODD)


@dataclass
class Block:
    """Rows ``first`` to ``first + n`` of a batch: bytes of their texts and n + 1 offsets."""

    first: int
    data: np.ndarray
    offsets: np.ndarray

    @property
    def n(self) -> int:
        return len(self.offsets) - 1

    def text(self, i: int) -> str:
        return self.data[self.offsets[i] : self.offsets[i + 1]].tobytes().decode("utf-8", "replace")


def blocks(texts: pa.Array, block_bytes: int = BLOCK_BYTES) -> Iterator[Block]:
    """The texts of a batch, nulls as empty ones, in blocks of whole rows."""
    texts = texts.cast(pa.large_binary()) if not pa.types.is_large_binary(texts.type) else texts
    if texts.null_count:
        texts = texts.fill_null(b"")
    _, where, data = texts.buffers()
    at = np.frombuffer(where, np.int64, len(texts) + 1, texts.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    i = 0
    while i < len(texts):
        j = max(i + 1, int(np.searchsorted(at, at[i] + block_bytes, "right")) - 1)
        j = min(j, len(texts))
        yield Block(i, raw[at[i] : at[j]], at[i : j + 1] - at[i])
        i = j


@dataclass
class Words:
    """Words of a block: start and end byte, the 64-bit hash, and for each row the first word's number (n + 1 entries)."""

    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    rows: np.ndarray
    stems: np.ndarray | None = None


_POWERS = np.ones(1, np.uint64)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        _POWERS = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n + n // 4, _ODD, np.uint64))])
    return _POWERS[:n]


_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_INVERSES = np.ones(1, np.uint64)


def _inverses(n: int) -> np.ndarray:
    global _INVERSES
    if len(_INVERSES) < n:
        _INVERSES = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n + n // 4, _INVERSE, np.uint64))])
    return _INVERSES[:n]


def words(block: Block, lower: bool = False, apart: np.ndarray = _IS_SPACE, stem: int = 0) -> Words:
    """All words with hashes; ``lower`` takes A-Z as a-z, ``apart`` tells the bytes between words.

    With ``stem``, ``stems`` has the hashes of the words' first ``stem`` bytes.
    """
    data = _LOWER[block.data] if lower else block.data
    inside = np.zeros(len(data) + 1, bool)
    inside[:-1] = ~apart[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    joints = block.offsets[1:-1]
    begins[joints] = inside[joints]  # a text never goes on in the next one
    start = np.flatnonzero(begins)
    stops = np.zeros(len(data) + 1, bool)
    stops[1:] = inside[:-1] & ~inside[1:]
    stops[joints] |= inside[joints - 1] & (joints > 0)
    end = np.flatnonzero(stops)
    with np.errstate(over="ignore"):
        run = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_BYTE_CODE[data] * _powers(len(data)), out=run[1:])
        back = _inverses(len(data) + 1)[start]
        h = _spread((run[end] - run[start]) * back ^ (end - start).astype(np.uint64))
        short = np.minimum(start + stem, end)
        stems = _spread((run[short] - run[start]) * back) if stem else None
    return Words(start, end, h, np.searchsorted(start, block.offsets, "left"), stems)


def grams(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k words from each word on, and whether these lie in one text; for all words of the block."""
    n = len(w.hash)
    h = np.zeros(n, np.uint64)
    with np.errstate(over="ignore"):
        for i in range(k):
            part = np.zeros(n, np.uint64)
            part[: max(0, n - i)] = w.hash[i:]
            h = _spread(h * _ODD + part)
    last = np.repeat(w.rows[1:], np.diff(w.rows))
    return h, np.arange(n) + k <= last


def row_of_word(w: Words) -> np.ndarray:
    return np.repeat(np.arange(len(w.rows) - 1), np.diff(w.rows))
