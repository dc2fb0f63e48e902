"""Token counts by a compiled finite-state tokenizer.

A tokenizer file (byte-pair encoding behind a splitting pattern for contractions, letters, single digits and symbols) is
compiled into two deterministic machines.

The splitter has six states over character classes; the class of a code point is found by probing the file's own normalizer and
splitter, once. Its transitions say where words begin. A chunk of characters is then a map from states to states; the maps
of all chunks of a block are computed side by side and composed by a parallel prefix scan, which gives every chunk its first state.

The word machine reads the bytes of a word, and each transition carries by how many tokens the encoding of what has been read so far
grows or shrinks; the sum along a word is its count. It rests on two properties of byte-pair encoding: a sequence of tokens is the
encoding of its text if each two neighbours are the encoding of theirs, and the encoding of a text ends in the one token that goes with
the encoding of what lies before it. So a state is the longest end of the read text that may begin a token, with the last token and the
count at every place in it: finitely many. Transitions are compiled from the file's merges when they are first taken and
kept, up to ``TRANSITIONS`` of them; counts of whole words are kept too, up to ``MEMO``. The library is not asked for tokens.

Texts beyond Latin letters, punctuation and currency signs go through the file's normalizer first, as composition and case may then
span several code points. Special tokens in a text part it and count one each.

Defined cases: a null or empty text has 0 tokens; repeated rows are counted alike; an empty table gives an empty result;
other columns are ignored unless named in ``keep``.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from carepath.llm._blocks import _ODD, _inverses, _powers, _spread, blocks
from carepath.llm._shared import carried, restored

#: Character classes; letters that can stand in a contraction have their own.
SPACE, SYMBOL, DIGIT, QUOTE, LETTER, ONE, E_, RV, L_ = range(9)
UNKNOWN = 255
#: States of the splitter: at a fresh position; in letters; in symbols; after a fresh quote; after it and r or v; after it and l.
FRESH, WORD, SYMBOLS, QUOTED, QUOTED_RV, QUOTED_L = range(6)
N_STATES = 6
#: Output of a transition: a token begins at this character, at the one before.
HERE, BEFORE = 1, 2
#: Code points that the normalizer takes one by one: Latin letters, general punctuation, currency signs.
COMPILED = (*range(0x250), *range(0x2010, 0x2060), *range(0x20A0, 0x20C0))
CHUNK = 128
#: Words kept by a worker, and transitions of its word machine.
MEMO = 1 << 19
TRANSITIONS = 1 << 19


def splitter() -> tuple[np.ndarray, np.ndarray]:
    """Next states and outputs by class and state."""
    step, out = np.zeros((9, N_STATES), np.uint8), np.zeros((9, N_STATES), np.uint8)
    letters = (LETTER, ONE, E_, RV, L_)
    for state in range(N_STATES):
        # A quote with r, v or l behind it that no contraction uses: the letter began a word of its own.
        late = BEFORE if state in (QUOTED_RV, QUOTED_L) else 0
        step[SPACE, state], out[SPACE, state] = FRESH, late
        step[DIGIT, state], out[DIGIT, state] = FRESH, late | HERE
        in_symbols = state in (SYMBOLS, QUOTED)
        step[SYMBOL, state], out[SYMBOL, state] = SYMBOLS, late | (0 if in_symbols else HERE)
        step[QUOTE, state], out[QUOTE, state] = (SYMBOLS, 0) if in_symbols else (QUOTED, late | HERE)
        for c in letters:
            step[c, state], out[c, state] = WORD, late or (0 if state == WORD else HERE)
    step[ONE, QUOTED], out[ONE, QUOTED] = FRESH, 0
    step[RV, QUOTED], out[RV, QUOTED] = QUOTED_RV, 0
    step[L_, QUOTED], out[L_, QUOTED] = QUOTED_L, 0
    step[E_, QUOTED_RV], out[E_, QUOTED_RV] = FRESH, 0
    step[L_, QUOTED_L], out[L_, QUOTED_L] = FRESH, 0
    return step, out


def compose(first: np.ndarray, then: np.ndarray) -> np.ndarray:
    """The maps that apply ``first`` and ``then``, row by row."""
    return np.take_along_axis(then, first, axis=1)


def prefix_scan(maps: np.ndarray) -> np.ndarray:
    """Row i: the composition of maps 0 to i, in rounds that double the reach."""
    done, reach = maps.copy(), 1
    while reach < len(done):
        done[reach:] = compose(done[:-reach], done[reach:])
        reach *= 2
    return done


def states(classes: np.ndarray, step: np.ndarray, chunk: int = CHUNK) -> np.ndarray:
    """The state before each character, from FRESH on, by chunk maps and their prefix scan."""
    n = len(classes)
    rows = max(1, -(-n // chunk))
    grid = np.full(rows * chunk, SPACE, np.intp)
    grid[:n] = classes
    grid = np.ascontiguousarray(grid.reshape(rows, chunk).T) * N_STATES
    flat = step.reshape(-1).astype(np.intp)
    maps = np.broadcast_to(np.arange(N_STATES), (rows, N_STATES)).copy()
    for column in grid:
        maps = flat[column[:, None] + maps]
    now = np.zeros(rows, np.intp)
    now[1:] = prefix_scan(maps)[:-1, FRESH]
    before = np.empty((chunk, rows), np.uint8)
    for t, column in enumerate(grid):
        before[t] = now
        now = flat[column + now]
    return before.T.reshape(-1)[:n]


def byte_letters() -> dict[str, int]:
    """The byte that each letter of a byte-level vocabulary stands for: printable ones for themselves, the others in order from 256 on."""
    printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    others = [b for b in range(256) if b not in set(printable)]
    return {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(others)}


class WordMachine:
    """The transducer of a word's bytes. Symbols are bytes, and bytes that end a word (256 more); texts of symbols are strings."""

    def __init__(self, model: dict):
        letters, end = byte_letters(), model["end_of_word_suffix"]

        def symbols(token: str) -> str:
            plain = token.removesuffix(end)
            codes = [letters[c] for c in plain]
            return "".join(map(chr, codes[:-1])) + chr(codes[-1] + (256 if plain != token else 0))

        spelled = {token: symbols(token) for token in model["vocab"] if token.removesuffix(end)}
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        #: Of two neighbouring texts, the order in which they are merged.
        self.rank = {(spelled[a], spelled[b]): i for i, (a, b) in enumerate(pairs)}
        self.tokens = set(spelled.values())
        self.begins = {t[:i] for t in self.tokens for i in range(1, len(t))}
        self._alone: dict[str, bool] = {}
        self._pair: dict[tuple[str, str], bool] = {}
        self.forget()

    def forget(self) -> None:
        """Back to the first state; what was compiled is compiled again when it is needed."""
        first = ("", (None,), (0,))
        self.states, self.number, self.step = [first], {first: 0}, {}
        self._pair.clear()

    def merged(self, text: str) -> list[str]:
        """The encoding by merging, for short texts."""
        parts = list(text)
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get((parts[i], parts[i + 1]), 1 << 60))
            if (parts[best], parts[best + 1]) not in self.rank:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return parts

    def goes(self, last: str | None, token: str) -> bool:
        """Whether ``token`` can stand behind ``last``, or first in a word, in an encoding."""
        if token not in self._alone:
            self._alone[token] = self.merged(token) == [token]
        if not self._alone[token] or last is None:
            return self._alone[token]
        if (last, token) not in self._pair:
            self._pair[last, token] = self.merged(last + token) == [last, token]
        return self._pair[last, token]

    def transition(self, state: int, symbol: int) -> tuple[int, int]:
        """The next state, and by how many tokens the encoding grows."""
        window, lasts, counts = self.states[state]
        read = window + chr(symbol)
        for at in range(len(read)):
            if read[at:] in self.tokens and self.goes(lasts[at], read[at:]):
                last, count = read[at:], counts[at] + 1
                break
        else:
            raise ValueError("a byte is not in the vocabulary")
        cut = next((i for i in range(len(read)) if read[i:] in self.begins), len(read))
        new = (read[cut:], (*lasts[cut:], last), tuple(c - count for c in (*counts[cut:], count)))
        if new not in self.number:
            self.number[new] = len(self.states)
            self.states.append(new)
        self.step[state << 9 | symbol] = found = (self.number[new], count)
        return found

    def count(self, word: bytes) -> int:
        """Tokens of a word."""
        if not word:
            return 0
        if len(self.step) > TRANSITIONS:
            self.forget()
        state, total, step = 0, 0, self.step
        for b in word[:-1]:
            state, more = step.get(state << 9 | b) or self.transition(state, b)
            total += more
        return total + (step.get(state << 9 | 256 | word[-1]) or self.transition(state, 256 | word[-1]))[1]


class Counter:
    """A compiled tokenizer file."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        library = Tokenizer.from_file(path)
        self.normalizer, self.pre_tokenizer = library.normalizer, library.pre_tokenizer
        self.step, self.out = splitter()
        self.specials = [t.content for t in library.get_added_tokens_decoder().values()]
        self.special = re.compile("|".join(map(re.escape, sorted(self.specials, key=len, reverse=True))) or r"(?!)")
        with open(path, encoding="utf-8") as file:
            self.machine = WordMachine(json.load(file)["model"])
        self.classes = np.full(0x110000, UNKNOWN, np.uint8)
        self.fold = np.arange(0x110000, dtype=np.uint32)
        #: Code points that the normalizer changes, if at all, into one other whatever stands beside them.
        self.simple = np.zeros(0x110000, bool)
        for point in COMPILED:
            folded = self.normalizer.normalize_str(chr(point))
            if len(folded) == 1:
                self.simple[point], self.fold[point] = True, ord(folded)
                self.classes[point] = self._class(folded)
        self.known, self.counts = np.zeros(0, np.uint64), np.zeros(0, np.int64)

    def _class(self, folded: str) -> int:
        pieces = lambda s: len(self.pre_tokenizer.pre_tokenize_str(s))
        if pieces(f"a{folded}") == 1 and pieces(f"b{folded}b") == 1:
            return {"s": ONE, "t": ONE, "m": ONE, "d": ONE, "e": E_, "r": RV, "v": RV, "l": L_}.get(folded, LETTER)
        if pieces(folded) == 0:
            return SPACE
        if pieces(folded * 2) == 2:
            return DIGIT
        return QUOTE if folded == "'" else SYMBOL

    def _points(self, text: str) -> np.ndarray:
        """Normalized code points of a text, all of known class."""
        points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        if self.simple[points].all():
            return self.fold[points]
        points = np.frombuffer(self.normalizer.normalize_str(text).encode("utf-32-le"), np.uint32)
        for point in np.unique(points[self.classes[points] == UNKNOWN]).tolist():
            self.classes[point] = self._class(chr(point))
        return points

    def count(self, texts: list[str]) -> np.ndarray:
        """Tokens of each text."""
        total = np.zeros(len(texts), np.int64)
        parts, owner = [], []
        for i, text in enumerate(texts):
            pieces = self.special.split(text) if any(s in text for s in self.specials) else [text]
            total[i] = len(pieces) - 1
            for piece in pieces:
                if piece:
                    parts.append(self._points(piece))
                    owner.append(i)
        if parts:
            gap = np.array([0x20], np.uint32)
            joined = np.concatenate([x for p in parts for x in (p, gap)])
            first = np.cumsum([0, *(len(p) + 1 for p in parts)])
            start, emitted = self._words(joined)
            edge = np.searchsorted(start, first)
            sums = np.concatenate([[0], np.cumsum(emitted)])
            np.add.at(total, owner, sums[edge[1:]] - sums[edge[:-1]])
        return total

    def _words(self, joined: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts of the splitter's words and the tokens that each emits, from normalized code points that end in a space."""
        classes = self.classes[joined]
        out = self.out[classes, states(classes, self.step)]
        begins = (out & HERE) > 0
        begins[:-1] |= (out[1:] & BEFORE) > 0
        start = np.flatnonzero(begins)
        stop = np.flatnonzero(begins | (classes == SPACE))
        end = stop[np.searchsorted(stop, start, "right")]  # the last character is a space
        with np.errstate(over="ignore"):
            run = np.zeros(len(joined) + 1, np.uint64)
            np.cumsum(_spread(joined.astype(np.uint64) + np.uint64(1)) * _powers(len(joined)), out=run[1:])
            h = _spread((run[end] - run[start]) * _inverses(len(joined) + 1)[start] + (end - start).astype(np.uint64) * _ODD)
        keys, at, back = np.unique(h, return_index=True, return_inverse=True)
        where = np.searchsorted(self.known, keys)
        hit = where < len(self.known)
        hit[hit] = self.known[where[hit]] == keys[hit]
        counts = np.zeros(len(keys), np.int64)
        counts[hit] = self.counts[where[hit]]
        if not hit.all():
            new = np.flatnonzero(~hit)
            counts[new] = [self.machine.count(joined[start[i] : end[i]].tobytes().decode("utf-32-le").encode()) for i in at[new].tolist()]
            if len(self.known) + len(new) > MEMO:
                self.known, self.counts = keys, counts
            else:
                both = np.concatenate([self.known, keys[new]])
                order = np.argsort(both, kind="stable")
                self.known, self.counts = both[order], np.concatenate([self.counts, counts[new]])[order]
        return start, counts[back]


_compiled: dict[str, Counter] = {}


def counter(path: str) -> Counter:
    """The file's machines, compiled once by a worker."""
    if path not in _compiled:
        _compiled[path] = Counter(path)
    return _compiled[path]


def counted(docs: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """``keep`` with n_bytes (UTF-8) and n_tokens. ``path``: the tokenizer file, at the same place on every executor."""
    source = carried(docs, keep, _text=F.col(text))
    schema = T.StructType([source.schema["_k"], T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = counter(path)
        for batch in batches:
            sizes, tokens = [], []
            for block in blocks(batch.column(1), 1 << 20):
                sizes.append(np.diff(block.offsets))
                tokens.append(machine.count([block.text(i) for i in range(block.n)]))
            join = lambda parts: pa.array(np.concatenate(parts) if parts else np.zeros(0, np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), join(sizes), join(tokens)], names=schema.names)

    return restored(source.mapInArrow(run, schema), keep, ["n_bytes", "n_tokens"])
