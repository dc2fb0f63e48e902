"""Secret scans through a trigram inverted index.

From each rule's regular expression a Boolean query over trigrams is derived: whatever text matches the rule must satisfy
the query. Blocks of rows get an inverted index over the trigrams that some query names, the queries are answered by
intersecting and uniting postings, and only the rows left are searched with the expression itself. Rules without a
mandatory trigram (long hexadecimal runs) have the query ``ALL`` and are searched in every row.

The index is built, asked and dropped within a block, so a scan is one pass without a shuffle. ``postings`` gives the
same index as a table for scans that come back with new rules, and ``candidates`` asks it with joins on row keys.

Defined cases: a null or empty text has no spans; repeated rows are scanned alike; an empty table gives an empty result;
other columns are ignored unless named in ``keep``. Spans are code points with the end left out; within a kind they
don't overlap, between kinds they may.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from re import _constants as op
from re import _parser

from carepath.llm._blocks import _LOWER, Block, blocks
from carepath.llm._shared import carried, restored

ALL = ("all",)


@dataclass(frozen=True)
class Rule:
    """``least`` is the shortest value that counts: of ``group``, else of the whole match."""

    kind: str
    pattern: str
    least: int = 0
    group: int = 0
    query: tuple = field(init=False, compare=False)

    def __post_init__(self):
        object.__setattr__(self, "query", query_of(self.pattern))

    def spans(self, text: str, expression: re.Pattern) -> list[tuple[int, int]]:
        return [m.span() for m in expression.finditer(text) if m.end(self.group) - m.start(self.group) >= self.least]


# ---------------------------------------------------------------- queries from expressions


def _both(a: tuple, b: tuple) -> tuple:
    return b if a == ALL else a if b == ALL or a == b else ("and", a, b)


def _either(a: tuple, b: tuple) -> tuple:
    return ALL if ALL in (a, b) else a if a == b else ("or", a, b)


def _of_string(s: str) -> tuple:
    return reduce(_both, (("tri", s[i : i + 3]) for i in range(len(s) - 2)), ALL)


def _of_strings(found: set[str]) -> tuple:
    return reduce(_either, map(_of_string, sorted(found)))


#: More strings than this are no longer followed one by one.
MOST_STRINGS = 64


def _walk(items) -> tuple[set[str] | None, tuple]:
    """The exact strings of a sequence (None if they aren't few), and what any match must satisfy besides."""
    strings, query, exact = {""}, ALL, True

    def cut() -> None:
        nonlocal strings, query, exact
        query, strings, exact = _both(query, _of_strings(strings)), {""}, False

    for kind, arg in items:
        sub, more = None, ALL
        if kind is op.LITERAL:
            sub = {chr(arg).lower()}
        elif kind is op.IN:
            sub = _of_class(arg)
        elif kind is op.SUBPATTERN:
            sub, more = _walk(arg[-1])
        elif kind is op.BRANCH:
            parts = [_walk(x) for x in arg[1]]
            if all(s is not None for s, _ in parts):
                sub = set().union(*(s for s, _ in parts))
            else:
                more = reduce(_either, (_both(q, _of_strings(s)) if s else q for s, q in parts))
        elif kind in (op.MAX_REPEAT, op.MIN_REPEAT):
            low, high, body = arg
            inner, asked = _walk(body)
            if inner is not None and (low, high) == (0, 1):
                sub = inner | {""}
            elif inner is not None and low == high <= 4:
                sub = reduce(lambda a, b: {x + y for x in a for y in b}, [inner] * low, {""})
            elif low:
                more = _both(asked, _of_strings(inner)) if inner else asked
        elif kind is op.AT:
            continue
        if sub is not None and len(sub) * len(strings) <= MOST_STRINGS:
            strings = {a + b for a in strings for b in sub}
        else:
            cut()
            if sub is not None:
                more = _both(more, _of_strings(sub))
        query = _both(query, more)
    return (strings, query) if exact else (None, _both(query, _of_strings(strings)))


def _of_class(arg) -> set[str] | None:
    found: set[str] = set()
    for kind, x in arg:
        if kind is op.LITERAL:
            found.add(chr(x).lower())
        elif kind is op.RANGE and x[1] - x[0] < 8:
            found |= {chr(c).lower() for c in range(x[0], x[1] + 1)}
        else:
            return None
    return found if len(found) <= 8 else None


def query_of(pattern: str) -> tuple:
    """The Boolean trigram query (in lower case) that every text with a match of ``pattern`` satisfies."""
    strings, query = _walk(_parser.parse(pattern))
    return _both(query, _of_strings(strings)) if strings else query


def trigrams_of(query: tuple) -> set[str]:
    return {query[1]} if query[0] == "tri" else set().union(*(trigrams_of(q) for q in query[1:]))


def answer(query: tuple, posting, everything):
    """The query's rows as a bitmap; ``posting`` gives a trigram's."""
    if query == ALL:
        return everything
    if query[0] == "tri":
        return posting(query[1])
    a, b = (answer(q, posting, everything) for q in query[1:])
    return a & b if query[0] == "and" else a | b


# ---------------------------------------------------------------- rules

#: The three base kinds.
BASE = (
    Rule("assign", r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 6, 2),
    Rule("access", r"AKIA[A-Z0-9]+", 20),
    Rule("hex", r"[0-9a-f]+", 24),
)
#: Kinds that the index makes cheap to add: each has mandatory trigrams.
MORE = (
    Rule("private_key", r"-----BEGIN (?:[A-Z]+ ){0,3}PRIVATE KEY-----"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]+"),
    Rule("code_host", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat_token", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("map_key", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("url_login", r"[a-z]{2,12}://[A-Za-z0-9._-]+:[^\s/@:]{3,}@"),
)
RULES = (*BASE, *MORE)


class Index:
    """Trigrams of all queries; for a block, a bitmap of rows per trigram."""

    def __init__(self, rules: tuple[Rule, ...]):
        self.grams = sorted(g for g in set().union(*(trigrams_of(r.query) for r in rules if r.query != ALL)) if g.isascii())
        self.number = {g: i for i, g in enumerate(self.grams)}
        self.table = np.zeros(1 << 24, np.uint16)
        for g, i in self.number.items():
            a, b, c = g.encode()
            self.table[a << 16 | b << 8 | c] = i + 1

    def pairs(self, block: Block) -> tuple[np.ndarray, np.ndarray]:
        """(trigram number, row) of the block, each once."""
        data = _LOWER[block.data]
        if len(data) < 3:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        code = data[:-2].astype(np.uint32) << np.uint32(16)
        code |= data[1:-1].astype(np.uint32) << np.uint32(8)
        code |= data[2:]
        got = self.table[code]
        at = np.flatnonzero(got)
        row = np.searchsorted(block.offsets, at, "right") - 1
        whole = at + 3 <= block.offsets[row + 1]
        key = np.unique(got[at[whole]].astype(np.int64) * block.n + row[whole])
        return key // block.n - 1, key % block.n

    def bitmaps(self, block: Block) -> np.ndarray:
        maps = np.zeros((len(self.grams), block.n), bool)
        maps[self.pairs(block)] = True
        return maps

    def rows(self, rule: Rule, maps: np.ndarray) -> np.ndarray:
        return answer(rule.query, lambda g: maps[self.number[g]] if g in self.number else np.ones(maps.shape[1], bool), np.ones(maps.shape[1], bool))


def _find(block: Block, index: Index, rules: tuple[Rule, ...], expressions: list[re.Pattern]) -> list[list[tuple[int, int, int]]]:
    """(start, rule number, end) of every row, sorted."""
    found: list[list[tuple[int, int, int]]] = [[] for _ in range(block.n)]
    maps = index.bitmaps(block)
    asked = np.array([index.rows(r, maps) for r in rules])
    for i in np.flatnonzero(asked.any(axis=0)):
        text = block.text(i)
        for k in np.flatnonzero(asked[:, i]):
            found[i] += [(a, int(k), b) for a, b in rules[k].spans(text, expressions[k])]
        found[i].sort()
    return found


def _joined(spans: list[tuple[int, int, int]], rules: tuple[Rule, ...]) -> str:
    return ",".join(f"{rules[k].kind}:{a}:{b}" for a, k, b in spans)


def scan(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text", rules: tuple[Rule, ...] = RULES, base: int = 3) -> DataFrame:
    """``keep`` and, per row: n_<kind> for each rule, base_spans (of the first ``base`` rules) and spans, as kind:start:end."""
    source = carried(docs, keep, _text=F.col(text))
    kinds = [f"n_{r.kind}" for r in rules]
    schema = T.StructType([source.schema["_k"], *(T.StructField(k, T.LongType()) for k in kinds), T.StructField("base_spans", T.StringType()), T.StructField("spans", T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, expressions = Index(rules), [re.compile(r.pattern) for r in rules]
        for batch in batches:
            found = [row for block in blocks(batch.column(1)) for row in _find(block, index, rules, expressions)]
            counts = [pa.array([sum(x[1] == k for x in row) for row in found], pa.int64()) for k in range(len(rules))]
            some = pa.array([_joined([x for x in row if x[1] < base], rules) for row in found], pa.string())
            every = pa.array([_joined(row, rules) for row in found], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts, some, every], names=schema.names)

    return restored(source.mapInArrow(run, schema), keep, schema.names[1:])


def digest(joined: str) -> str:
    return sha256(joined.encode()).hexdigest()


MASK = "[SECRET]"


def redacted(docs: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The same rows and columns with every span of ``text`` replaced by a mask; overlapping spans give one mask."""
    names = docs.columns
    where = names.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, expressions = Index(rules), [re.compile(r.pattern) for r in rules]
        for batch in batches:
            column, new = batch.column(where), []
            for block in blocks(column):
                for i, spans in enumerate(_find(block, index, rules, expressions)):
                    if not spans:
                        new.append(column[block.first + i].as_py())
                        continue
                    whole, out, done, upto = block.text(i), [], 0, -1
                    for a, _, b in spans:
                        if a >= upto:
                            out += [whole[done:a], MASK]
                        upto = max(upto, b)
                        done = upto
                    new.append("".join([*out, whole[done:]]))
            columns = [pa.array(new, pa.string()) if i == where else batch.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.mapInArrow(run, docs.schema)


# ---------------------------------------------------------------- the index as a table


def postings(docs: DataFrame, key: str = "doc_id", text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(trigram, key): the inverted index over the trigrams of all queries, to be written and asked again."""
    source = docs.select(key, F.col(text).alias("_text"))
    schema = T.StructType([T.StructField("trigram", T.StringType()), source.schema[0]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Index(rules)
        names = pa.array(index.grams, pa.string())
        for batch in batches:
            for block in blocks(batch.column(1)):
                g, row = index.pairs(block)
                yield pa.RecordBatch.from_arrays([names.take(pa.array(g)), batch.column(0).take(pa.array(row + block.first))], names=schema.names)

    return source.mapInArrow(run, schema)


def candidates(index: DataFrame, rule: Rule, key: str = "doc_id") -> DataFrame:
    """Keys whose postings satisfy a rule's query. A rule with the query ALL has no candidates here: it scans fully."""
    if rule.query == ALL:
        raise ValueError(f"{rule.kind} names no trigram; scan all rows")
    grams = sorted(trigrams_of(rule.query))
    has = {g: F.max((F.col("trigram") == g).cast("int")) == 1 for g in grams}
    return index.filter(F.col("trigram").isin(grams)).groupBy(key).agg(answer(rule.query, has.__getitem__, F.lit(True)).alias("_ok")).filter("_ok").select(key)
