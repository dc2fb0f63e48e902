import random

import numpy as np
import public_tokenizers
import pyarrow.parquet as pq
import pytest
from tokenizers import Tokenizer

from carepath.llm import tokens as T

HARD = ["", "it's we're  I'll don't 'rex 'l 'll 're 've' ''s '' 'r", "'r5 'v. 'l'l 'l\n", "<|endoftext|> hi <|startoftext|>", "É'S ÄÖ ü ß ﬁ İ Σας", "\x00\x1c\x1d a", "日本語 text", "¿qué? «a» — …'s '—", "½²³ ª º", "!'s !'re ?'", "a" * 500]


PATH = public_tokenizers.path("word_bpe_49k.json")
LIBRARY = Tokenizer.from_file(PATH)


def by_library(text):
    return len(LIBRARY.encode(text, add_special_tokens=False).ids)


@pytest.fixture(scope="module")
def machine():
    return T.Counter(PATH)


def test_counts_are_the_library_s(machine):
    random.seed(1)
    texts = HARD + ["".join(random.choice("'srtvlemd a5.- \néXÉ") for _ in range(random.randint(0, 300))) for _ in range(800)]
    texts += ["".join(random.choice("日本語のПривет ёй한글ᄒ\u0301\u0344😀👩\u200d🇫🇷İΣσςßﬁ٣१½ 'sA") for _ in range(random.randint(0, 200))) for _ in range(500)]
    assert machine.count(texts).tolist() == [by_library(t) for t in texts]


def test_whole_table(machine):
    """All documents of sf0.01, without one call of the library for a token."""
    texts = [t or "" for t in pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["text"]).column(0).to_pylist()]
    assert machine.count(texts).tolist() == [by_library(t) for t in texts]


def test_transitions_add_up_to_the_merges(machine, monkeypatch):
    """Random words over few letters, whose encodings change much while they are read; forgetting what was compiled changes nothing."""
    random.seed(4)
    words = ["".join(random.choice("theinrasong") for _ in range(random.randint(1, 14))) for _ in range(3000)]
    for bound in (1 << 19, 100):
        monkeypatch.setattr(T, "TRANSITIONS", bound)
        assert [machine.machine.count(w.encode()) for w in words] == [by_library(w) for w in words]


def test_states_do_not_depend_on_chunks():
    rng, (step, _) = np.random.default_rng(0), T.splitter()
    for n in (1, 5, 1000):
        classes = rng.integers(0, 9, n)
        state, want = T.FRESH, []
        for c in classes:
            want.append(state)
            state = step[c, state]
        for chunk in (1, 3, 128):
            assert T.states(classes, step, chunk).tolist() == want


def test_compose_is_associative():
    maps = np.random.default_rng(0).integers(0, 6, (3, 4, 6))
    assert (T.compose(T.compose(maps[0], maps[1]), maps[2]) == T.compose(maps[0], T.compose(maps[1], maps[2]))).all()


def test_memo_is_bounded(machine, monkeypatch):
    monkeypatch.setattr(T, "MEMO", 50)
    texts = [" ".join(f"word{i}x{j}" for j in range(30)) for i in range(10)]
    for t in texts:
        assert machine.count([t])[0] == by_library(t)
    assert len(machine.known) <= 100


def test_odd_rows(spark, odd, none):
    got = T.counted(odd, PATH, tuple(odd.columns)).collect()
    assert all((r.n_tokens, r.n_bytes) == (by_library(r.text or ""), len((r.text or "").encode())) for r in got)
    assert T.counted(none, PATH).count() == 0
