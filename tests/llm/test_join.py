import random
import re

import pytest

from carepath.llm import ngram_join as J

LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def brute(rows, spec):
    sets = {}
    for i, t in rows:
        w, k = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW)), spec.shingle
        sets[i] = frozenset(tuple(w[j : j + k]) for j in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(i for i in sets if sets[i])
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x = len(sets[a] & sets[b])
            if 100 * x >= spec.percent * (len(sets[a]) + len(sets[b]) - x):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    return {i: (len(sets[i]), find(i)) for i in sets}


@pytest.mark.parametrize("spec, crowded", [(J.JoinSpec(3, 90), 4096), (J.JoinSpec(), 5)])
def test_against_brute_force(spark, monkeypatch, spec, crowded):
    monkeypatch.setattr(J, "CROWDED", crowded)
    random.seed(3)
    words, rows = [f"w{i}" for i in range(60)], []
    for _ in range(9):
        base = [random.choice(words) for _ in range(random.choice([3, 12, 40, 200, 700]))]
        for _ in range(18):
            t = list(base)
            for _ in range(random.randint(0, max(1, len(base) // 40))):
                t[random.randrange(len(t))] = random.choice(words)
            rows.append((10 + 7 * len(rows), " ".join(t)))
    rows += [(90000, ""), (90001, None), (90002, "one"), (90003, "ONE"), (90004, "one two"), (90005, "  ")]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in J.joined(spark.createDataFrame(rows, "doc_id long, text string").repartition(4), spec).collect()}
    assert got == brute(rows, spec)


def test_bound_never_falls_short():
    import numpy as np

    rng = np.random.default_rng(1)
    for _ in range(200):
        pool = rng.integers(0, 1 << 62, 900, dtype=np.uint64)
        a, b = (np.unique(rng.choice(pool, rng.integers(1, 700))) for _ in range(2))
        x, y = J.signature(a), J.signature(b)
        assert J.bound(len(a), *J._level(x, y[None]), np.array([len(b)]))[0] >= len(np.intersect1d(a, b))


def test_one_id_with_different_texts(spark):
    a, b = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60))
    rows = [(0, b), (2, a), (2, b + " tail"), (3, a), (None, a), (None, "c d e f g h"), (5, b), (5, b)]
    for parts in (1, 3, 7):
        docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(parts)
        got = list((-1 if r.doc_id is None else r.doc_id, r.n_shingles, r.component_id) for r in J.joined(docs).collect())
        assert sorted(got, key=str) == sorted([(0, 56, 0), (2, 56, 2), (2, 57, 0), (3, 56, 2), (-1, 56, 2), (-1, 2, None), (5, 56, 0), (5, 56, 0)], key=str)
        kept = sorted(map(tuple, J.one_of_each(docs).collect()), key=str)
        assert kept == sorted([(0, b), (2, a), (None, "c d e f g h")], key=str)


def test_whole_table(spark):
    """On the given documents, both as the query takes them and as the pipeline does."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    rows = [tuple(r) for r in docs.collect()]
    for spec in (J.JoinSpec(3, 90), J.JoinSpec()):
        assert {r.doc_id: (r.n_shingles, r.component_id) for r in J.joined(docs, spec).collect()} == brute(rows, spec)


@pytest.mark.parametrize("small, crowded, frequent", [(4, 30, 16), (32, 4096, 1 << 30)])
def test_group_of_near_copies(spark, monkeypatch, small, crowded, frequent):
    """Copies of one text with random edits, some below the threshold with all others, beside texts that share a passage with them."""
    for name, value in (("SMALL", small), ("CROWDED", crowded), ("FREQUENT", frequent)):
        monkeypatch.setattr(J, name, value)
    random.seed(8)
    base, rows = [f"w{i}" for i in range(80)], []
    for i in range(60):
        t = list(base)
        for _ in range(random.choice([0, 1, 1, 2, 3, 4])):
            t[random.randrange(80)] = f"x{i}"
        rows.append((i, " ".join(t)))
    rows += [(1000 + i, " ".join(base[:12] + [f"y{i}.{j}" for j in range(random.randint(20, 60))])) for i in range(12)]
    spec = J.JoinSpec(3, 80)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in J.joined(spark.createDataFrame(rows, "doc_id long, text string").repartition(5), spec).collect()}
    assert got == brute(rows, spec)


def test_rows_grow_with_a_group_not_its_pairs(spark, monkeypatch):
    """A group of texts that the bound can't tell from near copies, nearly all below the threshold with each other."""
    random.seed(5)
    base, rows = [f"w{i}" for i in range(600)], []
    for i in range(150):
        t = list(base)
        for j in range(8):
            t[75 * j + random.randrange(70)] = f"x{i}"
        rows.append((i, " ".join(t)))
    made, written = {}, J.written

    def counted(df, tag):
        out = written(df, tag)
        made[tag] = out.count()
        return out

    monkeypatch.setattr(J, "written", counted)
    monkeypatch.setattr(J, "SMALL", 8)
    for limit in (J.TILE_SHINGLES, 20_000):  # as a whole, and as fragments
        monkeypatch.setattr(J, "TILE_SHINGLES", limit)
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in J.joined(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()}
        assert got == brute(rows, J.JoinSpec()) and len({c for _, c in got.values()}) > 1
        assert made["join-found"] < 10 * len(rows) and made["join-rest-tiles"]


def test_odd_rows(spark, odd, none):
    got = J.joined(odd).collect()
    assert len(got) == odd.count()
    assert {r.component_id for r in got if r.doc_id == 1} == {1} and {r.n_shingles for r in got if r.doc_id in (2, 3, 4)} == {0}
    kept = J.one_of_each(odd)
    assert kept.columns == odd.columns and kept.count() == odd.count() - 1  # a repeated row goes
    assert J.joined(none).count() == 0
