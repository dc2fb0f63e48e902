import hashlib
import random
import time

import numpy as np

from carepath.llm import suffixes as S


def brute(rows, length=50):
    first = {}
    for i, t in rows:
        b = (t or "").encode()
        for s in range(len(b) - length + 1) if i is not None else ():
            first[b[s : s + length]] = min(i, first.get(b[s : s + length], i))
    out = []
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for s in range(len(b) - length + 1) if i is not None else ():
            if first[b[s : s + length]] < i:
                gone[s : s + length] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((-1 if i is None else i, len(b), int(gone.sum()), runs, hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()))
    return sorted(out)


def test_suffix_order():
    random.seed(2)
    for _ in range(40):
        text = np.array([random.choice([1, 2]) if random.random() < 0.95 else 3 for _ in range(random.randint(1, 250))] * 2, np.uint8)
        at = np.array(sorted(random.sample(range(len(text)), len(text) // 2)))
        data = text.tobytes() + bytes(200)
        keys = [data[i : i + 50] for i in S.suffix_order(text, at, 50)]
        assert keys == sorted(keys)
    cover = set(S.difference_cover(32))
    assert {(a - b) % 32 for a in cover for b in cover} == set(range(32))


def test_against_brute_force(spark):
    random.seed(5)
    base = ["".join(random.choice("abé ") for _ in range(random.choice([40, 50, 60, 200, 2000]))) for _ in range(20)]
    piece = lambda: random.choice(base)[(a := random.randint(0, 150)) : a + random.randint(30, 120)] if random.random() < 0.7 else "xy" * random.randint(1, 60)
    rows = [(random.randint(0, 150), "".join(piece() for _ in range(random.randint(0, 6)))) for _ in range(150)]
    rows += [(None, base[0]), (None, None), (500, None), (501, ""), (502, base[4]), (503, base[4]), (503, base[4]), (504, "a" * 3000), (505, "a" * 5000)]
    got = S.deduplicated(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    assert sorted((-1 if r.doc_id is None else r.doc_id, *r[1:]) for r in got) == brute(rows)


def test_odd_rows(spark, odd, none):
    got = S.deduplicated(odd, keep_text=True).collect()
    assert len(got) == odd.count() and all(r.n_removed == 0 for r in got)
    assert S.deduplicated(none).count() == 0


def test_buckets_follow_the_size_of_the_texts(spark, monkeypatch):
    """What a worker unpacks at once doesn't grow with the table; the rows are the same."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").limit(150)
    want = sorted(map(tuple, S.deduplicated(docs).collect()))
    asked, anchors = [], S._anchors
    monkeypatch.setattr(S, "_anchors", lambda texts, spec, buckets: asked.append(buckets) or anchors(texts, spec, buckets))
    monkeypatch.setattr(S, "BUCKET_BYTES", 1000)
    assert sorted(map(tuple, S.deduplicated(docs).collect())) == want
    assert asked[0] >= sum(r[1] for r in want) // 1000 > 2 * int(spark.conf.get("spark.sql.shuffle.partitions"))


def test_ties_of_several_residues_are_compared_at_once():
    """Order as far as the depth, for texts that repeat at every offset."""
    rng = np.random.default_rng(4)
    base = rng.integers(97, 100, 300).astype(np.uint8)
    text = np.concatenate([np.concatenate([rng.integers(97, 123, int(rng.integers(1, 40))).astype(np.uint8), base]) for _ in range(400)])
    at = np.arange(len(text) - 50)
    began = time.process_time()
    order = S.suffix_order(text, at, 50)
    assert time.process_time() - began < 3
    strings = [text[i : i + 50].tobytes() for i in order]
    assert sorted(order.tolist()) == at.tolist() and all(a <= b for a, b in zip(strings[:-1], strings[1:], strict=True))
