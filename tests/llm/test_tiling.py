import random

from carepath.llm import tiling as G
from carepath.llm.queries import op10_greedy_tiling


def brute(a, b, least):
    free_a, free_b, out = [1] * len(a), [1] * len(b), []
    while True:
        best = (0, 0, 0)
        for i in range(len(a)):
            for j in range(len(b)):
                k = 0
                while i + k < len(a) and j + k < len(b) and free_a[i + k] and free_b[j + k] and a[i + k] == b[j + k]:
                    k += 1
                best = max(best, (k, i, j), key=lambda m: (m[0], -m[1], -m[2]))
        k, i, j = best
        if k < least:
            return sorted(out)
        free_a[i : i + k] = free_b[j : j + k] = [0] * k
        out.append((i, j, k))


def test_tiles_against_brute_force():
    random.seed(2)
    for _ in range(150):
        a, b = ([random.randint(1, 6) for _ in range(random.randint(0, n))] for n in (40, 60))
        if random.random() < 0.5 and len(a) > 10:
            b = b[:5] + a[8:] + b[5:9] + a[:8]
        assert sorted(G.greedy_tiles(a, b, G.TileSpec(least=3, search=8))) == brute(a, b, 3)


def test_reordered_passage_is_found(spark):
    words = [f"w{i}" for i in range(40)]
    docs = spark.createDataFrame([(1, " ".join(["x", "y"] + words[20:] + ["z"] * 5 + words[:20])), (2, " ".join(words[:25])), (3, " ".join(words).upper() + "!"), (4, None), (5, "")], "doc_id long, text string")
    bench = spark.createDataFrame([(7, " ".join(words)), (8, "too short"), (9, None)], "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.n_tiles, r.coverage) for r in G.tiled(docs, bench).collect()}
    assert got == {(1, 7): (2, 1.0), (3, 7): (1, 1.0)}
    assert {r.doc_id for r in G.without_benchmark(docs, bench).collect()} == {2, 4, 5}
    more = docs.unionByName(spark.createDataFrame([(None, " ".join(words)), (None, "clean"), (1, "another text of the id")], docs.schema))
    assert sorted(map(str, (r.text for r in G.without_benchmark(more, bench).collect()))) == sorted(["", "None", "another text of the id", "clean", " ".join(words[:25])])


def test_whole_table_against_brute_force(spark):
    import re

    sf = "/root/testdata/sf0.001"
    token = lambda t: re.findall(r"[a-z0-9\x80-\U0010ffff]+", (t or "").translate(str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})))
    docs, bench = (spark.read.parquet(f"{sf}/{t}.parquet").collect() for t in ("documents", "benchmark"))
    want = set()
    for b in bench:
        item = token(b.text)
        seeds = {tuple(item[i : i + 5]) for i in range(len(item) - 4)}
        for doc in docs:
            words = token(doc.text)
            near = [i for i in range(len(words) - 4) if tuple(words[i : i + 5]) in seeds]
            if near:
                part = words[max(0, near[0] - 5) : near[-1] + 10]
                if sum(t[2] for t in brute(item, part, 5)) >= 0.8 * len(item):
                    want.add((doc.doc_id, b.item_id))
    assert {(r.doc_id, r.item_id) for r in op10_greedy_tiling(spark, sf).collect()} == want


def test_odd_rows(spark, odd, none):
    bench = spark.createDataFrame([(1, "the token abcdef123456 and more words", 5)], "item_id long, text string, doc_id int")
    assert {r.doc_id for r in G.tiled(odd, bench).collect()} == {1}
    assert G.tiled(none, bench).count() == 0 and G.tiled(odd, bench.limit(0)).count() == 0
    assert G.without_benchmark(odd, bench).columns == odd.columns
