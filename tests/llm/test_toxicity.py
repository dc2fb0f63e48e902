import random

import numpy as np

from carepath.llm import toxicity as T


def corpus(n, seed):
    r = random.Random(seed)
    rows = []
    for i in range(n):
        words = ["w" + str(r.randint(0, 3000)) for _ in range(r.randint(5, 120))]
        y = int(r.random() < 0.2)
        for _ in range(3 * y):
            words.insert(r.randrange(len(words)), r.choice(["scoundrel", "villain", "rogue"]) + r.choice(["", "s", "ish"]))
        rows.append((i, " ".join(words), y, r.choice(["en", "fr"])))
    return rows


def test_gradients():
    spec = T.TrainSpec(buckets=64, width=3, filters=2)
    w = {k: v.astype(np.float64) for k, v in T.initial(spec).items()}
    rng = np.random.default_rng(0)
    w["embed"][:-1] = rng.normal(size=w["embed"][:-1].shape)
    for k in spec.widths:  # away from the kink that an empty text sits on
        w[f"bias{k}"] += 0.1
    lay, y = T.layout(T._as_block(["a b c d", "e", "", "a d e f g"]), spec), np.array([1.0, 0, 1, 0])
    _, g = T.gradients(w, spec, lay, y)
    for k in w:
        for at in zip(*(rng.integers(0, n, 4) for n in w[k].shape), strict=True):
            if k == "embed" and at[0] == len(w[k]) - 1:
                continue
            old, values = w[k][at], []
            for e in (1e-5, -1e-5):
                w[k][at] = old + e
                values.append(T.gradients(w, spec, lay, y)[0])
            w[k][at] = old
            assert abs((values[0] - values[1]) / 2e-5 - g[k][at]) < 1e-4


def test_held_out_accuracy(spark):
    rows = corpus(1200, 1)
    docs = spark.createDataFrame([(i, t, lang) for i, t, _, lang in rows], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, y) for i, _, y, _ in rows], "doc_id long, toxic int")
    model = T.fit(docs, labels)
    got = {r.doc_id: r.score for r in T.scored(docs, model).join(docs.filter(T.remainder(docs.doc_id) == 2), "doc_id", "left_semi").collect()}
    truth = {i: y for i, _, y, _ in rows}
    hits = sum((s >= 0.3) == (truth[i] == 1) for i, s in got.items())
    assert len(got) > 200 and hits / len(got) > 0.95


def test_odd_rows(spark, odd, none):
    labels = spark.createDataFrame([(1, 1, 0), (2, None, 0), (None, 1, 1)], "doc_id long, toxic int, quality int")
    model = T.fit(odd, labels)
    got = T.scored(odd, model, tuple(odd.columns)).collect()
    assert len(got) == odd.count() and all(0 <= r.score <= 1 for r in got) and "score_in" in got[0].asDict()
    assert T.scored(none, model).count() == 0


def test_every_labelled_row_is_learned_from(spark):
    """No label is left out however many rows it has; blocks, models and thresholds do not depend on how rows were dealt."""
    from dataclasses import replace

    rows = corpus(700, 2)
    docs = spark.createDataFrame([(i, t, lang) for i, t, _, lang in rows], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, y) for i, _, y, _ in rows], "doc_id long, toxic int")
    spec = replace(T.TrainSpec(), buckets=1 << 10, block_rows=200, epochs=2)
    usable = {r.doc_id: r.toxic for r in labels.filter(T.remainder(labels.doc_id) != 2).collect()}
    used = T.examples(docs, labels.filter(T.remainder(labels.doc_id) != 2).withColumnRenamed("toxic", "_y"), 3, spec).collect()
    assert len(used) == len(usable) > 450 and sum(r.y for r in used) == sum(usable.values())
    texts = {i: t for i, t, _, _ in rows}
    words = lambda t: T.tokens(T._as_block([t]), spec).ids.tolist()
    assert sorted(r.ids for r in used) == sorted(words(texts[i]) for i in usable)
    one, other = T.fit(docs, labels, spec=spec), T.fit(docs.repartition(7), labels.repartition(3), spec=spec)
    assert all(np.allclose(one.weights[k], other.weights[k], atol=1e-5) for k in one.weights) and abs(one.shift - other.shift) < 1e-3
    taken = []
    t = T.tokens(T._as_block([texts[i] for i in range(50)]), spec)
    old = T.laid
    T.laid = lambda t, at, s: taken.extend(at.tolist()) or old(t, at, s)
    try:
        T.gone_through(T.initial(spec), t, np.array([r[2] for r in rows[:50]]), np.arange(50), 2, np.random.default_rng(0), spec)
    finally:
        T.laid = old
    assert sorted(taken) == sorted([*range(50)] * 2)
