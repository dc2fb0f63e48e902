from dataclasses import replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pytest

from carepath.models import encoders
from carepath.models import layers as L
from carepath.models import train as TR
from carepath.models.nets import Batch, EndToEnd, FeatureSpec, TrajectoryModel, VisitModel
from carepath.plans import experiments as X
from carepath.plans import presets

RNG = np.random.default_rng(1)


def check_gradient(model, batch, places=40):
    model.loss(batch)
    g, w = model.gradient(), model.get()
    for i in RNG.choice(len(w), min(places, len(w)), replace=False):
        values = []
        for e in (1e-5, -1e-5):
            v = w.copy()
            v[i] += e
            model.set(v)
            values.append(model.loss(batch))
        assert g[i] == pytest.approx((values[0] - values[1]) / 2e-5, rel=1e-3, abs=1e-7)
    model.set(w)


def visit_model(head="sigmoid"):
    spec = FeatureSpec(text=True, stay=True, gap=True, dx=True)
    return VisitModel(spec, 3, {"dx": RNG.normal(size=(6, 4))}, {"dx": 2}, d=4, temporal_width=3, dropout=0.0, head=head)


def visit_batch(n=8):
    return Batch({"text": RNG.normal(size=(n, 4)), "stay": RNG.random(n), "gap": RNG.random(n), "dx": RNG.integers(0, 6, (n, 2))}, RNG.integers(0, 2, (n, 3)).astype(float))


@pytest.mark.parametrize("head", ["sigmoid", "softmax"])
def test_visit_model_gradient(head):
    check_gradient(visit_model(head), visit_batch())


@pytest.mark.parametrize("cell", ["gru", "lstm", "minimal_gru"])
@pytest.mark.parametrize("both", [False, True])
def test_trajectory_gradient(cell, both):
    mask = np.array([[0, 1, 1], [1, 1, 1], [0, 0, 1], [1, 1, 1]], float)
    batch = Batch({"window": RNG.normal(size=(4, 3, 5))}, RNG.integers(0, 2, (4, 2)).astype(float), mask)
    check_gradient(TrajectoryModel(5, 2, cell, 3, 2, both, dropout=0.0), batch)


def test_end_to_end_gradient():
    visit = visit_model()
    model = EndToEnd(visit, TrajectoryModel(visit.spec.width(4, 3), 2, "gru", 3, dropout=0.0))
    b = {"text": RNG.normal(size=(3, 2, 4)), "stay": RNG.random((3, 2)), "gap": RNG.random((3, 2)), "dx": RNG.integers(0, 6, (3, 2, 2))}
    check_gradient(model, Batch(b, RNG.integers(0, 2, (3, 2)).astype(float), np.ones((3, 2))))


def test_masked_steps_keep_the_state():
    m = TrajectoryModel(4, 2, "gru", 3, dropout=0.0)
    x = RNG.normal(size=(1, 2, 4))
    short = m.logits(Batch({"window": x}, np.zeros((1, 2)), np.ones((1, 2))))
    padded = m.logits(Batch({"window": np.concatenate([np.full((1, 3, 4), 9.0), x], axis=1)}, np.zeros((1, 2)), np.array([[0, 0, 0, 1, 1]], float)))
    assert np.allclose(short, padded)


def test_stable_activations():
    big = np.array([[1000.0, -1000.0, 0.0]])
    assert np.allclose(L.sigmoid(big), [[1, 0, 0.5]]) and np.allclose(L.softmax(big), [[1, 0, 0]])
    assert np.isfinite(L.bce(big, np.array([[0.0, 1.0, 1.0]]))[0])


def test_widths():
    assert FeatureSpec.of("dx+gap").width(768, 50) == 818
    with pytest.raises(ValueError):
        FeatureSpec()


def planted(n, lag):
    """Windows of one-hot codes; the label is the code ``lag`` steps before the last."""
    codes = RNG.integers(0, 5, (n, 3))
    return Batch({"window": np.eye(5)[codes]}, np.eye(5)[codes[:, 2 - lag]], np.ones((n, 3)))


@pytest.mark.parametrize("lag", [0, 1])
def test_windows_learn_what_was_planted(lag):
    m = TrajectoryModel(5, 5, "gru", 16, dropout=0.0)
    TR.fit_batches(m, planted(1500, lag), planted(200, lag), TR.TrainSpec(epochs=25, rate=1e-2, patience=10_000))
    test = planted(300, lag)
    assert (m.probabilities(test).argmax(axis=1) == test.y.argmax(axis=1)).mean() > 0.95


def test_early_stop_keeps_the_best():
    stop = TR.EarlyStop(10)
    stop.seen(1, 0.5, np.array([1.0]))
    stop.seen(5, 0.7, np.array([2.0]))
    assert stop.weights[0] == 1.0 and not stop.over(10) and stop.over(11)


def frame(spark, n=120):
    rng = np.random.default_rng(0)
    gap = rng.random(n)
    return spark.createDataFrame([(i, float(g), [0] if g > 0.5 else []) for i, g in enumerate(gap)], "sample_id long, gap double, y array<int>")


def test_summed_gradients_do_not_depend_on_partitions(spark):
    build, got = X.as_batch(("gap",), 1, 0), []
    for parts in (1, 3, 20):  # 20 are summed in tasks before they reach the driver
        m = VisitModel(FeatureSpec(gap=True), 1, d=4, temporal_width=4, dropout=0.0)
        df = frame(spark).repartition(parts)
        TR.fit(m, df, df, build, TR.TrainSpec(batch=60, epochs=2, mode="sync"))
        got.append(m.get())
    assert np.allclose(got[0], got[1], atol=1e-6) and np.allclose(got[0], got[2], atol=1e-6)


def test_averaged_training_learns(spark):
    build = X.as_batch(("gap",), 1, 0)
    m = VisitModel(FeatureSpec(gap=True), 1, d=4, temporal_width=8, dropout=0.0)
    df = frame(spark, 300).repartition(2)
    TR.fit(m, df, df, build, TR.TrainSpec(epochs=6, rate=2e-2, mode="local", local_steps=40))
    scores = TR.score(m, df, build).collect()
    assert sum((r.p >= 0.5) == (r.y == 1) for r in scores) > 280


def test_driver_mode_has_a_cap(spark):
    with pytest.raises(ValueError):
        TR.collected(frame(spark), X.as_batch(("gap",), 1, 0), 50)


def test_batches_of_sparse_labels():
    t = pa.table({"gap": [0.5, 1.0], "y": pa.array([[2, 4], []], pa.list_(pa.int32()))})
    b = X.as_batch(("gap",), 3, 2)(t)
    assert b.y.tolist() == [[1, 0, 1], [0, 0, 0]]


def test_presets_cover_the_tables():
    assert [len(x) for x in (presets.initial_tuned(), presets.initial_frozen(), presets.final_return(), presets.next_codes("grp"), presets.on_vectors(), presets.on_multi_hot())] == [5, 6, 8, 9, 9, 7]
    assert len(presets.grid(X.Config("g"), cell=["gru", "lstm"], layers=[1, 2, 3])) == 6


def test_prefix_samples_lose_no_visits(spark, monkeypatch):
    """What the sequence comparator trains on and scores has every visit of every prefix."""
    visits = [(1, i, i) for i in range(31)] + [(2, 100 + i, i) for i in range(4)]
    enc = spark.createDataFrame(visits, "subject_id long, visit_id long, day int")
    enc = enc.selectExpr("subject_id", "visit_id", "timestamp_ntz'2020-01-01' + make_interval(0, 0, 0, day) AS admit_ts", "0 AS y_return")
    prep = X.Prepared(spark, "")
    prep._made = {
        ("encounters",): enc, ("codes", "D", "grp"): enc.selectExpr("visit_id", "array('a') AS codes"),
        ("vocabulary", "D", "grp"): spark.createDataFrame([("a", X.C.FIRST_ID)], "code string, id int"),
        ("ids", "D", "grp"): enc.selectExpr("visit_id", f"array({X.C.FIRST_ID}) AS ids"),
        ("folds", "holdout", None): enc.selectExpr("visit_id", "0 AS run", "'test' AS role"),
    }
    seen = []
    monkeypatch.setattr(X, "trained", lambda cfg, model, rows, build, scaled: seen.append(build(rows.orderBy("sample_id").toArrow())))
    X.sequence_models(prep, presets.sequence_comparator())
    lengths = [*range(1, 31), 1, 2, 3]
    assert seen[0].mask.sum(axis=1).tolist() == lengths
    assert seen[0].x["window"].sum(axis=(1, 2)).tolist() == lengths and seen[0].mask.shape == (33, 30)


def test_no_patient_crosses_from_encoder_to_sequence_test(spark):
    """One fold table for both stages: no test patient of the sequence model was in another part of its visit encoder."""
    scale = X.Scale(d=4, epochs=1, rotations=(0, 7))
    prep = X.Prepared(spark, "/root/testdata/sf0.001")
    for cfg in (presets.on_vectors(scale)[4], presets.return_on_sequences(scale)[0]):
        t = X.sequence_models(prep, cfg)
        assert X.audited(prep, cfg, t).count() == 0
        parts = X.visit_vectors(prep, cfg)[2].withColumnRenamed("role", "below")
        crossed = t.rows.join(parts, ["rotation", "subject_id"]).filter("role = 'test' AND below <> 'test'")
        assert parts.filter("below = 'train'").count() > 50 and crossed.count() == 0
    by_visit = X.Config("by visit", features="gap", folds="visit", scale=scale)
    t = X.visit_models(prep, by_visit)
    assert X.audited(prep, by_visit, t).count() == 2  # the flawed split shows


def test_grouped_training_equals_the_driver(spark):
    """A rotation trained in a task gives the weights and scores of the same rows trained on the driver."""
    rows = frame(spark).selectExpr("*", "2 AS rotation", "CASE sample_id % 4 WHEN 0 THEN 'test' WHEN 1 THEN 'validation' ELSE 'train' END AS role")
    spec, build = TR.TrainSpec(epochs=3, eval_every=4), X.as_batch(("gap",), 1, 0)
    model = VisitModel(FeatureSpec(gap=True), 1, d=4, temporal_width=4, dropout=0.0)
    made = TR.fit_groups(model, rows.repartition(3), build, spec).collect()
    table = rows.toArrow().sort_by("sample_id")
    part = lambda r: build(table.filter(pc.equal(table.column("role"), r)))
    TR.fit_batches(model, part("train"), part("validation"), spec)
    told = [r for r in made if r.sample_id is None]
    assert len(told) == 1 and told[0].rotation == 2 and np.allclose(np.frombuffer(told[0].weights), model.get())
    scores = sorted((r.sample_id, r.p) for r in made if r.sample_id is not None)
    assert np.allclose([p for _, p in scores], model.probabilities(part("test")).ravel())


def test_tuned_weights_beyond_the_limit_are_joined(spark, monkeypatch):
    """No word loses its weight: what is joined gives the vectors of what is broadcast."""
    rng = np.random.default_rng(3)
    rows = [(i, i % 2, " ".join([f"w{v}" for v in rng.integers(0, 60, 30)] + [f"y{i % 2}"])) for i in range(80)] + [(80, 0, ""), (81, 1, "w1  w1 unseen")]
    texts = spark.createDataFrame(rows, "visit_id long, y int, text string")
    vectors = lambda e: {r.visit_id: r.vec for r in encoders.encode_text(texts, e, ("visit_id",)).collect()}
    want = vectors(encoders.label_tuned(texts, "y", 16))
    monkeypatch.setattr(encoders, "TUNED_WORDS", 10)
    got = vectors(encoders.label_tuned(texts, "y", 16))
    assert set(got) == set(want) == set(range(82))
    assert all(np.allclose(got[i], want[i], atol=1e-5) for i in want)


def test_results_tables_are_registered_whole(monkeypatch):
    from carepath.queries import modelling as M
    from carepath.queries._registry import QUERIES

    names = lambda configs: [c.name for c in configs]
    assert names(M.TABLES["w_tab_d"]) == names(presets.next_codes("parent")) and names(M.TABLES["w_tab_m"]) == names(presets.on_multi_hot())
    assert names(M.TABLES["w_tab_s"]) == names(M.TABLES["m_trajectory_eval"]) == names(presets.on_vectors())
    turns = {"visit5": 5, "holdout": 3, "labels": 3}
    assert all(c.scale.rotations == tuple(range(turns.get(c.folds, 10))) for configs in M.TABLES.values() for c in configs)
    monkeypatch.setattr(M.X, "run_all", lambda s, d, configs: configs)
    sweep = QUERIES["w_width_sweep"](None, "")
    assert [c.scale.temporal_width for c in sweep] == [1, 2, 5, 10, 20, 50, 100, 200, 500] and all(c.scale.rotations == tuple(range(10)) for c in sweep)


def test_parts_are_the_roles_of_every_rotation(spark):
    """Rows once with their parts tell what a copy of each row for every rotation told, balanced ones too."""
    prep = X.Prepared(spark, "/root/testdata/sf0.001")
    for settings in ({}, {"balance": None}, {"folds": "visit5", "balance": "once"}, {"folds": "holdout", "balance": None}, {"folds": "labels", "balance": None, "task": "codes", "target": "current"}):
        cfg = X.Config("c", **settings)
        cfg = replace(cfg, scale=X.Scale(rotations=tuple(range(X.turns(cfg)))[1:]))
        base = X.visits(prep, cfg)[0]
        base = X.folds.balance_once(base) if cfg.balance == "once" else base
        key = ["rotation", "role", "visit_id"]
        want = X.balanced(X.roles(base, prep, cfg), cfg).select(*key).collect()
        got = X.unfolded(X.parted(base, prep, cfg), cfg.scale.rotations).select(*key).collect()
        assert len(want) > 20 and sorted(got) == sorted(want)


def test_measures_of_arrays_are_those_of_cells(spark):
    from carepath.measures import metrics

    rng = np.random.default_rng(1)
    rows = [(r, i, sorted({int(c) for c in rng.integers(0, 7, rng.integers(0, 4))}), [round(float(v), 2) for v in rng.random(7)]) for r in (2, 5) for i in range(150)]
    rows += [(8, 1, [], [0.5] * 7), (9, 1, [3], [0.0] * 6 + [1.0])]
    arrays = spark.createDataFrame(rows, "rotation int, sample_id long, y array<int>, p array<double>").repartition(3)
    cells = arrays.selectExpr("rotation", "sample_id", "posexplode(p) AS (class_id, p)", "y AS t").selectExpr("rotation", "sample_id", "class_id", "p", "CAST(array_contains(t, class_id) AS int) AS y")
    for task in ("binary", "multilabel"):
        want = {r.rotation: r.asDict() for r in metrics.suite(cells, task, (1, 3), per=["rotation"]).collect()}
        got = {r.rotation: r.asDict() for r in metrics.suite_arrays(arrays, task, (1, 3)).collect()}
        assert got.keys() == want.keys()
        for r, measures in want.items():
            assert list(got[r]) == list(measures) and all(got[r][k] == pytest.approx(v, abs=1e-12) for k, v in measures.items())


def test_tuned_encoders_of_all_rotations_are_those_of_each(spark, monkeypatch):
    rng = np.random.default_rng(4)
    rows = [(i, i % 2, i % 3 - 1, " ".join([f"w{v}" for v in rng.integers(0, 50, 25)] + [f"y{i % 2}"])) for i in range(90)] + [(90, 0, 0, ""), (91, 1, 1, "w1  w1 unseen")]
    texts = spark.createDataFrame(rows, "visit_id long, y int, part int, text string")
    cases = [X.F.col("part") == 0, X.F.col("part") >= 0, X.F.col("part") > 5]
    for most in (64 << 20, 10):
        monkeypatch.setattr(encoders, "TUNED_BYTES", most)
        tuned = encoders.label_tuned_each(texts, "y", cases, 8)
        assert (tuned.table is None) == (most > 10)
        got = {r.visit_id: np.array(r.vec).reshape(3, 8) for r in encoders.encode_each(texts, tuned, ("visit_id",)).collect()}
        for i, case in enumerate(cases):
            want = encoders.encode_text(texts, encoders.label_tuned(texts.filter(case), "y", 8), ("visit_id",)).collect()
            assert len(want) == len(got) == 92 and all(np.allclose(got[r.visit_id][i], r.vec, atol=1e-5) for r in want)


def test_samples_stay_short_until_they_are_taken():
    """A long history or many classes cost room for the rows of a mini-batch only, and a held-out loss runs no backward pass."""
    n = 300
    table = pa.table({"steps": pa.array([[[2, 3]] * (1 + i % 40) for i in range(n)], pa.list_(pa.list_(pa.int32()))), "mask": [[True] * (1 + i % 40) for i in range(n)], "y": pa.array([[2]] * n, pa.list_(pa.int32()))})
    held = X.Windows(4000, 2, 4000, None, "ids", 2).hold(table)
    batch = held.take(np.array([0, 2]))
    assert batch.x["window"].shape == (2, 3, 4000) and batch.y.shape == (2, 4000) and batch.x["window"].sum() == 8
    outer, on, given, number, visits = held.x
    assert sum(a.nbytes for a in (outer.at, on.at, on.flat, given, number, visits.at, visits.flat)) < 1_000_000  # dense: 384 MB
    m = TrajectoryModel(4000, 4000, "gru", 2)
    m.backward = None
    assert TR.mean_loss(m, held.only(np.arange(4))) > 0


def test_rotations_beyond_a_task_are_trained_in_the_same_jobs(spark):
    """All rotations in a few jobs, with the scores of every test row; before, each rotation had jobs of its own."""
    rows = frame(spark, 300).selectExpr("*", "array(CAST(sample_id % 3 AS tinyint), CAST((sample_id + 1) % 3 AS tinyint)) AS parts").repartition(20)
    build, turns = X.as_batch(("gap",), 1, 0), [X.Turn({"gap": (0.0, 1.0)}), X.Turn({"gap": (0.0, 0.5)})]
    m = VisitModel(FeatureSpec(gap=True), 1, d=4, temporal_width=8, dropout=0.0)
    spark.sparkContext.setJobGroup("turns", "")
    weights, fitted = TR.fit_turns(m, rows, build, TR.TrainSpec(epochs=4, rate=2e-2, local_steps=30), turns)
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("turns"))
    spark.sparkContext.setJobGroup("", "")
    assert jobs < 60 and [f.steps for f in fitted] == [120, 120] and not np.allclose(*weights)
    scores = TR.score_turns(m, rows, build, turns, (4, 7), weights).collect()
    assert sorted((r.rotation, r.sample_id) for r in scores) == sorted([(4, i) for i in range(2, 300, 3)] + [(7, i) for i in range(1, 300, 3)])
    right = sum((r.p[0] >= 0.5) == bool(r.y) for r in scores if r.rotation == 4)
    assert right > 85


def test_scoring_vectors_are_those_of_training():
    """Codes normed by the table and times by their different values give what each row by itself gives."""
    rng = np.random.default_rng(5)
    m = VisitModel(FeatureSpec.of("dx+gap+text"), 3, {"dx": rng.normal(size=(9, 4))}, {"dx": 5}, 4, 6, dropout=0.3)
    b = Batch({"dx": rng.integers(0, 9, (40, 5)), "gap": rng.integers(0, 4, 40) / 4, "text": rng.normal(size=(40, 4))}, np.zeros((40, 3)))
    assert np.allclose(m.scored_vector(b), m.visit_vector(b)) and np.allclose(m.scored_logits(b), m.logits(b))
    assert m.value(b) == pytest.approx(m.loss(b))


def test_held_rows_are_bounded():
    """What a task holds, and makes dense where nothing is learned, does not grow with its rows; losses and scores stay."""
    from carepath.models import packed

    rng = np.random.default_rng(3)
    sizes = rng.integers(1, 40, 3000)
    steps = [[rng.integers(1, 51, 3).tolist() for _ in range(n)] for n in sizes]
    table = pa.table({"steps": pa.array(steps, pa.list_(pa.list_(pa.int32()))), "mask": [[True] * n for n in sizes], "y": pa.array([s[-1] for s in steps], pa.list_(pa.int32()))})
    made = []

    class Seen(packed.Windows):
        def dense(self, x, at, turn):
            out = super().dense(x, at, turn)
            made.append(out[0]["window"].size)
            return out

    rows = Seen(50, 1, 50, None, "ids", 1).hold(table)
    m = TrajectoryModel(50, 50, "minimal_gru", 4, bidirectional=True, head="softmax")
    whole = m.value(rows.take(np.arange(len(rows))))
    assert made.pop() > packed.DENSE_CELLS
    assert abs(TR.mean_loss(m, packed.by_length(rows)) - whole) < 1e-9
    got = np.concatenate([p for _, _, p in TR.scored(m, packed.by_length(rows))])
    assert max(made) <= packed.DENSE_CELLS
    order = packed.by_length(rows).rows
    assert np.allclose(got[np.argsort(order)][:50], m.probabilities(rows.take(np.arange(50))))
    parts = list(TR.slices(iter(table.to_batches(max_chunksize=100)), 1 << 16))
    assert pa.concat_tables(parts).equals(table) and max(sum(b.nbytes for b in p.to_batches()) for p in parts) <= 1 << 16 and len(parts) > 1


def test_training_knows_no_size_and_no_partitions(spark, monkeypatch):
    """The same weights whatever a task was said to hold and however rows were dealt; every block takes each of its training rows once an epoch."""
    enc = frame(spark, 300).selectExpr("*", "array(CAST(sample_id % 3 AS tinyint)) AS parts", "sample_id AS subject_id")
    build = X.as_batch(("gap",), 1, 0)
    monkeypatch.setattr(TR, "BLOCK_ROWS", 100)
    got = []
    for most, dealt in ((200_000, 1), (5, 1), (5, 7)):
        m = VisitModel(FeatureSpec(gap=True), 1, d=4, temporal_width=8, dropout=0.0)
        rows = X.written(TR.in_blocks(enc.repartition(dealt)))
        monkeypatch.setattr(X, "spec_of", lambda cfg, most=most: TR.TrainSpec(batch=8, epochs=3, rate=2e-2, driver_rows=most))
        t = X.trained(X.Config("c", features="gap", scale=X.Scale(rotations=(0,))), m, rows, build, ["gap"])
        got.append((t.told.first(), sorted((r.sample_id, r.p) for r in t.scores.collect())))
    assert [len(s) for _, s in got] == [100] * 3 and got[0][0].train_rows == 100 and got[0][0].steps == 3 * -(-100 // (8 * 3))
    for told, scores in got[1:]:
        assert np.allclose(np.frombuffer(told.weights), np.frombuffer(got[0][0].weights)) and np.allclose(scores, got[0][1])
    taken = []
    monkeypatch.setattr(X.Visits, "dense", lambda self, x, at, turn, old=X.Visits.dense: taken.extend(x["gap"][at]) or old(self, x, at, turn))
    table = rows.filter("block = 1").toArrow()
    collected = lambda df, b, turns, model, weights, part, work: [(*work(model, b.hold(table), 0), len(table))]
    monkeypatch.setattr(TR, "_by_turn", collected)
    TR.fit_turns(m, rows, build, TR.TrainSpec(batch=8, epochs=1), [X.Turn()], blocks=3)
    assert len(table) > 30 and sorted(taken) == sorted(2 * table.column("gap").to_pylist())  # in training, and in the held-out pass of this stand-in


def test_blocks_of_a_task_are_kept_apart():
    batches = pa.table({"block": [4, 4, 4, 7, 7, 9], "i": range(6)}).to_batches(max_chunksize=2)
    assert [t.column("i").to_pylist() for t in TR.by_block(iter(batches))] == [[0, 1, 2], [3, 4], [5]]


def test_vectors_made_once_are_those_of_each_batch():
    rng = np.random.default_rng(2)
    visit = VisitModel(FeatureSpec.of("dx+gap"), 3, {"dx": rng.normal(size=(9, 4))}, {"dx": 2}, 4, 6)
    steps = [[None if i % 5 == 0 else {"visit_id": i - 1, "dx": [i % 9, 3], "gap": 1.0 * i}, {"visit_id": i, "dx": [(i + 1) % 9, 3], "gap": 1.0 * (i + 1)}] for i in range(40)]
    table = pa.table({"steps": steps, "mask": [[s[0] is not None, True] for s in steps], "y": pa.array([[1]] * 40, pa.list_(pa.int32()))})
    held = X.Windows(3, 0, visit.spec.width(4, 6), 2, visit.spec.names).hold(table).turned(X.Turn({"gap": (0.0, 40.0)}, below=X.pickle.dumps(visit)))
    at = np.array([3, 0, 17, 39])
    want, got = held.take(at), TR.made_once(held).take(at)
    assert np.allclose(want.x["window"], got.x["window"], atol=1e-6) and (want.mask == got.mask).all() and want.x["window"].any()
