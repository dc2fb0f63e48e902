from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from carepath.functions import scoring, sqlfns
from carepath.measures import metrics
from carepath.operators import codes, cohorts, folds, notes, sequences, temporal
from carepath.sources import retail

SF = "/root/testdata/sf0.01"
DAY = datetime(2020, 1, 1)


def visits(spark, days, stay=0):
    rows = [(1, i, DAY + timedelta(days=d), DAY + timedelta(days=d + stay), "") for i, d in enumerate(days)]
    return spark.createDataFrame(rows, "subject_id long, visit_id long, admit_ts timestamp_ntz, discharge_ts timestamp_ntz, urgency string")


def test_windows_and_prefixes_of_four_visits(spark):
    v = visits(spark, [0, 1, 2, 3])
    two = sequences.sliding(v, 2).collect()
    assert sorted((r.visit_ids, r.target_visit) for r in two) == [([0, 1], 2), ([1, 2], 3)]
    assert [(r.visit_ids, r.target_visit) for r in sequences.sliding(v, 3).collect()] == [([0, 1, 2], 3)]
    (six,) = sequences.sliding(v, 6).collect()
    assert six.visit_ids == [None, None, None, 0, 1, 2] and six.mask == [False] * 3 + [True] * 3
    (right,) = sequences.sliding(v, 6, pad_side="right").collect()
    assert right.visit_ids == [0, 1, 2, None, None, None]
    assert sorted((r.visit_ids, r.target_visit) for r in sequences.prefixes(v).collect()) == [([0], 1), ([0, 1], 2), ([0, 1, 2], 3)]
    assert len(sequences.sliding(v, 2, last_visit="keep").collect()) == 3


@pytest.mark.parametrize("gap, inclusive, label", [(0, False, 1), (29, False, 1), (30, False, 0), (30, True, 1), (31, True, 0)])
def test_return_label_at_its_bounds(spark, gap, inclusive, label):
    v = visits(spark, [0, gap])
    for strategy in ("window", "range_join"):
        got = {r.visit_id: r.y_return for r in temporal.return_label(v, inclusive=inclusive, strategy=strategy).collect()}
        assert got == {0: label, 1: 0}
    back = {r.visit_id: r.y_return for r in temporal.return_label(v, inclusive=inclusive, direction="backward").collect()}
    assert back == {0: 0, 1: label}


def test_gaps_of_first_and_overlapping_visits(spark):
    v = visits(spark, [0, 2], stay=5)
    assert [r.gap_days for r in temporal.prior_gap(v).orderBy("visit_id").collect()] == [None, 0]
    assert [r.gap_days for r in temporal.prior_gap(v, negative="keep", first_fill=99).orderBy("visit_id").collect()] == [99, -3]


def test_minmax_of_constant_and_unseen_values(spark):
    df = spark.createDataFrame([(1, 5), (3, 5), (9, 5), (None, None)], "a int, b int")
    fit = temporal.fit_minmax(df, ["a", "b"], F.col("a") < 5)
    got = [(r.a_scaled, r.b_scaled) for r in temporal.apply_minmax(df, fit).collect()]
    assert got == [(0.0, 0.0), (1.0, 0.0), (1.0, 0.0), (None, None)]


def test_parents_of_code_shapes(spark):
    dx = ["25000", "4019", "E8499", "V4581", "v45", "41", None]
    df = spark.createDataFrame([(c,) for c in dx], "c string")
    assert [r[0] for r in df.select(codes.condense(F.col("c"), "D")).collect()] == ["D_250", "D_401", "D_E849", "D_V45", "D_V45", "D_41", None]
    sqlfns.register(spark)
    assert spark.sql("SELECT condense_proc('3893') AS p, condense_dx('e8499') AS d").first() == ("P_38", "D_E849")


def test_code_lists(spark):
    ev = spark.createDataFrame([(1, "b", 2, 0), (1, "a", 1, 0), (1, "b", 3, 0), (2, "z", 1, 5), (2, "y", 1, 4)], "visit_id long, code string, seq int, tie int")
    got = {r.visit_id: r.codes for r in codes.ordered_list(ev).collect()}
    assert got == {1: ["a", "b", "b"], 2: ["y", "z"]}
    assert {r.visit_id: (r.codes, r.n_truncated) for r in codes.ordered_list(ev, cap=2).collect()}[1] == (["a", "b"], 1)
    padded = {r.visit_id: (r.padded, r.mask) for r in codes.pad(codes.ordered_list(ev), size=3).collect()}
    assert padded[1] == (["a", "b", ""], [True, True, False])
    vocab = codes.vocabulary(ev)
    assert [(r.code, r.id) for r in vocab.orderBy("id").collect()] == [("b", 2), ("a", 3), ("y", 4), ("z", 5)]
    unk = codes.map_codes(ev, spark.createDataFrame([("a", "A")], "code string, grp string"), "grp", "UNK")
    assert sorted(r.code for r in unk.collect()) == ["A", "UNK", "UNK", "UNK", "UNK"]


def test_notes(spark):
    n = spark.createDataFrame([(1, 1, "c", "Dr. Él\r\nsaid: M.D.  #1"), (2, 2, "c", " ".join(["w"] * 513)), (3, 3, "c", " ".join(["w"] * 512)), (4, 4, "c", "")], "visit_id long, note_id long, category string, text string")
    cleaned = n.withColumn("text", notes.clean(F.col("text")))
    assert cleaned.filter("note_id = 1").first().text == "dr él said md 1"
    count = {r.note_id: r["count"] for r in notes.chunk(cleaned).groupBy("note_id").count().collect()}
    assert count == {1: 1, 2: 2, 3: 1}
    assert notes.chunk(cleaned, tail="merge").filter("note_id = 2").first().n_tokens == 513
    assert notes.chunk(cleaned, tail="drop").filter("note_id = 2").first().n_tokens == 512
    assert [(r.chunk_no, r.n_tokens) for r in sqlfns.exploded_chunks(cleaned.filter("note_id = 2"), 512).orderBy("chunk_no").collect()] == [(0, 512), (1, 1)]


def test_merged_chunk_probabilities(spark):
    rows = [(i, 0, 1, p) for i, ps in enumerate(((0.9,), (0.9, 0.1), (0.2, 0.4, 0.6, 0.8))) for p in ps]
    df = spark.createDataFrame(rows, "sample_id long, class_id int, y int, p double")
    got = [round(r.p, 9) for r in scoring.merge_chunks(df).orderBy("sample_id").collect()]
    assert got == [0.9, 0.7, 0.6]


@pytest.mark.parametrize("pairs, auc, rp", [([(0.5, 1), (0.5, 0)], 0.5, 0.0), ([(0.9, 1), (0.1, 0)], 1.0, 1.0), ([(0.1, 1), (0.9, 0)], 0.0, 0.0), ([(0.3, 0), (0.2, 0)], None, 0.0)])
def test_ranking_measures(spark, pairs, auc, rp):
    df = spark.createDataFrame([(i, 0, y, p) for i, (p, y) in enumerate(pairs)], "sample_id long, class_id int, y int, p double")
    assert metrics.roc_auc(df).first().auc == auc
    assert metrics.recall_at_precision(df).first().rp == rp
    if auc is not None:
        assert metrics.pr_auc(df).first().aupr == pytest.approx(df.agg(sqlfns.aupr_udf("p", "y")).first()[0])


def test_recall_at_k_from_rows_and_arrays(spark):
    long = spark.createDataFrame([(s, c, int(c in t), p) for s, t, ps in ((1, {0, 3}, [0.9, 0.8, 0.1, 0.8]), (2, set(), [0.1] * 4)) for c, p in enumerate(ps)], "sample_id long, class_id int, y int, p double")
    wide = spark.createDataFrame([(1, [0.9, 0.8, 0.1, 0.8], [0, 3]), (2, [0.1] * 4, [])], "sample_id long, p array<double>, y array<int>")
    for empty, factor in (("skip", 1.0), ("zero", 0.5)):
        a = metrics.recall_at_k(long, (1, 2, 3), empty=empty).first()
        assert list(a) == list(metrics.recall_at_k_arrays(wide, (1, 2, 3), empty=empty).first()) == [0.5 * factor, 0.5 * factor, 1.0 * factor]


def test_folds_are_isolated_and_even(spark):
    rows = temporal.return_label(retail.encounters(spark, SF)).select("subject_id", "visit_id", "y_return").persist()
    dealt = folds.by_subject(cohorts.patient_label(rows))
    assert dealt.select("stratum", "fold").distinct().count() == 20
    per_stratum = dealt.groupBy("stratum", "fold").count().groupBy("stratum").agg((F.max("count") - F.min("count")).alias("d")).collect()
    assert all(r.d <= 1 for r in per_stratum)
    roles = rows.join(dealt.select("subject_id", "fold"), "subject_id").join(folds.rotation(spark, 10), "fold")
    assert folds.audit_subjects(roles).isEmpty()
    assert folds.audit_never_tested(rows, roles).isEmpty()
    assert roles.filter("role = 'test'").count() == rows.count()
    bad = rows.join(folds.by_visit(rows).select("visit_id", "fold"), "visit_id").join(folds.rotation(spark, 10), "fold")
    assert not folds.audit_subjects(bad).isEmpty()
    assert folds.audit_label_input("backward", ["gap", "stay"]) == ["gap"] and not folds.audit_label_input("forward", ["gap"])


def test_balance_by_roles(spark):
    rows = spark.range(1000).select(F.col("id").alias("visit_id"), (F.col("id") % 10 == 0).cast("int").alias("y_return"), F.when(F.col("id") < 800, "train").otherwise("test").alias("role"))
    both = {(r.role, r.y_return): r["count"] for r in folds.balance(rows, by=["role"]).groupBy("role", "y_return").count().collect()}
    assert both == {("train", 1): 80, ("train", 0): 80, ("test", 1): 20, ("test", 0): 20}
    one = {(r.role, r.y_return): r["count"] for r in folds.balance(rows, by=["role"], roles=("train",)).groupBy("role", "y_return").count().collect()}
    assert one == {("train", 1): 80, ("train", 0): 80, ("test", 1): 20, ("test", 0): 180}


def test_cohort_identities(spark):
    enc = retail.encounters(spark, SF)
    p = cohorts.profile(temporal.return_label(enc)).first()
    assert p.positive + p.negative == p.patients == p.single_visit + p.multi_visit and p.visits - p.patients == 13_500
    lists = codes.ordered_list(retail.code_events(spark, SF, "D"))
    assert cohorts.next_dx_dataset(enc, lists).count() == 13_271
    assert cohorts.next_dx_dataset(enc, lists, require_label_codes=False).count() == 13_500
    assert {r.scheme: r.samples for r in sequences.count_report(enc).collect()} == {"sliding_3": 10_526, "sliding_6": 6_370, "prefixes": 13_500, "prefix_cells": 75_200}
    assert sequences.sliding(enc, 3).count() == 10_526 and sequences.sliding(enc, 6).count() == 6_370


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    enc = visits(spark, [0, 1]).repartition(3)
    one = plan(temporal.return_label(temporal.stay_length(temporal.prior_gap(enc))))
    assert one.count("hashpartitioning(subject_id") == 1 and one.count("Window [") == 1
    mapped = plan(codes.map_codes(retail.code_events(spark, SF, "D"), retail.code_dict(spark, SF, "D"), "grp"))
    assert "BroadcastHashJoin" in mapped and "SortMergeJoin" not in mapped
    assert "PushedFilters: [In(source" in plan(notes.select_category(retail.notes(spark, SF), ["src0", "src1"]))
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert "CartesianProduct" not in plan(folds.text_overlap(docs, spark.read.parquet(f"{SF}/benchmark.parquet")))
    assert "WindowGroupLimit" in plan(__import__("carepath.operators.relational", fromlist=["top_k"]).top_k(docs, ["doc_id"], 2, ["source"]))


def test_text_models_have_no_visit_vector(spark):
    with pytest.raises(ValueError):
        sequences.attach(visits(spark, [0]), spark.createDataFrame([], "visit_id long, model_id string, h array<float>"), "m", uses_text=True)


def test_windows_in_tasks_equal_windows(spark):
    v = visits(spark, [0, 1, 2, 3, 4])
    want = {(r.target_visit, tuple(r.visit_ids)) for r in sequences.sliding(v, 2, partial="none").collect()}
    assert {(r.target_visit, tuple(r.visit_ids)) for r in sequences.sliding_in_tasks(v, 2).collect()} == want


def test_stores(spark, tmp_path):
    from carepath.models import encoders
    from carepath.sources import tables

    texts = spark.createDataFrame([(1, 0, 1, "a b"), (2, 0, 1, "a b"), (3, 0, 1, "c")], "visit_id long, chunk_no int, n_chunks int, text string")
    path = str(tmp_path / "store")
    new = [tables.upsert_missing(encoders.encode_text(texts.filter(f"visit_id <= {n}"), encoders.HashedProjection(8)), path, "content").count() for n in (2, 3, 3)]
    assert new == [1, 1, 0] and spark.read.parquet(path).count() == 2


def test_logistic_reference_orders_like_the_feature(spark):
    from carepath.models import reference

    rows = spark.createDataFrame([(i, i / 50, int(i > 25)) for i in range(50)], "visit_id long, gap double, y int")
    assert metrics.roc_auc(reference.logistic(rows, rows, ["gap"], "y")).first().auc == 1.0


def test_comparison_with_a_base_of_zero(spark):
    rows = spark.createDataFrame([("base", 0.0, 0.5), ("other", 0.25, 0.75), ("none", 0.0, None)], "config string, f1 double, aupr double")
    got = {r.config: tuple(r)[1:] for r in metrics.compare(rows, "config", "base", ["f1", "aupr"]).collect()}
    assert got == {"base": (0.0, 0.0, None, 0.0), "other": (25.0, 25.0, None, 50.0), "none": (0.0, None, None, None)}


def test_prefixes_of_a_long_history_are_whole(spark):
    v = spark.sql("SELECT 1L AS subject_id, id AS visit_id, timestamp_ntz'2020-01-01' + make_interval(0, 0, 0, CAST(id AS INT)) AS admit_ts FROM range(131)")
    got = {r.target_visit: r.visit_ids for r in sequences.prefixes(v).collect()}
    assert got == {t: list(range(t)) for t in range(1, 131)}
    cut = {r.target_visit: (r.n, r.n_cut) for r in sequences.prefixes(v, max_len=100).collect()}
    assert cut == {t: (min(t, 100), max(0, t - 100)) for t in range(1, 131)}


def test_curves_bring_no_scores_to_one_task(spark):
    """What a single task orders is the steps' sums; distinct scores are dealt by step. The area equals a direct count."""
    import numpy as np

    from carepath.measures import metrics

    rng = np.random.default_rng(2)
    p, y = np.concatenate([rng.random(3000), [0.0, 1.0, 1.0, 1e-15]]), np.concatenate([rng.integers(0, 2, 3000), [0, 1, 0, 1]])
    scores = spark.createDataFrame([(i, 0, int(b), float(a)) for i, (a, b) in enumerate(zip(p, y, strict=True))], "sample_id long, class_id int, y int, p double")
    pos, neg = p[y == 1][:, None], p[y == 0]
    assert abs(metrics.roc_auc(scores).first()["auc"] - ((pos > neg) + (pos == neg) / 2).mean()) < 1e-12
    plan = metrics.curve(scores)._jdf.queryExecution().executedPlan().toString()
    ordered = [part for part in plan.split("Window ")[1:] if "SinglePartition" in part.split("Window ")[0]]
    assert all("_s" in part.split("\n")[0] and " p#" not in part.split("\n")[0].split("windowspecdefinition")[-1] for part in ordered)


def test_label_split_meets_the_demand_of_every_label(spark):
    """Rarest labels first, each round dealt by what earlier ones left: every label's share of a split is near its ratio."""
    import random

    from carepath.operators import folds

    random.seed(6)
    rows = [(i, sorted({f"c{min(int(random.expovariate(0.35)), 14)}" for _ in range(random.randint(1, 5))})) for i in range(1500)] + [(5000, [])]
    ratios = {"train": 8.0, "validation": 1.0, "test": 1.0}
    got = {r.key: r.split for r in folds.iterative_label_split(spark.createDataFrame(rows, "key long, labels array<string>"), ratios).collect()}
    assert set(got) == {i for i, _ in rows}
    for label in {x for _, v in rows for x in v}:
        own = [got[i] for i, v in rows if label in v]
        for split, ratio in ratios.items():
            assert abs(own.count(split) - ratio / 10 * len(own)) <= max(2.0, 0.03 * len(own)), (label, split)


def test_chunks_by_sub_words(spark):
    from carepath.operators import notes

    texts = [(1, "aaaa bb cccccccc d " * 9), (2, "x" * 50), (3, ""), (4, None)]
    rows = notes.chunk(spark.createDataFrame(texts, "note_id long, text string"), size=10, unit="subword_estimate").collect()
    for i, text in texts:
        own = sorted((r for r in rows if r.note_id == i), key=lambda r: r.chunk_no)
        assert " ".join(r.text for r in own) == " ".join((text or "").split()) and [r.chunk_no for r in own] == list(range(len(own)))
        for r in own:
            costs = [-(-len(w) // 4) for w in r.text.split(" ")]
            assert sum(costs) == r.n_tokens and sum(costs[:-1]) < 10 + costs[-1] and r.n_chunks == len(own)


def test_lsh_recall(spark):
    """The registered search finds 0.9 or more of the pairs within its distance, by brute force on the whole table."""
    import numpy as np

    from carepath.queries import queries

    sf = "/root/testdata/sf0.001"
    e = spark.read.parquet(f"{sf}/embeddings.parquet").toPandas()
    x, ids = np.stack(e.embedding).astype(float), e.vec_id.to_numpy()
    asked = ids % 100 == 0
    far = np.sqrt(((x[asked][:, None] - x[None]) ** 2).sum(-1))
    want = {(int(a), int(b)) for a, row in zip(ids[asked], far, strict=True) for b, d in zip(ids, row, strict=True) if d <= 1.35 and a != b}
    got = {(r.query_id, r.vec_id) for r in queries()["v_nearest_lsh"](spark, sf).collect()}
    assert want and got <= want and len(got) >= 0.9 * len(want)


def test_lsh_exchanges_no_vectors(spark, monkeypatch):
    """Items are read once and kept where they are; repeated rows count once, rows without a vector or an id never."""
    import io
    from contextlib import redirect_stdout

    from carepath.functions import vectors

    e = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").select("vec_id", "embedding")
    asked = e.filter("vec_id % 100 = 0")
    once = vectors.nearest_lsh(e, asked, 1.35, bucket=2.0)
    with redirect_stdout(io.StringIO()) as plan:
        once.explain()
    assert "Exchange" not in plan.getvalue() and "Join" not in plan.getvalue()
    want = sorted(map(tuple, once.collect()))
    odd = spark.createDataFrame([(None, [0.0] * 64), (100, None), (7, None)], "vec_id long, embedding array<float>")
    monkeypatch.setattr(vectors, "HELD_QUERIES", 2)
    more = e.unionByName(e.filter("vec_id < 50")).unionByName(odd)
    got = sorted(map(tuple, vectors.nearest_lsh(more, asked.unionByName(asked).unionByName(odd), 1.35, bucket=2.0).collect()))
    assert want and [g[:2] for g in got] == [w[:2] for w in want]
    assert vectors.nearest_lsh(e.limit(0), asked, 1.35).count() == 0


def test_chunks_of_all_rotations_are_merged_in_one_pass(spark):
    rows = [(r, v, c, int(v == 1), (r + v + c + k) / 10) for r in (0, 1) for v in (1, 2) for c in (0, 1) for k in range(v)]
    scores = spark.createDataFrame(rows, "rotation int, sample_id long, class_id int, y int, p double")
    together = sorted(map(tuple, scoring.merge_chunks(scores, per=("rotation",)).collect()))
    alone = sorted((r, *m) for r in (0, 1) for m in scoring.merge_chunks(scores.filter(F.col("rotation") == r)).collect())
    assert together == alone
