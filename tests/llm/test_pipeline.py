import re

import duckdb
import test_join
import test_secrets
import test_tiling

from carepath.llm import ngram_join, secrets, toxicity
from carepath.llm._shared import table
from carepath.llm.oracles import ORACLES

SF = "/root/testdata/sf0.001"
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def holds_item(text, items):
    words = re.findall(r"[a-z0-9\x80-\U0010ffff]+", (text or "").translate(LOW))
    for item in items:
        seeds = {tuple(item[i : i + 5]) for i in range(len(item) - 4)}
        near = [i for i in range(len(words) - 4) if tuple(words[i : i + 5]) in seeds]
        if near and sum(t[2] for t in test_tiling.brute(item, words[max(0, near[0] - 5) : near[-1] + 10], 5)) >= 0.8 * len(item):
            return True
    return False


def test_stages_against_brute_force(spark):
    """Each stage on all its predecessor kept, against a decision by plain means for every document."""
    import corpus_pipeline as P

    docs = table(spark, SF, "documents")
    columns, kept = docs.columns, docs
    texts = {r.doc_id: r.text for r in docs.collect()}
    model = toxicity.fit(docs, table(spark, SF, "labels"))
    items = [re.findall(r"[a-z0-9\x80-\U0010ffff]+", (r.text or "").translate(LOW)) for r in table(spark, SF, "benchmark").collect()]
    for name, stage in P.STAGES[:-1]:
        kept = P.written(stage(spark, kept, SF), "test")
        got = {r.doc_id: r.text for r in kept.collect()}
        assert kept.columns == columns
        if name == "toxicity":
            want = {i: t for i, t in texts.items() if model.score(toxicity.logits(model.weights, model.spec, [t or ""]))[0] < model.spec.cut}
        elif name == "ngram_jaccard_join":
            linked = test_join.brute(list(texts.items()), ngram_join.JoinSpec())
            want = {i: t for i, t in texts.items() if linked[i][1] == i}
        elif name == "benchmark_decontamination":
            want = {i: t for i, t in texts.items() if not holds_item(t, items)}
        else:
            want = texts
            for i, t in texts.items():
                clean = not test_secrets.brute(t or "") and secrets.MASK not in got[i]
                assert not test_secrets.brute(got[i] or "") and (got[i] == t if clean else secrets.MASK in got[i])
            assert all(r.n_chars == len(r.text or "") for r in kept.collect() if secrets.MASK in (r.text or ""))
        assert set(got) == set(want) and 0.5 * len(texts) < len(got) <= len(texts)
        texts = got
    mixed = P.STAGES[-1][1](spark, kept, SF)
    con = duckdb.connect()
    con.register("documents", kept.toArrow())
    want = {r[0]: r[1] for r in con.sql(f"SELECT doc_id, taken FROM ({ORACLES['op7_pareto_mix']})").fetchall()}
    got = {r.doc_id: (r.taken, r.copies) for r in mixed.collect()}
    assert {i: t for i, (t, _) in got.items() if t} == {i: t for i, t in want.items() if t} and all(c > 0 for _, c in got.values())


def test_stages_give_unused_heap_back(spark, none):
    """Each stage begins with a full collection on the executors, the only one in which their heap shrinks."""
    import corpus_pipeline as P

    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    full = lambda: sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())
    for _, stage in P.STAGES:
        before = full()
        stage(spark, none, SF)
        assert full() > before
