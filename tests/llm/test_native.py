"""Quality rules and mixing: equal to their twins, native, and whole on odd rows."""

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parent.parent))
import twins

from carepath.llm import mixing, quality, queries


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_twins(spark, name):
    sf = "/root/testdata/sf0.001"
    assert twins.rows(queries.queries()[name](spark, sf).toPandas()) == twins.rows(twins.connect(sf).sql(queries.oracle_sql()[name]).df())


def test_ledger(spark, odd, none):
    df = spark.createDataFrame([(1, "a b c d e f g h " * 4), (2, "x\ny\nx\nx"), (3, None), (4, "a b c d e f g h i j k l m n o p q r s t u v")], "doc_id long, text string")
    got = {r.doc_id: r for r in quality.ledger(df).collect()}
    assert (got[1].n_repeat_words, got[2].n_dup_lines, got[3].n_words, got[4].failures & 3) == (32, 2, 0, 0)
    book = quality.apply_policy(quality.ledger(df), "base")
    assert {r.doc_id for r in book.filter("kept").collect()} == {4}
    alone = {r.rule: (r.failing, r.only_this) for r in quality.ablation(book, "base").collect()}
    assert alone == {"few_words": (2, 2), "repeated_windows": (1, 1)}
    assert quality.overlaps(book).filter("a = 'few_words' AND b = 'repeated_windows'").first().docs == 0
    assert quality.ledger(odd, tuple(odd.columns)).count() == odd.count() and quality.ledger(none).count() == 0
    assert "Python" not in book._jdf.queryExecution().executedPlan().toString()


def test_mix(spark, odd, none):
    rows = [(i, " ".join(["w"] * (1 + i * 37 % 300)), ["a", "b", "c", None][i % 4 if i % 3 else 0]) for i in range(600)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mixed(df).collect()
    assert len(got) == 600 and all(0 <= r.copies <= 2 and r.taken == r.copies * r.size for r in got)
    for source in ("a", "b", "c", None):
        own = [r for r in got if r.source == source]
        assert abs(sum(r.taken for r in own) - own[0].target) <= 150 and own[0].target <= 2 * own[0].source_size
    assert sum(r.target for r in {r.source: r for r in got}.values()) == pytest.approx(1.5 * sum(r.size for r in got))
    assert sorted(map(str, got)) == sorted(map(str, mixing.mixed(df.repartition(7)).collect()))
    mix = mixing.mixed(odd, keep=tuple(odd.columns))
    assert mix.count() == odd.count() and "size_in" in mix.columns
    assert mixing.mixed(none).count() == 0
    assert "Python" not in mix._jdf.queryExecution().executedPlan().toString()
