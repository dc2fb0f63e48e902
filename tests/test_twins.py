import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parent))
import twins

from carepath import queries as core

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    return twins.connect(SF)


@pytest.mark.parametrize("name", sorted(core.oracle_sql()))
def test_query_equals_its_twin(spark, con, name):
    got = core.queries()[name](spark, SF).toPandas()
    assert twins.rows(got) == twins.rows(con.sql(core.oracle_sql()[name]).df())


@pytest.mark.parametrize("name, tables", [("d_rotation_8_1_1", {"orders", "lineitem"}), ("d_rotation_3_1_1", {"orders", "lineitem"}), ("r16_grid", {"orders", "lineitem"})])
def test_query_reads_given_tables(spark, name, tables):
    files = core.queries()[name](spark, SF).inputFiles()
    assert {Path(f).stem for f in files} == tables
