import pytest

from graphsplit import queries
from tests.compare import database, same

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    return database(SF)


#: Whole methods take many Spark jobs each; these stand for the others here.
SAMPLE = {"deep_optimum", "deep_fast_planted", "deep_wide_split", "base_shared_deep", "base_relaxed_fast", "base_hash", "base_range", "e4_shared"}
QUICK = sorted(n for n in queries.SQL if n in SAMPLE or not n.startswith(("deep_", "base_", "e1", "e2", "e3", "e4", "e5", "e6", "e7", "e8", "e9")))


@pytest.mark.parametrize("name", QUICK)
def test_query_gives_what_sql_gives(spark, con, name):
    same(queries.QUERIES[name](spark, SF), queries.SQL[name], con)


def test_driver_entry_imports_and_names_agree():
    import __spark_entry__ as entry

    assert set(queries.QUERIES) <= set(entry.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())
