"""The theory's closed forms read their inputs from lineitem, so they follow what it holds."""

import pytest

from depstrata.queries import queries

LINES = [(1, 2.0, "A"), (1, 4.0, "A"), (2, 2.0, "N"), (3, 4.0, "R"), (4, 1.0, "R"), (5, 3.0, "R")]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("lines"))
    spark.createDataFrame(LINES, "l_orderkey long, l_quantity double, l_returnflag string").coalesce(1).write.parquet(f"{path}/lineitem.parquet")
    return path


def test_success_budget(spark, folder):
    assert sorted({r.k for r in queries()["success_budget"](spark, folder).collect()}) == [1, 2]


def test_return_probabilities(spark, folder):
    got = queries()["return_probabilities"](spark, folder).collect()
    assert [r["size"] for r in got] == [1.0, 1.0, 3.0] and abs(sum(r.probability for r in got) - 1) < 1e-6


def test_max_index_cdf(spark, folder):
    got = queries()["max_index_cdf"](spark, folder).collect()
    assert sorted({r.m for r in got}) == [1, 2, 3, 4] and all(r.exact == 1 for r in got if r.m == 4)
