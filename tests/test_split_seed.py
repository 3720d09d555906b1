"""The split of a node is a shortest set, also where failures in a row end the search at a longer one."""

import duckdb
import pytest
from pyspark.sql import functions as F

from depstrata import queries
from depstrata.operators.counting import ROW
from depstrata.plans.tree import discover_many


def test_a_split_is_a_shortest_set_whatever_the_seed(spark):
    """a and b are a key; of twelve columns any three are one within the error, and no two."""
    odd = [F.pmod(F.xxhash64(F.lit(i), "id"), F.lit(60)).alias(f"c{i}") for i in range(12)]
    df = spark.range(400).select((F.col("id") % 20).alias("a"), F.floor(F.col("id") / 20).alias("b"), *odd)
    for tree in discover_many(df, range(3), D=3, eps=0.005, measure="ratio").values():
        assert tree.split_of(ROW).children == ("a", "b") and tree.split_of(ROW).error == 0


@pytest.fixture(scope="module")
def odd_seed():
    """One staged table and one tree for all queries, of a seed whose search ends at three columns for the root."""
    with pytest.MonkeyPatch.context() as m:
        stage, tree, kept = queries.staged, queries._purchases_tree, {}
        m.setattr(queries, "_W1_SEED", 22)
        m.setattr(queries, "staged", lambda df: kept.setdefault("df", None) or kept.update(df=stage(df)) or kept["df"])
        m.setattr(queries, "_purchases_tree", lambda df: kept.get("tree") or kept.update(tree=tree(df)) or kept["tree"])
        yield


@pytest.mark.parametrize("name", ["tree_measures_purchases", "features_categorical", "features_interval_quantile", "features_price_customer", "features_qty_customer"])
def test_rows_of_the_sql_whatever_the_seed(spark, odd_seed, name):
    folder, db = "/root/testdata/sf0.01", duckdb.connect()
    for t in ("customer", "part", "orders", "lineitem"):
        db.sql(f"create view {t} as select * from '{folder}/{t}.parquet'")
    want, got = db.sql(queries.oracle_sql()[name]), queries.queries()[name](spark, folder)
    assert got.columns == want.columns
    assert sorted(map(tuple, got.collect()), key=str) == sorted(want.fetchall(), key=str)
