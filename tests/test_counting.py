from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from depstrata.functions.columns import canonical, decimal_columns, digest, profile
from depstrata.operators.counting import ROW, DistinctCounter, cuboids, exact, prefix_rollup, prefix_sketch, sorted_profile
from depstrata.operators.dependency import collapse_equivalents, dependency_stats, descendants, determined, equivalent_columns, error_ratio, error_rows, holds, is_minimal, repair, violations, witnesses
from depstrata.sources import enforce_set
from tests.fixtures import purchases


def test_null_is_a_value(spark):
    df = spark.createDataFrame([(None, 1), (1, None), (None, None)], "a int, b int")
    c = DistinctCounter(df)
    assert c.count(["a", "b"]) == 3
    assert c.count(["a"]) == 2
    assert c.count([]) == 1
    assert c.count_many([["a"], ["b"], ["a", "b"]])[frozenset("ab")] == 3
    assert df.select(digest(["a", "b"]).alias("k")).distinct().count() == 3
    assert sorted_profile(df, ["a", "b"]) == prefix_rollup(df, ["a", "b"]) == [2, 3]


def test_empty_and_single(spark):
    e = DistinctCounter(spark.createDataFrame([], "a int, b int"))
    assert (e.count([]), e.count(["a"]), e.rows) == (0, 0, 0)
    assert sorted_profile(e.df, ["a"]) == [0]
    s = DistinctCounter(spark.createDataFrame([(1,)], "a int"))
    assert (s.count([]), s.rows) == (1, 1)


def test_nan_and_zero(spark):
    df = spark.createDataFrame([(float("nan"),), (float("nan"),), (0.0,), (-0.0,)], "x double")
    assert DistinctCounter(df).count(["x"]) == 2
    assert sorted_profile(df, ["x"]) == [2]


def test_prefixes_agree(spark):
    df = purchases(spark)
    order = ["channel", "day", "buyer", "item", "weight"]
    want = [DistinctCounter(df).count(order[: i + 1]) for i in range(len(order))]
    assert prefix_rollup(df, order) == want
    assert sorted_profile(df, order) == sorted_profile(df, order, 3) == want
    assert all(abs(a - b) <= 1 for a, b in zip(prefix_sketch(df, order), want))
    assert cuboids(df, ["channel", "day"], "cube").count() == 4


def test_errors(spark):
    df = purchases(spark, dirty=True)
    assert DistinctCounter(df).stats(["ord", "item"], ROW).error == Fraction(1, 19)
    assert round(error_rows(df, ["item"], "price"), 6) == 0.052632
    assert error_ratio(df, ["item"], "price") == pytest.approx(1 / 6)
    assert holds(df, ["item"], "price", 0.06) and not holds(df, ["item"], "price", 0.06, "ratio")
    assert exact(0.125) == Fraction(1, 8)
    assert dependency_stats(df, [], "kind").r_lhs == 1


def test_ratio_can_rise_outside_descendants(spark):
    df = purchases(spark)
    assert error_ratio(df, ["age"], "kind") == pytest.approx(0.6)
    assert error_ratio(df, ["age", "buyer_name"], "kind") == pytest.approx(0.625)


def test_descendants(spark):
    df = purchases(spark)
    assert descendants(df, "ord") == {"ord", "buyer", "day", "channel", "buyer_name", "phone", "age"}
    assert descendants(df, "item") == {"item", "kind", "price", "weight", "ship_cost"}
    assert descendants(df, ROW) == set(df.columns)
    assert ["ship_cost", "weight"] in equivalent_columns(df, ["weight", "ship_cost", "age"])
    arrays = spark.createDataFrame([(1, [1, None], None), (1, [1, None], None), (2, [2], b"x")], "k int, a array<int>, b binary")
    assert descendants(arrays, "k") == {"k", "a", "b"}


def test_minimal(spark):
    c = DistinctCounter(purchases(spark))
    assert is_minimal(c, ["ord", "item"], ROW)
    assert not is_minimal(c, ["ord", "item", "day"], ROW)


def test_repair_removes_the_error(spark):
    df = purchases(spark, dirty=True)
    kept = repair(df, ["item"], ["price"])
    assert 1 - kept.count() / 19 == pytest.approx(error_rows(df, ["item"], "price"))
    assert error_rows(kept, ["item"], "price") == 0
    assert violations(df, ["item"], ["price"]).count() == 1
    assert witnesses(df, ["item"], ["price"]).count() == 2


def test_columns(spark):
    df = purchases(spark)
    assert decimal_columns(df) == decimal_columns(df, "type") == ["weight", "ship_cost"]
    assert decimal_columns(df, "off") == []
    p = {r.column_name: r for r in profile(df, exact=True).collect()}
    assert (p["weight"].r, p["weight"].nulls, p["weight"].is_decimal) == (3, 7, True)
    m = spark.createDataFrame([({"a": 1, "b": 2},), ({"b": 2, "a": 1},)], "m map<string,int>")
    assert canonical(m).distinct().count() == 1


def test_enforce_set(spark):
    df = spark.createDataFrame([(1, 2), (1, 2), (3, None)], "a int, b int")
    assert enforce_set(df).count() == 2
    assert sorted(r.weight for r in enforce_set(df, "weight").collect()) == [1, 2]
    with pytest.raises(ValueError):
        enforce_set(df, "reject")


def test_nested_values_and_nulls_count(spark):
    rows = [(1, [1, None], (1, None), -0.0), (1, [1], (None, 1), 0.0), (2, [None, 1], (1, None), float("nan")), (2, None, None, None), (2, [], (None, None), None)]
    df = spark.createDataFrame(rows, "k int, a array<int>, s struct<x:int,y:int>, v double")
    c = DistinctCounter(df)
    assert [c.count(s) for s in (["a"], ["s"], ["v"], ["k", "v"], ["k", "a"], [])] == [5, 4, 3, 3, 5, 1]
    assert c.count_many([["a", "s"], ["k", "s"], ["v", "s"]]) == {frozenset("as"): 5, frozenset("ks"): 5, frozenset("vs"): 5}
    assert sorted_profile(df, ["k", "v", "s"], 3) == [2, 3, 5]


def test_determined_agrees_with_descendants(spark):
    df = purchases(spark)
    nodes = ["ord", "item", "buyer", "age", "weight"]
    assert determined(df, nodes) == {n: descendants(df, n) for n in nodes}
    assert collapse_equivalents(df.withColumn("twin", F.concat("buyer", "buyer"))) == {"twin": "buyer", "ship_cost": "weight"}
