from itertools import combinations

from pyspark.sql import functions as F

from depstrata.operators.counting import ROW, DistinctCounter, Part
from depstrata.operators.dependency import Below, descendants, equivalent_columns
from depstrata.plans.tree import SchemaTree
from depstrata.sources import staged


def test_of_equally_short_splits_the_one_with_least_error(spark):
    """x and z are a key but for one row, within the error; x and y are one without any."""
    df = spark.createDataFrame([(x, y, 0 if (x, y) == (0, 1) else y) for x in range(20) for y in range(10)], "x int, z_ int, z int").withColumnRenamed("z_", "y")
    for seed in range(4):
        root = SchemaTree.discover(df, D=2, eps=0.005, measure="ratio", seed=seed).split_of(ROW)
        assert set(root.children) == {"x", "y"} and root.error == 0, seed


def test_a_part_changes_no_answer(spark, monkeypatch):
    a = F.floor(F.col("id") / 4)
    df = staged(spark.range(40_000).select("id", a.alias("a"), F.concat(F.lit("t"), a).alias("twin"), (F.col("id") % 7).alias("b"), F.when(F.col("id") % 5 > 0, a % 11).alias("c"), (a % 3).alias("d")))
    part = Part.of(df, staged)
    assert part is not None and 0 < part.df.count() < 40_000 / 2
    sets = [s for k in (1, 2) for s in combinations(df.columns, k)]
    for eps in (0, 0.01, 0.6):
        assert DistinctCounter(df, part=part).test_many(sets, ROW, eps) == DistinctCounter(df).test_many(sets, ROW, eps)
    below = Below(df, part)
    assert {c: below.of(c) for c in df.columns} == {c: descendants(df, c) for c in df.columns}
    assert equivalent_columns(df, part=part) == equivalent_columns(df)
    wide = df.select("a", "twin", "b", "c", "d")
    with_part = SchemaTree.discover(wide, D=3, eps=0.005, measure="ratio", seed=0)
    monkeypatch.setattr(Part, "of", staticmethod(lambda *_: None))
    assert SchemaTree.discover(wide, D=3, eps=0.005, measure="ratio", seed=0).signature() == with_part.signature()
