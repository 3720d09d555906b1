from itertools import combinations

from pyspark.sql import functions as F

from depstrata.operators.counting import DistinctCounter, Twins
from depstrata.plans.problem import permute
from depstrata.sources import workloads


def test_twins_change_no_count(spark):
    """u is a function of a that is no twin, v parts from a beyond the rows that propose classes, and a NULL is a value."""
    a = F.when(F.col("id") % 1000 > 0, (F.col("id") / 3).cast("int"))
    df = spark.range(20_000).select(a.alias("a"), (F.col("id") % 7).alias("b"))
    df = df.select("*", (F.col("a") + 1).alias("t"), F.floor(F.col("a") / 2).alias("u"), F.when(F.col("a") > 6000, 0).otherwise(F.col("a")).alias("v"), F.concat(F.lit("x"), "b").alias("w"))
    twins = Twins(df)
    assert "t" in twins.below["a"] and twins.below["b"] == ("w",)
    plain, short = DistinctCounter(df), DistinctCounter(df, twins=twins)
    sets = [s for k in range(4) for s in combinations(df.columns, k)]
    assert short.count_many(sets) == plain.count_many(sets)
    assert short.meter.jobs < plain.meter.jobs


def test_a_wide_table_takes_no_more_jobs_than_its_classes(spark):
    base = spark.range(3_000).select((F.col("id") / 4).cast("int").alias("a"), (F.col("id") % 4).alias("b"), (F.col("id") % 11).alias("c"))
    df = workloads.twinned(base, 90)
    counter = DistinctCounter(df, twins=Twins(df), batch=1)
    order = permute(df.columns, 1)
    r = counter.count_many([order[:i] for i in range(20, 90)])
    assert set(r.values()) == {3_000} and counter.meter.jobs <= 8
