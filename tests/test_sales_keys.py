import os

from pyspark.sql import functions as F

from depstrata import queries
from depstrata.operators.counting import DistinctCounter
from depstrata.sources import workloads


def test_as_many_rows_as_the_wide_table(spark, tmp_path):
    """Two parts of one key double some rows, some suppliers are missing, and a line stands twice."""
    from depstrata.sources import load

    source = "/root/testdata/sf0.001"
    for t in ("region", "nation", "customer", "orders", "part", "supplier", "lineitem"):
        df = load(spark, source, t)
        if t == "part":
            df = df.union(df.where("p_partkey % 3 = 0").withColumn("p_name", F.lit("other")))
        if t == "supplier":
            df = df.where("s_suppkey % 4 > 0")
        if t == "lineitem":
            df = df.union(df.limit(500))
        df.write.parquet(os.path.join(tmp_path, f"{t}.parquet"))
    wide, keys = workloads.sales_wide(spark, str(tmp_path)), workloads.sales_keys(spark, str(tmp_path), queries._LINE_POOL)
    assert len(wide.columns) == 31 and keys.columns == [*queries._LINE_POOL, "rest0", "rest1"]
    assert keys.count() == wide.count() and DistinctCounter(keys).rows == DistinctCounter(wide).rows
    pool = list(queries._LINE_POOL)
    assert DistinctCounter(keys).rows > DistinctCounter(wide, pool).rows
    assert keys.select(*pool).exceptAll(wide.select(*pool)).count() == 0


def test_runs_on_a_large_table_count_one_set_at_a_time(spark, monkeypatch):
    """A part of the rows settles most sets; no shuffle holds the table once for each of several sets."""
    asked = []
    run = DistinctCounter._run
    monkeypatch.setattr(queries.Part, "LEAST", 1 << 11)
    monkeypatch.setattr(DistinctCounter, "_run", lambda self, sets: (asked.append((len(sets), len(self.columns))), run(self, sets))[1])
    rows = queries._QUERIES["fa_runs_sales_wide"](spark, "/root/testdata/sf0.001").count()
    assert rows == 16 and asked and max(asked) == (1, 10) and len(asked) < 60
