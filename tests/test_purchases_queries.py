"""Queries on trees of purchases where several splits pass within the error: rows have to be those of the SQL."""

import duckdb
import pytest

from depstrata.queries import oracle_sql, queries

NAMES = ("relations_purchases", "tree_measures_purchases", "features_price_customer", "features_qty_customer", "features_categorical", "features_interval_quantile")

#: Rows of one copy; each line of an order has another part.
CUSTOMERS, PARTS, ORDERS, LINES = 40, 331, 1200, 4


def _write(path, copies):
    """Tables where (l_partkey, o_custkey) is a key but for some rows, and (l_partkey, o_orderdate) is one as (l_orderkey, l_partkey) is.

    Of two copies the keys and the days are shifted, but not the names: (c_name, o_orderdate) is as good as (o_custkey, o_orderdate).
    """
    db = duckdb.connect()
    each = f"(select unnest(range({copies})) as i)"
    day = "timestamp '1995-01-01' + to_days(cast({} as int))"
    tables = {
        "customer": f"select k + i * {CUSTOMERS} as c_custkey, 'Customer#' || k as c_name, cast(k * 7 % 5 as int) as c_nationkey, k * 1.37 as c_acctbal, 's' || k % 3 as c_mktsegment from {each}, (select unnest(range({CUSTOMERS})) as k)",
        "part": f"select k + i * {PARTS} as p_partkey, 'n' || k // 8 % 8 as p_name, 'b' || k // 8 % 4 as p_brand, 't' || k // 8 % 5 as p_type, cast(1 + k // 8 % 40 as int) as p_size, 900 + k % 100 / 10.0::double as p_retailprice from {each}, (select unnest(range({PARTS})) as k)",
        # An order's day follows from its number, but for three orders that take the day before of the same customer.
        "orders": f"""select k + i * {ORDERS} as o_orderkey, k % {CUSTOMERS} + i * {CUSTOMERS} as o_custkey, 's' || hash(k) % 3 as o_orderstatus, k * 1.5 as o_totalprice,
            {day.format(f"(case when k in (700, 900, 1100) then k - {CUSTOMERS} else k end) // {CUSTOMERS} + i * 5000")} as o_orderdate, 'p' || hash(k + 9999) % 5 as o_orderpriority from {each}, (select unnest(range({ORDERS})) as k)""",
        # Customer c's n-th line has part (c * 8 + n) modulo the parts, but for one line in 400 that takes the part of an earlier order.
        "lineitem": f"""select k // {LINES} + i * {ORDERS} as l_orderkey, (k // {LINES} % {CUSTOMERS} * 8 + (case when k % 400 = 399 and k > 1000 then k // {LINES} // {CUSTOMERS} * {LINES} - 1 else k // {LINES} // {CUSTOMERS} * {LINES} + k % {LINES} end)) % {PARTS} + i * {PARTS} as l_partkey,
            1 as l_suppkey, k % {LINES} as l_linenumber, cast(1 + hash(k) % 50 as double) as l_quantity, 10.0 * (1 + hash(k) % 50) + 0.25 as l_extendedprice from {each}, (select unnest(range({ORDERS * LINES})) as k)""",
    }
    for t, sql in tables.items():
        db.sql(f"copy ({sql}) to '{path}/{t}.parquet' (format parquet)")
    return str(path)


@pytest.fixture(scope="module")
def folders(tmp_path_factory):
    return {n: _write(tmp_path_factory.mktemp(f"copies{n}"), n) for n in (1, 2)}


@pytest.mark.parametrize(("name", "copies"), [*((n, 1) for n in NAMES), *((n, 2) for n in NAMES[:2])])
def test_rows_of_the_sql(spark, folders, name, copies):
    db = duckdb.connect()
    for t in ("customer", "part", "orders", "lineitem"):
        db.sql(f"create view {t} as select * from '{folders[copies]}/{t}.parquet'")
    want = db.sql(oracle_sql()[name])
    got = queries()[name](spark, folders[copies])
    assert got.columns == want.columns
    rows = sorted(map(str, map(tuple, got.collect())))
    assert rows == sorted(map(str, want.fetchall())) and rows
