"""Queries of the methods, variants, baselines and measures."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Sequence
from decimal import Decimal
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depstrata import streaming, theory
from depstrata.functions import aggregates as A
from depstrata.functions import columns as C
from depstrata.operators import counting, dependency
from depstrata.operators.counting import ROW, DistinctCounter, Part, Twins
from depstrata.plans import baselines, features, forward, shortest
from depstrata.plans.problem import Problem, permute
from depstrata.plans.tree import SchemaTree
from depstrata.sources import enforce_set, load, shuffles_dropped, staged, workloads

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_ORACLES: dict[str, str] = {}

# SQL of the workload tables.
PURCHASES = """select l.*, o_custkey, o_orderdate, o_orderpriority, o_orderstatus, c_name, c_nationkey, c_mktsegment, c_acctbal, p_name, p_brand, p_type, p_size, p_retailprice
from (select l_orderkey, l_partkey, cast(sum(l_quantity) as bigint) qty, cast(sum(cast(l_extendedprice as decimal(18,2))) as double) amount from lineitem group by all) l
join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join part on l_partkey = p_partkey"""
KPI = """select user_id, cast(ts as date) as day, 'd' || strftime(ts, '%j') as day_no, cast(hour(ts) // 6 as int) as slot, c_name, c_nationkey, n_name, n_regionkey, c_mktsegment,
count(*) n_events, count(*) filter (event_type = 'error') n_err, round(avg(value), 6) mean_value, max(value) max_value
from events join customer on user_id = c_custkey join nation on c_nationkey = n_nationkey group by all"""
SALES = """select * exclude (o_orderkey, c_custkey, n_nationkey, r_regionkey, p_partkey, s_suppkey) from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey
join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey"""


def query(oracle: str | None = None):
    def keep(f):
        _QUERIES[f.__name__] = f
        if oracle:
            _ORACLES[f.__name__] = oracle
        return f

    return keep


def _rows(spark: SparkSession, rows: Sequence[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


def _name(columns: Sequence[str]) -> str:
    return " ".join(sorted(columns))


# -- SQL pieces ---------------------------------------------------------------
def _r(columns: Sequence[str], table: str) -> str:
    """Scalar subquery of a distinct count."""
    return f"(select count(*) from (select distinct {', '.join(columns)} from {table}))" if columns else f"(select least(count(*), 1) from {table})"


def _subsets(columns: Sequence[str], limit: int) -> list[tuple[str, ...]]:
    from itertools import combinations

    return [c for k in range(1, limit + 1) for c in combinations(columns, k)]


def _subset_counts(columns: Sequence[str], table: str, limit: int) -> str:
    """Rows (names, size, mask, r) of all subsets up to a size."""
    place = {c: i for i, c in enumerate(columns)}
    return " union all ".join(f"select '{_name(s)}' as names, {len(s)} as size, {sum(1 << place[c] for c in s)} as mask, {_r(s, table)} as r" for s in _subsets(columns, limit))


def _minimal_keys_sql(columns: Sequence[str], table: str, limit: int) -> str:
    return f"""with s as ({_subset_counts(columns, table, limit)}), t as (select {_r(columns, table)} as n), k as (select s.* from s, t where r = n)
select names as columns, cast(size as bigint) as n_columns from k where not exists (select 1 from k j where j.mask & k.mask = j.mask and j.mask <> k.mask)"""


def _forward_sql(orders: Sequence[Sequence[str]], table: str, goal: Callable[[Sequence[str]], str]) -> str:
    """The rule behind forward addition: of all sets that pass, the one whose positions, from the last down, are lexicographically least."""
    parts = []
    for k, order in enumerate(orders):
        place = {c: i for i, c in enumerate(order)}
        rows = " union all ".join(
            f"select '{_name(s)}' as names, {len(s)} as size, '{''.join(chr(97 + i) for i in sorted((place[c] for c in s), reverse=True))}' as code where {goal(s)}"
            for s in _subsets(order, len(order))
        )
        parts.append(f"select {k} as order_id, arg_min(names, code) as columns, cast(arg_min(size, code) as bigint) as n_columns from ({rows})")
    return " union all ".join(parts)


_ORDERS = ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
_CUSTOMER = ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")
_LINEITEM = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")
_ORDERS_WALKS = (("o_custkey", "o_totalprice", "o_orderdate", "o_orderstatus", "o_orderpriority", "o_orderkey"), _ORDERS, permute(_ORDERS, 1), permute(_ORDERS, 2))
_CUSTOMER_WALKS = (_CUSTOMER[::-1], permute(_CUSTOMER, 3), permute(_CUSTOMER, 4))


def _key_of(columns: Sequence[str], table: str) -> Callable[[Sequence[str]], str]:
    return lambda s: f"{_r(s, table)} = {_r(columns, table)}"


def _walks(spark: SparkSession, p: Problem, walks: Sequence[Sequence[str]], run) -> DataFrame:
    out = []
    for i, w in enumerate(walks):
        got = run(p, w)
        out.append((i, _name(got.columns), got.size))
    return _rows(spark, out, "order_id int, columns string, n_columns long")


# -- counts and dependencies ----------------------------------------------------
_ESSENTIAL = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus")
_COUNTED = (("l_orderkey", "l_linenumber"), ("l_orderkey", "l_partkey"), ("l_orderkey", "l_suppkey"), ("l_orderkey", "l_partkey", "l_suppkey"), ("l_returnflag", "l_linestatus"), _LINEITEM)


@query(" union all ".join(f"select '{_name(s)}' as columns, {_r(s, 'lineitem')} as r" for s in _COUNTED))
def distinct_counts_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = DistinctCounter(load(spark, sf_dir, "lineitem")).count_many(_COUNTED)
    return _rows(spark, [(_name(s), got[frozenset(s)]) for s in _COUNTED], "columns string, r long")


_ERRORS = (
    ("lineitem", "l_orderkey", "l_linestatus"), ("lineitem", "l_returnflag", "l_linestatus"), ("orders", "o_custkey", "o_orderstatus"), ("orders", "o_totalprice", "o_custkey"),
    ("part", "p_retailprice", "p_brand"), ("part", "p_name", "p_type"), ("events", "user_id,props", "event_type"), ("events", "value", "event_type"), ("documents", "text", "source"),
    ("documents", "n_chars", "lang"), ("conversations", "turn", "role"), ("conversations", "conv_id", "role"), ("customer", "c_acctbal", "c_mktsegment"), ("labels", "quality", "toxic"),
)


def _error_sql(table: str, lhs: str, rhs: str) -> str:
    return f"""select '{table}' as table_name, '{lhs}' as lhs, '{rhs}' as rhs, round(1 - sum(m) / sum(n), 6) as error, round(1 - count(*) / sum(k), 6) as ratio
from (select max(n) m, sum(n) n, count(*) k from (select {lhs}, {rhs}, count(*) n from {table} group by all) group by {lhs})"""


@query(" union all ".join(_error_sql(*e) for e in _ERRORS))
def dependency_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []
    for table, lhs, rhs in _ERRORS:
        s = dependency.dependency_stats(load(spark, sf_dir, table), lhs.split(","), rhs)
        out.append((table, lhs, rhs, round(float(s.error), 6), round(float(s.ratio), 6)))
    return _rows(spark, out, "table_name string, lhs string, rhs string, error double, ratio double")


def _descendants_sql(table: str, nodes: Sequence[str], columns: Sequence[str]) -> str:
    return f"with t as materialized ({table}) " + " union all ".join(
        f"select '{n}' as node, '{c}' as column_name where not exists (select 1 from t group by {n} having count(distinct {c}) + (case when count({c}) < count(*) then 1 else 0 end) > 1)"
        for n in nodes for c in columns if n != c
    )


_P_COLS = ("l_orderkey", "l_partkey", "qty", "amount", "o_custkey", "o_orderdate", "o_orderpriority", "o_orderstatus", "c_name", "c_nationkey", "c_mktsegment", "c_acctbal", "p_name", "p_brand", "p_type", "p_size", "p_retailprice")
_S_COLS = (*_LINEITEM, *_ORDERS[1:], *_CUSTOMER[1:], "n_name", "n_regionkey", "r_name", "p_name", "p_brand", "p_type", "p_size", "p_retailprice", "s_name", "s_nationkey", "s_acctbal")
_K_COLS = ("user_id", "day", "day_no", "slot", "c_name", "c_nationkey", "n_name", "n_regionkey", "c_mktsegment", "n_events", "n_err", "mean_value", "max_value")


def _descend(spark: SparkSession, df: DataFrame, nodes: Sequence[str]) -> DataFrame:
    down = dependency.determined(df, nodes)
    return _rows(spark, [(n, c) for n in nodes for c in sorted(down[n] - {n})], "node string, column_name string")


@query(_descendants_sql(PURCHASES, ("l_orderkey", "l_partkey", "o_custkey"), _P_COLS))
def descendants_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _descend(spark, workloads.purchases(spark, sf_dir), ("l_orderkey", "l_partkey", "o_custkey"))


@query(_descendants_sql(SALES, ("l_orderkey", "l_suppkey", "c_nationkey"), _S_COLS))
def descendants_sales_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _descend(spark, workloads.sales_wide(spark, sf_dir), ("l_orderkey", "l_suppkey", "c_nationkey"))


@query(f"""with t as materialized ({KPI}) select distinct string_agg(b, ' ' order by b) as columns from (
{" union all ".join(f"select '{a}' as a, '{b}' as b where {_r((a,), 't')} = {_r(tuple(dict.fromkeys((a, b))), 't')} and {_r((b,), 't')} = {_r(tuple(dict.fromkeys((a, b))), 't')}" for a in _K_COLS for b in _K_COLS)}
) group by a""")  # fmt: skip
def equivalent_columns_kpi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rows(spark, [(_name(c),) for c in dependency.equivalent_columns(workloads.kpi_wide(spark, sf_dir))], "columns string")


@query(" union all ".join(f"select '{c}' as column_name where {_r([x for x in _LINEITEM if x != c], 'lineitem')} < {_r(_LINEITEM, 'lineitem')}" for c in _LINEITEM))
def essential_columns_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = Problem(DistinctCounter(load(spark, sf_dir, "lineitem")))
    return _rows(spark, [(c,) for c in forward.essential_columns(p)], "column_name string")


@query(" union all ".join(f"select '{c}' as column_name where {_r(_ESSENTIAL, 'lineitem')} = {_r(_LINEITEM, 'lineitem')} and {_r([x for x in _ESSENTIAL if x != c], 'lineitem')} < {_r(_LINEITEM, 'lineitem')}" for c in _ESSENTIAL))
def essential_columns_line_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Without the price and the date, all keys of lineitem need the order."""
    p = Problem(DistinctCounter(load(spark, sf_dir, "lineitem")), pool=_ESSENTIAL)
    return _rows(spark, [(c,) for c in forward.essential_columns(p)], "column_name string")


_DOUBLES = {"customer": ["c_acctbal"], "supplier": ["s_acctbal"], "part": ["p_retailprice"], "orders": ["o_totalprice"], "lineitem": ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], "events": ["value"]}


@query(" union all ".join(f"select '{t}' as table_name, '{c}' as column_name from {t} having bool_or({c} <> floor({c}))" for t, cs in _DOUBLES.items() for c in cs))
def decimal_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rows(spark, [(t, c) for t in _DOUBLES for c in C.decimal_columns(load(spark, sf_dir, t))], "table_name string, column_name string")


@query(" union all ".join(f"select '{c}' as column_name, {_r((c,), 'orders')} as r, count(*) filter ({c} is null) as nulls from orders" for c in _ORDERS))
def column_profile_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.profile(load(spark, sf_dir, "orders"), exact=True).select("column_name", "r", "nulls")


@query("select l_returnflag, l_linestatus, l_linenumber, count(*) as weight from lineitem group by all")
def weighted_set_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return enforce_set(load(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus", "l_linenumber"), "weight")


def _is_minimal_sql(sets: Sequence[Sequence[str]]) -> str:
    parts = []
    for s in sets:
        less = [f"{_r([x for x in s if x != c], 'lineitem')} < {_r(_LINEITEM, 'lineitem')}" for c in s if len(s) > 1]
        parts.append(f"select '{_name(s)}' as columns, {' and '.join([f'{_r(s, "lineitem")} = {_r(_LINEITEM, "lineitem")}', *less])} as minimal")
    return " union all ".join(parts)


_TRIED = (("l_orderkey", "l_extendedprice"), ("l_orderkey", "l_partkey"), ("l_orderkey", "l_partkey", "l_suppkey"), ("l_orderkey", "l_extendedprice", "l_tax"))


@query(_is_minimal_sql(_TRIED))
def minimal_tests_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    counter = DistinctCounter(load(spark, sf_dir, "lineitem"))
    return _rows(spark, [(_name(s), dependency.is_minimal(counter, s, ROW)) for s in _TRIED], "columns string, minimal boolean")


_TRIED_FD = (("o_orderkey",), ("o_custkey", "o_orderdate"), ("o_orderkey", "o_orderstatus"), ("o_custkey", "o_orderdate", "o_orderpriority"), ("o_orderstatus",))


def _is_minimal_fd_sql(sets: Sequence[Sequence[str]], y: str, t: str) -> str:
    fd = lambda s: f"{_r(s, t)} = {_r(tuple(dict.fromkeys((*s, y))), t)}"
    return " union all ".join(f"select '{_name(s)}' as columns, {' and '.join([fd(s), *[f'not ({fd([x for x in s if x != c])})' for c in s]])} as minimal" for s in sets)


@query(_is_minimal_fd_sql(_TRIED_FD, "o_totalprice", "orders"))
def minimal_fd_tests_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    counter = DistinctCounter(load(spark, sf_dir, "orders"))
    return _rows(spark, [(_name(s), dependency.is_minimal(counter, s, "o_totalprice")) for s in _TRIED_FD], "columns string, minimal boolean")


_V = "row_number() over (partition by text order by n desc, source)"
_RANKED = f"with g as (select text, source, count(*) n from documents group by all), k as (select text, source, {_V} as rank from g)"


@query(f"{_RANKED} select doc_id, d.source from documents d join k on d.text = k.text and d.source = k.source where rank > 1")
def violations_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dependency.violations(load(spark, sf_dir, "documents"), ["text"], ["source"]).select("doc_id", "source")


@query(f"{_RANKED} select doc_id, d.source from documents d join k on d.text = k.text and d.source = k.source where rank = 1")
def repair_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dependency.repair(load(spark, sf_dir, "documents"), ["text"], ["source"]).select("doc_id", "source")


# -- forward addition and its variants --------------------------------------------
@query(_forward_sql(_ORDERS_WALKS, "orders", _key_of(_ORDERS, "orders")))
def fa_key_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _walks(spark, Problem(DistinctCounter(load(spark, sf_dir, "orders"))), _ORDERS_WALKS, forward.forward_key)


@query(_forward_sql(_CUSTOMER_WALKS, "customer", _key_of(_CUSTOMER, "customer")))
def fa_key_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _walks(spark, Problem(DistinctCounter(load(spark, sf_dir, "customer"))), _CUSTOMER_WALKS, forward.forward_key)


_FD_POOL = tuple(c for c in _ORDERS if c != "o_custkey")
_FD_WALKS = (_FD_POOL[::-1], permute(_FD_POOL, 5), permute(_FD_POOL, 6))


@query(_forward_sql(_FD_WALKS, "orders", lambda s: f"{_r(s, 'orders')} = {_r((*s, 'o_custkey'), 'orders')}"))
def fa_fd_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _walks(spark, Problem(DistinctCounter(load(spark, sf_dir, "orders")), "o_custkey"), _FD_WALKS, forward.forward_search)


_DOC_WALKS = (("text", "n_chars", "source"), ("source", "n_chars", "text"))


def _row_error(table: str, lhs: Sequence[str], rhs: str, eps: str) -> str:
    c = ", ".join(lhs)
    return f"(select 1 - sum(m) / sum(n) from (select max(n) m, sum(n) n from (select {c}, {rhs}, count(*) n from {table} group by all) group by {c})) <= {eps}"


@query(_forward_sql(_DOC_WALKS, "documents", lambda s: _row_error("documents", s, "lang", "0.06")))
def fa_approx_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load(spark, sf_dir, "documents").select("text", "n_chars", "source", "lang")
    return _walks(spark, Problem(DistinctCounter(df), "lang", 0.06), _DOC_WALKS, forward.forward_search)


_EPS = ("0.001", "0.005", "0.01", "0.05", "0.1")


@query(" union all ".join(f"select {e} as eps, * from ({_forward_sql(_DOC_WALKS, 'documents', lambda s, e=e: _row_error('documents', s, 'lang', e))}) where columns is not null" for e in _EPS))
def fa_eps_grid_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W6: the answer at each error of a grid."""
    counter = DistinctCounter(load(spark, sf_dir, "documents").select("text", "n_chars", "source", "lang"))
    out = []
    for e in _EPS:
        for i, w in enumerate(_DOC_WALKS):
            got = forward.forward_search(Problem(counter, "lang", Fraction(e)), w)
            if got.found:
                out.append((Decimal(e), i, _name(got.columns), got.size))
    return _rows(spark, out, "eps decimal(4,3), order_id int, columns string, n_columns long")


def _prefixes_sql(kept: tuple[str, ...], pool: tuple[str, ...], ok: Callable[[Sequence[str]], str], limit: int) -> str:
    """Column additions as nested cases, one for each outcome: the test need not be monotone."""
    known = lambda s: f"'{_name(s)}'"
    if len(kept) == limit:
        return f"case when {ok(kept)} then {known(kept)} end"
    cases = [f"when {ok(kept + pool[: h + 1])} then {_prefixes_sql((*kept, pool[h]), pool[:h], ok, limit)}" for h in range(len(pool))]
    return f"case when {ok(kept)} then {known(kept)} {' '.join(cases)} end"


_RATIO = (
    ("documents", "lang", ("n_chars", "source", "text"), ("0.01", "0.05", "0.1", "0.5")), ("conversations", "role", ("turn", "conv_id", "text"), ("0.1", "0.5")),
    ("part", "p_brand", ("p_retailprice", "p_size", "p_type", "p_name"), ("0.05", "0.2", "0.5")), ("events", "event_type", ("props", "user_id", "value"), ("0.1", "0.25")),
    ("orders", "o_orderstatus", ("o_orderpriority", "o_custkey", "o_orderdate", "o_totalprice"), ("0.01", "0.4", "0.7")),
)


def _ratio_sql(table: str, y: str, pool: tuple[str, ...], eps: str) -> str:
    sets = [(), *_subsets(pool, len(pool))]
    one = ", ".join(f"1 - {_r(s, table)} / {_r((*s, y), table)} as e{sum(1 << pool.index(c) for c in s)}" for s in sets)
    ok = lambda s: f"e{sum(1 << pool.index(c) for c in s)} <= {eps}"
    walks = ((0, pool), (1, pool[::-1]))
    return " union all ".join(f"select '{table}' as table_name, {eps} as eps, {i} as order_id, {_prefixes_sql((), w, ok, len(w))} as columns from (select {one})" for i, w in walks)


@query("select * from (" + " union all ".join(_ratio_sql(t, y, pool, e) for t, y, pool, grid in _RATIO for e in grid) + ") where columns is not null")
def fa_ratio_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Forward addition under the ratio error, which may rise with a column added."""
    out = []
    for table, y, pool, grid in _RATIO:
        counter = DistinctCounter(load(spark, sf_dir, table).select(*pool, y))
        for e in grid:
            for i, w in enumerate((pool, pool[::-1])):
                got = forward.forward_search(Problem(counter, y, Fraction(e), "ratio", pool), w)
                if got.found:
                    out.append((table, Decimal(e), i, _name(got.columns)))
    return _rows(spark, out, "table_name string, eps decimal(3,2), order_id int, columns string")


@query(_forward_sql(_ORDERS_WALKS, "orders", _key_of(_ORDERS, "orders")))
def be_key_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _walks(spark, Problem(DistinctCounter(load(spark, sf_dir, "orders"))), _ORDERS_WALKS, baselines.backward_search)


@query("select cast(range as int) as seed, true as same from range(6)")
def fa_equals_be(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = Problem(DistinctCounter(load(spark, sf_dir, "orders")))
    out = []
    for seed in range(6):
        order = permute(_ORDERS, seed)
        out.append((seed, set(forward.forward_search(p, order).columns) == set(baselines.backward_search(p, order).columns)))
    return _rows(spark, out, "seed int, same boolean")


@query("select s as sweep, columns, n_columns from (select unnest(['linear', 'bisect', 'kary', 'rollup', 'sorted', 'sketch', 'sample']) as s) cross join (" + _forward_sql(_ORDERS_WALKS[:1], "orders", _key_of(_ORDERS, "orders")) + ")")
def sweeps_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []
    for name in forward.SWEEPS:
        p = Problem(DistinctCounter(load(spark, sf_dir, "orders")))  # nothing known from another sweep
        got = forward.forward_search(p, _ORDERS_WALKS[0], sweep=name)
        out.append((name, _name(got.columns), got.size))
    return _rows(spark, out, "sweep string, columns string, n_columns long")


_N_SORTED = " union all ".join(f"select {i} as n_columns, {_r(_LINEITEM[:i], 'lineitem')} as r" for i in range(1, len(_LINEITEM) + 1))


@query(_N_SORTED)
def prefix_counts_sorted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rows(spark, list(enumerate(counting.sorted_profile(load(spark, sf_dir, "lineitem"), _LINEITEM), 1)), "n_columns int, r long")


@query(_N_SORTED)
def prefix_counts_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rows(spark, list(enumerate(counting.prefix_rollup(load(spark, sf_dir, "lineitem"), _LINEITEM), 1)), "n_columns int, r long")


def _shortest_sql(columns: Sequence[str], table: str, limit: int, eps: Sequence[str]) -> str:
    parts = [f"select {e} as eps, cast(min(size) as bigint) as n_columns from s where 1 - r / {_r(columns, table)} <= {e}" for e in eps]
    return f"with s as ({_subset_counts(columns, table, limit)}) " + " union all ".join(f"select * from ({p}) where n_columns is not null" for p in parts)


_K_DISCRETE = ("user_id", "day", "slot", "c_nationkey", "c_mktsegment", "n_events", "n_err")


@query(f"with t as materialized ({KPI}), s as ({_subset_counts(_K_DISCRETE, 't', 3)}) select cast(size as bigint) as n_columns, names as columns from s where r = {_r(_K_COLS, 't')} order by size, names limit 1")
def shortest_key_kpi(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = Problem(DistinctCounter(workloads.kpi_wide(spark, sf_dir)), pool=_K_DISCRETE)
    got = shortest.shortest_within_error(p, 3)
    return _rows(spark, [(got.size, _name(got.columns))], "n_columns long, columns string")


_O_POOL = ("o_custkey", "o_orderdate", "o_orderpriority", "o_orderstatus")


def _ratio(s: Sequence[str], y: str, t: str) -> str:
    return f"1 - {_r(s, t)} / {_r((*s, y), t)}"


@query("select eps, cast(min(size) as bigint) as n_columns from (" + " union all ".join(f"select '{e}' as eps, {len(s)} as size where {_ratio(s, 'o_orderkey', 'orders')} <= {e}" for e in ("0.001", "0.005", "0.05") for s in _subsets(_O_POOL, 4)) + ") group by eps")
def shortest_eps_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    counter = DistinctCounter(load(spark, sf_dir, "orders"))
    out = []
    for e in ("0.001", "0.005", "0.05"):
        got = shortest.shortest_within_error(Problem(counter, "o_orderkey", Fraction(e), "ratio", _O_POOL), 4)
        if got.found:
            out.append((e, got.size))
    return _rows(spark, out, "eps string, n_columns long")


_ME_POOL = ("c_nationkey", "c_acctbal", "c_mktsegment")


@query(f"with s as ({_subset_counts(_ME_POOL, 'customer', 2)}), e as (select size, 1 - r / {_r(_CUSTOMER, 'customer')} as error from s where 1 - r / {_r(_CUSTOMER, 'customer')} <= 0.05) select round(error, 6) as error, cast(size as bigint) as n_columns from e order by e.error, size limit 1")
def min_error_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    counter = DistinctCounter(load(spark, sf_dir, "customer"))
    got = shortest.shortest_min_error(Problem(counter, ROW, 0.05, pool=_ME_POOL), 2)
    return _rows(spark, [(round(float(got.error), 6), got.size)] if got.found else [], "error double, n_columns long")


_GRID = ("0.0", "0.001", "0.01", "0.05")


@query(f"with s as ({_subset_counts(_ME_POOL, 'customer', 2)}), g as (select unnest([0.0, 0.001, 0.01, 0.05]::double[]) as eps) select eps, cast(min(size) as bigint) as n_columns from s, g where 1 - r / {_r(_CUSTOMER, 'customer')} <= eps group by eps order by eps limit 1")
def grid_min_error_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    counter = DistinctCounter(load(spark, sf_dir, "customer"))
    p = Problem(counter, ROW, 0.05, pool=_ME_POOL)
    got = baselines.grid_min_error(p, _GRID, 2)
    grid = [float(g) for g in _GRID if got.found and got.error <= Fraction(g)]
    return _rows(spark, [(min(grid), got.size)] if got.found else [], "eps double, n_columns long")


@query("select names as columns from (" + _subset_counts(("event_id", "ts", "user_id", "event_type"), "events", 1) + f") where r = {_r(('event_id', 'ts', 'user_id', 'event_type'), 'events')} and names <> 'event_id'")
def adaptive_second_key_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = Problem(DistinctCounter(load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")))
    got = shortest.next_solution(p, ["event_id"], 1, seed=4)
    return _rows(spark, [(_name(got.columns),)] if got.found else [], "columns string")


def _keys(spark: SparkSession, found: Sequence[Sequence[str]]) -> DataFrame:
    return _rows(spark, [(_name(s), len(s)) for s in found], "columns string, n_columns long")


@query(_minimal_keys_sql(_ORDERS, "orders", 6))
def all_keys_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, shortest.enumerate_solutions(Problem(DistinctCounter(load(spark, sf_dir, "orders")))))


# -- baselines --------------------------------------------------------------------
@query(_minimal_keys_sql(_ORDERS, "orders", 3))
def minimal_uniques_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, baselines.brute_force(Problem(DistinctCounter(load(spark, sf_dir, "orders"))), 3))


@query(_minimal_keys_sql(_LINEITEM, "lineitem", 2))
def minimal_uniques_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, baselines.brute_force(Problem(DistinctCounter(load(spark, sf_dir, "lineitem"), batch=12)), 2))


def _levelwise_sql(columns: Sequence[str], table: str, limit: int) -> str:
    place = {c: i for i, c in enumerate(columns)}
    rows = [
        f"select '{_name(s)}' as lhs, '{y}' as rhs, {sum(1 << place[c] for c in s)} as mask where {_r(s, table)} = {_r((*s, y), table)}"
        for s in [(), *_subsets(columns, limit)] for y in columns if y not in s
    ]
    return f"with d as ({' union all '.join(rows)}) select lhs, rhs from d where not exists (select 1 from d e where e.rhs = d.rhs and e.mask & d.mask = e.mask and e.mask <> d.mask)"


@query(_levelwise_sql(_CUSTOMER, "customer", 2))
def levelwise_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = baselines.levelwise(DistinctCounter(load(spark, sf_dir, "customer")), 2)
    return _rows(spark, [(_name(lhs), y) for lhs, y in found], "lhs string, rhs string")


@query(_minimal_keys_sql(("s_suppkey", "s_name", "s_nationkey", "s_acctbal"), "supplier", 4))
def row_wise_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, baselines.row_wise(load(spark, sf_dir, "supplier")))


@query(_minimal_keys_sql(_ORDERS, "orders", 3))
def hybrid_keys_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, baselines.hybrid_search(Problem(DistinctCounter(load(spark, sf_dir, "orders"))), 3))


@query(_minimal_keys_sql(_CUSTOMER, "customer", 3))
def cube_keys_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, baselines.cube_keys(load(spark, sf_dir, "customer"), 3))


@query(" union all ".join(f"select '{_name(_ORDERS[i : i + d])}' as columns, cast({d} as bigint) as n_columns where {_r(_ORDERS[i : i + d], 'orders')} = {_r(_ORDERS, 'orders')}" for d in (1, 2, 3) for i in range(6 - d + 1)))
def adjacent_keys_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keys(spark, baselines.adjacent_keys(Problem(DistinctCounter(load(spark, sf_dir, "orders"))), 3))


@query(_minimal_keys_sql(("event_id", "ts", "user_id", "event_type"), "events", 1))
def restart_keys_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = Problem(DistinctCounter(load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")))
    return _keys(spark, baselines.restart_enumeration(p, 16, limit=1))


# -- trees --------------------------------------------------------------------------
_W1_SEED = 0


def _purchases_tree(df: DataFrame) -> SchemaTree:
    """W1: an error of 0.005 in distinct rows."""
    return SchemaTree.discover(df, stage=False, D=3, eps=0.005, measure="ratio", seed=_W1_SEED)


def _edge_sql(table: str, edges: Sequence[tuple], total: Sequence[str], eps: str = "0", decimals: Sequence[str] = ()) -> str:
    """Tree rows, each only if the data bear it out.

    A column hangs below a parent that determines it; a split determines its parent within the error, and no single column below the parent does;
    a leaf hangs on the deepest node that determines it.
    """
    depth = {n: d for n, _, d, _ in edges}
    inner = {n for n, _, _, k in edges if k == "skeleton"}
    splits: dict[str, tuple[str, ...]] = {}
    for n, p, _, k in edges:
        if k == "skeleton":
            splits[p] = (*splits.get(p, ()), n)
    up = {n: p for n, p, _, _ in edges}
    count = {}

    def r(columns: Sequence[str]) -> str:
        """Name of a count in the one-row table of all counts."""
        return count.setdefault(tuple(sorted(set(columns))), f"r{len(count)}")

    fd = lambda a, c: f"{r((a, c))} = {r((a,))}"
    parts = ["select '<row>' as node, cast(null as varchar) as parent, 0 as depth, 'root' as kind"]
    for node, parent, d, kind in edges:
        tests = [] if parent == ROW else [fd(parent, node)]
        if kind == "leaf":
            tests += [f"not ({fd(n, node)})" for n in sorted(inner) if depth[n] > (depth[parent] if parent != ROW else 0)]
        else:
            whole = total if parent == ROW else (*splits[parent], parent)
            tests.append(f"1 - {r(splits[parent])} / {r(whole)} <= {eps}")
            below = [c for c in total if c not in decimals and c != parent and (parent == ROW or c in up and parent in _above(up, c)) and len(splits[parent]) > 1]
            tests += [f"1 - {r((c,))} / {r(total if parent == ROW else (c, parent))} > {eps}" for c in below]
        parts.append(f"select '{node}', '{parent}', {d}, '{kind}' from counts where {' and '.join(tests) or 'true'}")
    counts = ", ".join(f"{_r(c, 't')} as {n}" for c, n in count.items())
    return f"with t as materialized ({table}), counts as materialized (select {counts}) " + " union all ".join(parts)


def _above(up: dict[str, str], node: str) -> list[str]:
    out = []
    while (node := up.get(node)) is not None:
        out.append(node)
    return out


_W1_EDGES = (
    ("l_orderkey", ROW, 1, "skeleton"), ("l_partkey", ROW, 1, "skeleton"), ("o_custkey", "l_orderkey", 2, "skeleton"), ("o_orderdate", "l_orderkey", 2, "skeleton"),
    ("o_orderpriority", "l_orderkey", 2, "leaf"), ("o_orderstatus", "l_orderkey", 2, "leaf"), ("qty", ROW, 1, "leaf"), ("amount", ROW, 1, "leaf"),
    *((c, "o_custkey", 3, "leaf") for c in ("c_name", "c_nationkey", "c_mktsegment", "c_acctbal")),
    *((c, "l_partkey", 2, "leaf") for c in ("p_name", "p_brand", "p_type", "p_size", "p_retailprice")),
)


_W1_RELATIONS = (
    (("l_orderkey", "l_partkey"), ROW, "both", f"{_r(('l_orderkey', 'l_partkey'), 't')} = {_r(_P_COLS, 't')}"),
    (("o_custkey", "o_orderdate"), "l_orderkey", "approximate", f"{_r(('o_custkey', 'o_orderdate'), 't')} < {_r(('l_orderkey', 'o_custkey', 'o_orderdate'), 't')}"),
    *(((p,), n, "one-way", "true" if p == ROW else f"{_r((p, n), 't')} = {_r((p,), 't')}") for n, p, _, k in _W1_EDGES if k == "leaf"),
)


@query(_edge_sql(PURCHASES, _W1_EDGES, _P_COLS, "0.005", ("amount", "c_acctbal", "p_retailprice")))
def tree_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _purchases_tree(staged(workloads.purchases(spark, sf_dir))).to_df(spark).select("node", "parent", "depth", "kind")


_W2_EDGES = (
    ("user_id", ROW, 1, "skeleton"), ("day", ROW, 1, "skeleton"), ("slot", ROW, 1, "skeleton"), ("day_no", "day", 2, "leaf"),
    *((c, "user_id", 2, "leaf") for c in ("c_name", "c_nationkey", "n_name", "n_regionkey", "c_mktsegment")),
    *((c, ROW, 1, "leaf") for c in ("n_events", "n_err", "mean_value", "max_value")),
)


@query(_edge_sql(KPI, _W2_EDGES, _K_COLS, "0", ("mean_value", "max_value")))
def tree_kpi(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = SchemaTree.discover(workloads.kpi_wide(spark, sf_dir), D=3)
    return tree.to_df(spark).select("node", "parent", "depth", "kind")


def _realisations_sql(table: str, pool: Sequence[str], root: str) -> str:
    """Splits of the first node: all the shortest sets that determine it, without itself and its twins."""
    sets = _subset_counts([c for c in pool if c != root], table, 2)
    return f"""with s as ({sets}), k as (select * from s where r = {_r(pool, table)})
select '<row>' as node, '{root}' as columns where {_r((root,), table)} = {_r(pool, table)} union all select '{root}', names from k where size = (select min(size) from k)"""


def _realisations(spark: SparkSession, df: DataFrame, seeds: int) -> DataFrame:
    """W3: the splits of the first two levels over the different trees of a table."""
    from depstrata.plans.tree import discover_many

    trees = discover_many(df, range(seeds), D=2, decimals="off", twins="keep")
    first = {s.children[0] for t in trees.values() for s in t.splits if s.parent == ROW and len(s.children) == 1}
    out = {(s.parent, _name(s.children)) for t in trees.values() for s in t.splits if s.parent in (ROW, *first)}
    return _rows(spark, sorted(out), "node string, columns string")


@query(_realisations_sql("orders", _ORDERS, "o_orderkey"))
def tree_orders_realisations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _realisations(spark, load(spark, sf_dir, "orders"), 12)


@query(_realisations_sql("(select * exclude (c_name) from customer)", [c for c in _CUSTOMER if c != "c_name"], "c_custkey"))
def tree_customer_realisations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Without the name, the key's twin."""
    return _realisations(spark, load(spark, sf_dir, "customer").drop("c_name"), 12)


@query(f"""with t as materialized ({PURCHASES}), e as ({" union all ".join(f"select '{' '.join(sorted(lhs))}' as lhs, '{rhs}' as rhs, '{kind}' as kind where {test}" for lhs, rhs, kind, test in _W1_RELATIONS)}) select * from e""")
def relations_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joint relations of splits and one-way relations of leaves."""
    return _purchases_tree(staged(workloads.purchases(spark, sf_dir))).relations(spark).select("lhs", "rhs", "kind")


@query(f"""with t as materialized ({PURCHASES}), c as (select {_r(_P_COLS, 't')} * 17 as cells, {_r(('l_orderkey', 'l_partkey', 'qty', 'amount'), 't')} * 4 + {_r(('l_orderkey',), 't')} * 5 + {_r(('o_custkey',), 't')} * 5 + {_r(('l_partkey',), 't')} * 6 as layered)
select 'nodes' as measure, 18.0::double as value union all select 'skeleton', 5 union all select 'splits', 2 union all select 'leaves', 13 union all select 'depth', 3 union all select 'compression', round(layered / cells, 6) from c""")  # fmt: skip
def tree_measures_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = staged(workloads.purchases(spark, sf_dir))
    tree = _purchases_tree(df)
    return _rows(spark, [*((k, float(v)) for k, v in tree.stats().items()), ("compression", round(tree.compression(df), 6))], "measure string, value double")


@query(f"""with t as materialized (select *, case when (l_orderkey + l_partkey) % 1000 = 7 then 'other' else c_mktsegment end as seg from ({PURCHASES})) select 'o_custkey' as node, 'c_mktsegment' as column_name where {_r(('o_custkey', 'seg'), 't')} > {_r(('o_custkey',), 't')}""")
def revalidate_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W9: edges of a tree that changed rows break."""
    df = staged(workloads.purchases(spark, sf_dir))
    tree = _purchases_tree(df)
    odd = (F.col("l_orderkey") + F.col("l_partkey")) % 1000 == 7
    return _rows(spark, tree.broken_edges(df.withColumn("c_mktsegment", F.when(odd, "other").otherwise(F.col("c_mktsegment")))), "node string, column_name string")


_SMALL = {
    "region": ("r_regionkey", "r_name"), "nation": ("n_nationkey", "n_name", "n_regionkey"), "supplier": ("s_suppkey", "s_name", "s_nationkey", "s_acctbal"),
    "part": ("p_name", "p_brand", "p_type", "p_size", "p_retailprice"), "labels": ("doc_id", "quality", "toxic"), "benchmark": ("item_id", "text"), "conversations": ("conv_id", "turn", "role"),
    "pages": ("url", "page_id"), "embeddings": ("label", "vec_id"), "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_shipdate"),
}


@query(" union all ".join(f"select '{t}' as table_name, cast(min(size) as bigint) as n_columns from ({_subset_counts(cols, t, 3)}) where r = {_r(cols, t)}" for t, cols in _SMALL.items()))
def shortest_keys_of_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W8: the size of the shortest key of each table."""
    out = []
    for t, cols in _SMALL.items():
        got = shortest.shortest_within_error(Problem(DistinctCounter(load(spark, sf_dir, t).select(*cols))), 3)
        out.append((t, got.size if got.found else None))
    return _rows(spark, out, "table_name string, n_columns long")


def _layer(spark: SparkSession, sf_dir: str, node: str) -> DataFrame:
    df = staged(workloads.purchases(spark, sf_dir))
    return _purchases_tree(df).decompose(df)[node]


@query(f"select distinct o_custkey, c_acctbal, c_mktsegment, c_name, c_nationkey from ({PURCHASES})")
def layers_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _layer(spark, sf_dir, "o_custkey")


@query(f"select distinct l_partkey, p_brand, p_name, p_retailprice, p_size, p_type from ({PURCHASES})")
def layers_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _layer(spark, sf_dir, "l_partkey")


@query(f"select distinct l_orderkey, o_custkey, o_orderdate, o_orderpriority, o_orderstatus from ({PURCHASES})")
def layers_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _layer(spark, sf_dir, "l_orderkey")


@query(PURCHASES)
def recompose_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = staged(workloads.purchases(spark, sf_dir))
    tree = _purchases_tree(df)
    return tree.recompose(tree.decompose(df))


# -- features -------------------------------------------------------------------------
def _flat(df: DataFrame) -> DataFrame:
    """Column names that SQL needs no quotes for; doubles rounded."""
    kinds = dict(df.dtypes)
    one = lambda c: F.round(F.col(f"`{c}`") + 1e-8, 5) if kinds[c] == "double" else F.col(f"`{c}`")
    return df.select(*[one(c).alias(c.replace("@", "_at_")) for c in df.columns])


@query(f"select distinct o_custkey, c_acctbal, c_mktsegment, c_name, c_nationkey from ({PURCHASES})")
def features_direct_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = staged(workloads.purchases(spark, sf_dir))
    return features.direct_features(df, _purchases_tree(df), "o_custkey").select("o_custkey", "c_acctbal", "c_mktsegment", "c_name", "c_nationkey")


_FUNC_SQL = {"max": "max({})", "mean": "avg({})", "std": "stddev_samp({})"}


def _two_level_sql(value: str, prefix: str) -> str:
    inner = ", ".join(f"{s.format(value)} as {f}_" for f, s in _FUNC_SQL.items())
    outer = ", ".join(f"round({s.format(f + '_')} + 1e-8, 5) as {prefix}__{f}_at_l_orderkey__{g}_at_o_custkey" for f in _FUNC_SQL for g, s in _FUNC_SQL.items())
    flat = ", ".join(f"round({s.format(value)} + 1e-8, 5) as {prefix}__{f}_at_o_custkey" for f, s in _FUNC_SQL.items())
    return f"""with t as materialized ({PURCHASES}), a as (select o_custkey, l_orderkey, {inner} from t group by all), b as (select o_custkey, {outer} from a group by all), c as (select o_custkey, {flat} from t group by all)
select * from b join c using (o_custkey)"""


def _customer_features(spark: SparkSession, sf_dir: str, targets: Sequence[str], functions=None) -> DataFrame:
    df = staged(workloads.purchases(spark, sf_dir))
    return _flat(features.build_features(df, _purchases_tree(df), "o_custkey", targets, functions))


@query(_two_level_sql("p_retailprice", "p_retailprice"))
def features_price_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_features(spark, sf_dir, ["p_retailprice"])


@query(_two_level_sql("amount", "amount"))
def features_amount_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_features(spark, sf_dir, ["amount"])


@query(_two_level_sql("qty", "qty").replace("round(max(max_) + 1e-8, 5)", "max(max_)").replace("round(max(qty) + 1e-8, 5)", "max(qty)"))
def features_qty_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_features(spark, sf_dir, ["qty"])


@query(f"select o_custkey, count(distinct o_orderpriority) as o_orderpriority__n_distinct_at_o_custkey from ({PURCHASES}) group by all")
def features_priority_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_features(spark, sf_dir, ["o_orderpriority"])


@query("select * from (values ('l_orderkey > o_custkey'), ('o_custkey')) as t(path)")
def features_price_subpaths(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = staged(workloads.purchases(spark, sf_dir))
    path = features.simplify_path(df, features.aggregation_path(_purchases_tree(df), "p_retailprice", "o_custkey"))
    return _rows(spark, [(" > ".join(w),) for w in features.subpaths(path)], "path string")


@query(f"""with t as materialized ({PURCHASES}), a as (select o_custkey, l_orderkey, count(distinct p_type) n from t group by all),
b as (select o_custkey, {', '.join(f"round({s.format('n')} + 1e-8, 5) as p_type__n_distinct_at_l_orderkey__{g}_at_o_custkey" for g, s in _FUNC_SQL.items())} from a group by all),
c as (select o_custkey, count(distinct p_type) as p_type__n_distinct_at_o_custkey from t group by all) select b.* replace (p_type__n_distinct_at_l_orderkey__max_at_o_custkey::bigint as p_type__n_distinct_at_l_orderkey__max_at_o_custkey), p_type__n_distinct_at_o_custkey from b join c using (o_custkey)""")  # fmt: skip
def features_categorical(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_features(spark, sf_dir, ["p_type"])


@query(f"""with t as materialized ({PURCHASES}), a as (select o_custkey, l_orderkey, avg(case when p_size >= 10 and p_size < 30 then 1.0 else 0.0 end) i, quantile_cont(p_size, 0.5) q from t group by all),
b as (select o_custkey, round(avg(case when i >= 10 and i < 30 then 1.0 else 0.0 end) + 1e-8, 5) p_size__in_10_30_at_l_orderkey__in_10_30_at_o_custkey, round(quantile_cont(i, 0.5) + 1e-8, 5) p_size__in_10_30_at_l_orderkey__q50_at_o_custkey,
round(avg(case when q >= 10 and q < 30 then 1.0 else 0.0 end) + 1e-8, 5) p_size__q50_at_l_orderkey__in_10_30_at_o_custkey, round(quantile_cont(q, 0.5) + 1e-8, 5) p_size__q50_at_l_orderkey__q50_at_o_custkey from a group by all),
c as (select o_custkey, round(avg(case when p_size >= 10 and p_size < 30 then 1.0 else 0.0 end) + 1e-8, 5) p_size__in_10_30_at_o_custkey, round(quantile_cont(p_size, 0.5) + 1e-8, 5) p_size__q50_at_o_custkey from t group by all) select * from b join c using (o_custkey)""")  # fmt: skip
def features_interval_quantile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_features(spark, sf_dir, ["p_size"], [A.interval_probability(10, 30), A.quantile(0.5)])


@query("select l_suppkey, round(max(l_quantity) + 1e-8, 5) as l_quantity__max_at_l_suppkey, round(avg(l_quantity) + 1e-8, 5) as l_quantity__mean_at_l_suppkey, round(stddev_samp(l_quantity) + 1e-8, 5) as l_quantity__std_at_l_suppkey, count(distinct l_returnflag) as l_returnflag__n_distinct_at_l_suppkey from lineitem group by all")
def features_shallow_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(features.shallow_features(load(spark, sf_dir, "lineitem"), "l_suppkey", ["l_quantity", "l_returnflag"]))


# -- theory ---------------------------------------------------------------------------
@query("select k, delta, cast(case when k = 1 then 1 else floor(ln(delta) / ln(1 - 1.0 / k)) + 1 end as bigint) as failures from (select distinct cast(k as int) as k from (select count(*) as k from lineitem group by l_orderkey)) cross join (select unnest([0.1, 0.01, 0.001]::double[]) as delta)")
def success_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The budget for as many answers as an order has lines, for each such number."""
    found = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").cast("int").alias("k")).select("k").distinct().collect()
    return _rows(spark, [(k, d, theory.failure_budget(k, d)) for k in sorted(r.k for r in found) for d in (0.1, 0.01, 0.001)], "k int, delta double, failures long")


@query("""with d as (select cast(row_number() over (order by l_returnflag) - 1 as int) as id, count(distinct l_orderkey)::double as d from lineitem group by l_returnflag)
select a.id, a.d as size, round(1 - sum(a.d / (a.d + b.d)) + any_value(a.d / (select sum(d) from d)), 9) as probability from d a join d b on a.id <> b.id group by a.id, a.d""")  # fmt: skip
def return_probabilities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of three answers as large as the sets of orders with a line of each return flag."""
    found = load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").alias("n")).orderBy("l_returnflag").collect()
    sizes = [r.n for r in found]
    return _rows(spark, [(i, float(d), round(float(p), 9)) for i, (d, p) in enumerate(zip(sizes, theory.return_probabilities(sizes)))], "id int, size double, probability double")


@query("select d, m, round(case d when 1 then m / n when 2 then m * (m - 1) / (n * (n - 1)) else m * (m - 1) * (m - 2) / (n * (n - 1) * (n - 2)) end, 9) as exact, round(pow(m / n, d), 9) as limit_law from (select unnest([1, 2, 3]) as d) cross join (select distinct cast(l_quantity as int) as m from lineitem) cross join (select max(l_quantity) as n from lineitem)")
def max_index_cdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For as many columns as the largest quantity of a line, at each quantity."""
    ms = sorted(r.m for r in load(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("int").alias("m")).distinct().collect())
    n = ms[-1]
    out = [(d, m, round(theory.max_index_cdf(d, m / n, n), 9), round(theory.max_index_cdf(d, m / n), 9)) for d in (1, 2, 3) for m in ms]
    return _rows(spark, out, "d int, m int, exact double, limit_law double")


_LINE_POOL = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_tax", "l_shipdate")


def _runs_sql(walks: Sequence[tuple[str, Sequence[str]]]) -> str:
    """The answers of forward addition on lineitem for orders of its columns, by the rule behind it: the key whose positions as bits make the least number."""
    first = f"with s as ({_subset_counts(_LINE_POOL, 'lineitem', len(_LINE_POOL))}), k as materialized (select * from s where r = {_r(_LINEITEM, 'lineitem')}) "
    code = lambda order: " + ".join(f"((mask >> {i}) & 1) * {1 << list(order).index(c)}" for i, c in enumerate(_LINE_POOL))
    return first + " union all ".join(f"select {tag}, arg_min(names, {code(order)}) as columns, cast(arg_min(size, {code(order)}) as bigint) as n_columns from k" for tag, order in walks)


_RUN_SEEDS = range(16)


@query(_runs_sql([(f"{i} as seed", permute(_LINE_POOL, i)) for i in _RUN_SEEDS]))
def fa_runs_sales_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W4: a run for each of several random orders on a table with many competing keys."""
    with shuffles_dropped(spark):
        df = staged(workloads.sales_keys(spark, sf_dir, _LINE_POOL))
        part = Part.of(df, lambda t: staged(t, "part"))
        p = Problem(DistinctCounter(df, part=part), pool=_LINE_POOL)
        if part is None:
            # A large table would be shuffled once for each set; there a part of the rows settles most tests, and what a run learns saves the next ones more.
            forward.prefetch(p, [permute(_LINE_POOL, i) for i in _RUN_SEEDS], None)
        out = []
        for i in _RUN_SEEDS:
            got = forward.random_forward(p, None, i)
            out.append((i, _name(got.columns), got.size))
    return _rows(spark, out, "seed int, columns string, n_columns long")


_SHORT = "(select min(size) from k)"


@query(
    _runs_sql([(f"{i} as seed", permute(_LINE_POOL, i)) for i in _RUN_SEEDS]).replace(") select", "), runs as (select", 1)
    + f"), m as (select count(*) as n from k where not exists (select 1 from k j where j.mask & k.mask = j.mask and j.mask <> k.mask)) select cast(n as bigint) as n_answers, count(*) as n_runs, count_if(n_columns = {_SHORT}) as n_shortest, count_if(n_columns = {_SHORT}) >= n_runs / n as at_least_1_in_k from runs, m group by n"
)
def success_sales_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W4: how often a run returns one of the shortest answers, beside the bound of 1 in K for K answers."""
    p = Problem(DistinctCounter(staged(workloads.sales_wide(spark, sf_dir).select(*_LINEITEM))), pool=_LINE_POOL)
    answers = shortest.enumerate_solutions(p)
    short = min(map(len, answers))
    hits = sum(forward.random_forward(p, None, i).size == short for i in _RUN_SEEDS)
    return _rows(spark, [(len(answers), len(_RUN_SEEDS), hits, hits >= len(_RUN_SEEDS) / len(answers))], "n_answers long, n_runs long, n_shortest long, at_least_1_in_k boolean")


def _twin_columns(n: int) -> list[str]:
    return [*_LINE_POOL, *[f"x{i}" for i in range(n - len(_LINE_POOL))]]


def _twin_of(c: str) -> str:
    return _LINE_POOL[int(c[1:]) % len(_LINE_POOL)] if c.startswith("x") else c


#: Columns and the ways to search among so many.
_WIDTHS = ((8, ("linear", "bisect", "kary", "backward")), (31, ("bisect", "backward")), (128, ("bisect",)), (512, ("bisect",)))
_TWIN_WALKS = {n: permute(_twin_columns(n), n) for n, _ in _WIDTHS}


@query("select *, true as within_bound from (" + _runs_sql([(f"{n} as n, '{m}' as method", list(dict.fromkeys(map(_twin_of, _TWIN_WALKS[n])))) for n, ms in _WIDTHS for m in ms]) + ")")
def evaluation_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W5: lineitem with 8 to 512 columns; the answer up to twins, and whether the evaluations are within the bound of forward addition or elimination."""
    out = []
    # Few large pieces of a file would be few tasks, and the wide table is not stored.
    base = staged(load(spark, sf_dir, "lineitem").select(*_LINE_POOL).repartition(2 * spark.sparkContext.defaultParallelism))
    # The columns of a table are the first ones of each wider one, so a count holds for all of them.
    known: dict[frozenset[str], int] = {}
    for n, ms in _WIDTHS:
        df = workloads.twinned(base, n)
        counter = DistinctCounter(df, twins=Twins(df), known=known)
        for m in ms:
            p = Problem(counter)
            got = baselines.backward_search(p, _TWIN_WALKS[n]) if m == "backward" else forward.forward_search(p, _TWIN_WALKS[n], sweep=m)
            bound = {"backward": theory.backward_bound(n), "bisect": theory.forward_bound(n, got.size), "linear": n * (got.size + 1) + 2, "kary": 4 * theory.forward_bound(n, got.size)}[m]
            out.append((n, m, _name({_twin_of(c) for c in got.columns}), got.size, got.evaluations <= bound))
    return _rows(spark, out, "n int, method string, columns string, n_columns long, within_bound boolean")


# -- surrounding operators ------------------------------------------------------------
@query(f"select r_name, p_brand, o_orderstatus, count(*) as n, sum(l_quantity) as qty, count(distinct s_name) as suppliers from ({SALES}) group by all")
def sales_wide_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.sales_wide(spark, sf_dir).groupBy("r_name", "p_brand", "o_orderstatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.count_distinct("s_name").alias("suppliers"))


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def top_k_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return features.top_k(load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", 20, ["o_orderkey"])


_GS = ("l_returnflag", "l_linestatus", "l_linenumber")


@query("select cast(set_id as bigint) as set_id, count(*) as r from (select grouping_id(l_returnflag, l_linestatus, l_linenumber) as set_id from lineitem group by rollup (l_returnflag, l_linestatus, l_linenumber)) group by set_id")
def grouping_sets_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counting.cuboids(load(spark, sf_dir, "lineitem"), _GS, "rollup")


@query("select cast(set_id as bigint) as set_id, count(*) as r from (select grouping_id(l_returnflag, l_linestatus, l_linenumber) as set_id from lineitem group by cube (l_returnflag, l_linestatus, l_linenumber)) group by set_id")
def cube_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counting.cuboids(load(spark, sf_dir, "lineitem"), _GS, "cube")


@query(f"""select user_id, strftime(day, '%Y-%m-%d') as day, slot, n_events, round(avg(n_events) over w, 6) as n_events_mean, max(n_events) over w as n_events_max, coalesce(n_events - lag(n_events) over (partition by user_id order by day, slot), 0) as n_events_step
from ({KPI}) window w as (partition by user_id order by day, slot rows between 3 preceding and current row)""")  # fmt: skip
def rolling_kpi(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = workloads.kpi_wide(spark, sf_dir).select("user_id", "day", "slot", "n_events").withColumn("at", F.struct("day", "slot"))
    out = features.rolling(df, ["user_id"], "at", "n_events", 4)
    return out.select("user_id", F.date_format("day", "yyyy-MM-dd").alias("day"), "slot", "n_events", F.round("n_events_mean", 6).alias("n_events_mean"), "n_events_max", F.coalesce("n_events_step", F.lit(0)).alias("n_events_step"))


@query("""select c.c_custkey, 'semi' as kind from customer c where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 300000)
union all select c.c_custkey, 'anti' from customer c where not exists (select 1 from orders where o_custkey = c_custkey)""")  # fmt: skip
def semi_anti_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = load(spark, sf_dir, "customer").select("c_custkey"), load(spark, sf_dir, "orders")
    semi = c.join(o.where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").withColumn("kind", F.lit("semi"))
    return semi.unionByName(c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").withColumn("kind", F.lit("anti")))


@query("""select 'both' as side, k from (select c_nationkey k from customer intersect select s_nationkey from supplier) union all select 'customer', k from (select c_nationkey k from customer except select s_nationkey from supplier)
union all select 'supplier', k from (select s_nationkey k from supplier except select c_nationkey from customer)""")  # fmt: skip
def set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    named = lambda df, n: df.select(F.lit(n).alias("side"), "k")
    return named(a.intersect(b), "both").unionByName(named(a.subtract(b), "customer")).unionByName(named(b.subtract(a), "supplier"))


@query("select event_type, cast(props->>'k' as int) as k, count(*) as n from events group by all")
def json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = workloads.events_props(spark, sf_dir)
    return e.groupBy("event_type", F.col("props")["k"].cast("int").alias("k")).agg(F.count("*").alias("n"))


@query("select regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, count(*) as n, cast(sum(length(html)) as bigint) as chars from pages group by all")
def url_host_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.pages_parsed(spark, sf_dir).groupBy("host").agg(F.count("*").alias("n"), F.sum("n_html").alias("chars"))


@query("select label, count(*) as n, min(len(embedding)) as dim, count(distinct embedding) as r from embeddings group by all")
def array_embedding_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "embeddings")
    return e.groupBy("label").agg(F.count("*").alias("n"), F.min(F.size("embedding")).cast("long").alias("dim"), F.count_distinct("embedding").alias("r"))


@query("""select e.event_id, (select arg_max(f.value, f.ts) from events f where f.user_id = e.user_id and f.event_type = 'view' and f.ts <= e.ts) as last_value from events e where e.event_type = 'purchase'""")
def asof_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    return features.asof(left, e.where("event_type = 'view'").select("user_id", "ts", "value"), "user_id", "ts", "value").select("event_id", "last_value")


def _event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = load(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


@query("select user_id, count(*) as n from events group by user_id having count(distinct event_type) > 1")
def stream_fd_monitor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streaming.collected(streaming.monitor(_event_stream(spark, sf_dir), ["user_id"], ["event_type"]), f"fd_{uuid.uuid4().hex}", "complete")


@query("""with p as (select date_trunc('day', ts) as start, user_id, event_type, count(*) n from events group by all), e as (select start, user_id, max(n) m, sum(n) n, count(*) k from p group by all)
select cast(start as timestamp) as start, cast(sum(n) as bigint) as n_rows, count(*) as r_lhs, cast(sum(k) as bigint) as r_both, round(1 - sum(m) / sum(n), 6) as error, round(1 - count(*) / sum(k), 6) as ratio
from e group by start having start + interval 1 day <= (select max(ts) - interval 1 hour from events)""")  # fmt: skip
def stream_windowed_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = streaming.with_watermark(_event_stream(spark, sf_dir))
    out = streaming.collected(streaming.windowed_error(stream, ["user_id"], ["event_type"]), f"we_{uuid.uuid4().hex}", "append")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)
