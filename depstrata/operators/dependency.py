"""Functional dependencies: tests, errors, descendants, equivalents, violations and repair."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from depstrata.functions.columns import canonical, decimal_columns, value_keys, value_parts
from depstrata.operators.counting import ROW, DistinctCounter, Part, Stats, exact

_CHUNK = 40  # columns in one aggregation, below the limit of generated code


@dataclass(frozen=True)
class Dependency:
    lhs: tuple[str, ...]
    rhs: tuple[str, ...] | str
    error: Fraction
    measure: str = "rows"

    @property
    def exact(self) -> bool:
        return self.error == 0


def dependency_stats(df: DataFrame, lhs: Iterable[str], rhs: Iterable[str] | str, weight: str | None = None) -> Stats:
    lhs, y = list(lhs), ([] if rhs == ROW else [rhs] if isinstance(rhs, str) else list(rhs))
    columns = None if rhs == ROW else list(dict.fromkeys([*lhs, *y]))
    return DistinctCounter(df, columns, weight).stats(lhs, rhs)


def error_rows(df: DataFrame, lhs: Iterable[str], rhs: Iterable[str] | str, weight: str | None = None) -> float:
    """Least share of rows to delete so that lhs determines rhs."""
    return float(dependency_stats(df, lhs, rhs, weight).error)


def error_ratio(df: DataFrame, lhs: Iterable[str], rhs: Iterable[str] | str) -> float:
    """1 - r(lhs) / r(lhs and rhs)."""
    return float(dependency_stats(df, lhs, rhs).ratio)


def holds(df: DataFrame, lhs: Iterable[str], rhs: Iterable[str] | str, eps: float | Fraction = 0, measure: str = "rows") -> bool:
    return dependency_stats(df, lhs, rhs).of(measure) <= exact(eps)


def is_minimal(counter: DistinctCounter, lhs: Iterable[str], rhs: Iterable[str] | str, eps: float | Fraction = 0, measure: str = "rows") -> bool:
    """lhs determines rhs and no set with one column less does; all tests in one batch."""
    lhs = frozenset(lhs)
    first, *less = counter.test_many([lhs, *[lhs - {c} for c in sorted(lhs)]], rhs, eps, measure)
    return first and not any(less)


def _one_value(name: str, kind: T.DataType):
    """Whether a group has one value of a column, NULL being one; min and max skip NULL, so it is counted."""
    c = F.col(f"`{name}`")
    if isinstance(kind, (T.ArrayType, T.StructType, T.BinaryType)):
        c = F.xxhash64(c, F.when(c.isNull(), 1).otherwise(0))
    return (F.min(c).eqNullSafe(F.max(c)) & ((F.count(c) == 0) | (F.count(c) == F.count("*")))).alias(name)


def descendants(df: DataFrame, target: Iterable[str] | str, candidates: Sequence[str] | None = None) -> set[str]:
    """Columns that the target determines: one aggregation for all of them, instead of one test each."""
    df = canonical(df)
    if target == ROW:
        return set(candidates if candidates is not None else df.columns)
    y = [target] if isinstance(target, str) else list(target)
    cols = [c for c in (candidates if candidates is not None else df.columns) if c not in y]
    out = {c for c in y if candidates is None or c in candidates}
    for at in range(0, len(cols), _CHUNK):
        part = cols[at : at + _CHUNK]
        each = df.groupBy(*[F.col(f"`{c}`") for c in y]).agg(*[_one_value(c, df.schema[c].dataType) for c in part])
        got = each.agg(*[F.coalesce(F.bool_and(f"`{c}`"), F.lit(True)).alias(c) for c in part]).first()
        out |= {c for c in part if got[c]}
    return out


def determined(df: DataFrame, nodes: Sequence[str], candidates: Sequence[str] | None = None) -> dict[str, set[str]]:
    """descendants() of several columns in one job: rows travel once for each node, as numbers of the node and of the candidates."""
    df = canonical(df)
    cols = list(candidates if candidates is not None else df.columns)
    used = list(dict.fromkeys([*nodes, *cols]))
    out: dict[str, set[str]] = {}
    slim = df.select(*[k for i, c in enumerate(used) for k in value_keys(c, df.schema[c].dataType, f"v{i}_")])
    place = {c: i for i, c in enumerate(used)}
    for at in range(0, len(cols), _CHUNK):
        part = cols[at : at + _CHUNK]
        keyed = F.explode(F.array(*[F.struct(F.lit(n).alias("node"), F.col(f"v{place[n]}_0").alias("a"), F.col(f"v{place[n]}_1").alias("b")) for n in nodes])).alias("k")
        rows = slim.select(keyed, *[f"v{place[c]}_{h}" for c in part for h in (0, 1)])
        one = [(F.min(f"v{place[c]}_{h}") == F.max(f"v{place[c]}_{h}")) for c in part for h in (0, 1)]
        each = rows.groupBy("k.node", "k.a", "k.b").agg(*[(x & y).alias(f"o{i}") for i, (x, y) in enumerate(zip(one[::2], one[1::2]))])
        found = {r.node: r for r in each.groupBy("node").agg(*[F.bool_and(f"o{i}").alias(f"o{i}") for i in range(len(part))]).collect()}
        for n in nodes:
            out.setdefault(n, set()).update(c for i, c in enumerate(part) if n not in found or found[n][f"o{i}"])
    return out


class Below:
    """The columns that a column determines, each asked for once.

    part: of a large table.  What it contradicts does not hold; what it leaves is settled on the table, as one number for all columns left, which
    together have one value exactly if each has.
    """

    def __init__(self, df: DataFrame, part: Part | None = None):
        self.df, self.part = canonical(df), part
        self._found: dict[str, set[str]] = {}

    def of(self, node: str) -> set[str]:
        if node not in self._found:
            self._found[node] = self._left(node) if self.part is not None else descendants(self.df, node)
        return self._found[node]

    def _left(self, node: str) -> set[str]:
        left = self.part.may_determine(node)
        if not left:
            return {node}
        values = [v for c in left for v in value_parts(c, self.df.schema[c].dataType)]
        each = self.df.select(F.col(f"`{node}`").alias("a"), *[F.xxhash64(F.lit(h), *values).alias(f"h{h}") for h in (0, 1)]).groupBy("a")
        same = each.agg(*[(F.min(f"h{h}") == F.max(f"h{h}")).alias(f"o{h}") for h in (0, 1)]).agg(F.bool_and("o0") & F.bool_and("o1")).first()[0]
        return {node, *left} if same is not False else determined(self.df, [node], [node, *left])[node]


def equivalent_columns(df: DataFrame, columns: Sequence[str] | None = None, part: Part | None = None) -> list[list[str]]:
    """Classes of columns that determine each other, sorted.

    Equivalent columns have the same number of distinct values, so only columns of equal counts are compared; all in one job, after one of counts.
    part: of a large table, of which only the columns that it leaves are compared.
    """
    cols = list(columns or df.columns)
    if part is not None:
        likely = part.may_be_equivalent(cols)
        return sorted([*equivalent_columns(df, likely), *([c] for c in cols if c not in likely)] if likely else [[c] for c in cols])
    r = DistinctCounter(df, cols, batch=64).count_many([[c] for c in cols])
    by: dict[int, list[str]] = {}
    for c in cols:
        by.setdefault(r[frozenset([c])], []).append(c)
    tried = [c for own in by.values() if len(own) > 1 for c in own]
    down = determined(df.select(*tried), tried) if tried else {}
    out, seen = [], set()
    for c in cols:
        if c not in seen:
            own = sorted(d for d in down.get(c, {c}) if c in down.get(d, {c})) if c in down else [c]
            seen |= set(own)
            out.append(own)
    return sorted(out)


def collapse_equivalents(df: DataFrame, columns: Sequence[str] | None = None, part: Part | None = None, decimals: Sequence[str] | None = None) -> dict[str, str]:
    """Column -> the column that stands for it, of each class of more than one: the first of the table that is no fraction, else the first."""
    order = list(columns or df.columns)
    decimals = set(decimal_columns(df.select(*order)) if decimals is None else decimals)
    out = {}
    for own in equivalent_columns(df, order, part):
        head = min(own, key=lambda c: (c in decimals, order.index(c)))
        out |= {c: head for c in own if c != head}
    return out


def violations(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> DataFrame:
    """Rows outside the majority of a group of lhs that has more than one rhs; ties keep the smallest rhs."""
    return _ranked(df, lhs, rhs).where("rank_ > 1").drop("n_", "rank_")


def repair(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> DataFrame:
    """Rows of the majority: lhs -> rhs holds, and the share of rows removed is the error."""
    return _ranked(df, lhs, rhs).where("rank_ = 1").drop("n_", "rank_")


def _ranked(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> DataFrame:
    # Counts are aggregated before they are ranked, so a frequent lhs is a few rows in the window.
    n = df.groupBy(*lhs, *rhs).agg(F.count("*").alias("n_"))
    order = F.row_number().over(Window.partitionBy(*lhs).orderBy(F.desc("n_"), *rhs))
    ranked = n.withColumn("rank_", order)
    renamed = ranked.select(*[F.col(c).alias(f"{c}__k") for c in (*lhs, *rhs)], "n_", "rank_")
    on = [F.col(c).eqNullSafe(F.col(f"{c}__k")) for c in (*lhs, *rhs)]
    return df.join(renamed, on).drop(*[f"{c}__k" for c in (*lhs, *rhs)])


def witnesses(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str] | str, k: int = 10) -> DataFrame:
    """All columns of up to two rows for each of at most k groups of lhs that have more than one rhs."""
    columns = df.columns
    y = F.struct(*(columns if rhs == ROW else rhs))
    pick = F.struct(*columns)
    groups = df.groupBy(*lhs).agg(F.min(y).alias("lo"), F.max(y).alias("hi"), F.min_by(pick, y).alias("one"), F.max_by(pick, y).alias("two"))
    bad = groups.where(~F.col("lo").eqNullSafe(F.col("hi"))).limit(k)
    return bad.select(F.explode(F.array("one", "two")).alias("row")).select("row.*")
