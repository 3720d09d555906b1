"""Features of an anchor entity: direct values, and aggregates along the tree's paths.

The path from a variable to the anchor is simplified: hops between levels that stand one to one are left out.  Every subpath
(each level between kept or skipped) gives features, with a function at each of its hops.  Subpaths
share their first hops, and all functions of a hop are one aggregation.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from depstrata.functions.aggregates import CATEGORICAL_FUNCS, NUMERIC_FUNCS, FeatureFunction
from depstrata.operators.counting import ROW
from depstrata.operators.dependency import descendants
from depstrata.plans.tree import SchemaTree


@dataclass(frozen=True)
class Path:
    variable: str
    levels: tuple[str, ...]  # nodes from the first above the variable to the anchor
    through_root: bool


def relation_kind(tree: SchemaTree, anchor: str, node: str) -> str:
    """one-to-one if the anchor has one value of the node, else one-to-many."""
    return "one-to-one" if node == anchor or node in tree.below(anchor) else "one-to-many"


def direct_columns(tree: SchemaTree, anchor: str, equivalents: Sequence[str] = ()) -> list[str]:
    """Columns below the anchor and the columns that are equivalent to it."""
    below = set(tree.below(anchor))
    for e in equivalents:
        below |= {e} | set(tree.below(e))
    return [c for c in tree.columns if c in below and c != anchor]


def direct_features(df: DataFrame, tree: SchemaTree, anchor: str, equivalents: Sequence[str] = ()) -> DataFrame:
    cols = direct_columns(tree, anchor, equivalents)
    return df.groupBy(anchor).agg(*[F.any_value(F.col(c)).alias(c) for c in cols])


def aggregation_path(tree: SchemaTree, node: str, anchor: str) -> Path:
    """Shortest way through the tree, without the row id and without combinations of columns, which are no entities."""
    up, to = tree.path_up(node), tree.path_up(anchor)
    meet = next(x for x in up if x in to)
    way = up[: up.index(meet) + 1] + to[: to.index(meet)][::-1]
    return Path(node, tuple(x for x in way[1:] if x != ROW and x not in tree.combinations), meet == ROW)


def simplify_path(df: DataFrame, path: Path) -> Path:
    """Leave out levels that the level kept before determines not at all to the contrary: a level is kept only if it groups several of the level before.

    A level v determines the one kept before it where there is one of that for each v: then aggregating by v adds nothing.
    """
    kept: list[str] = []
    before = path.variable
    for v in path.levels:
        if v == path.levels[-1] or before not in descendants(df.select(v, before), v, [before]):
            kept.append(v)
            before = v
    return Path(path.variable, tuple(kept), path.through_root)


def subpaths(path: Path) -> list[tuple[str, ...]]:
    """All ways to keep or skip the levels before the anchor."""
    *middle, anchor = path.levels
    return [(*c, anchor) for k in range(len(middle), -1, -1) for c in combinations(middle, k)]


def _kind(t: T.DataType) -> str:
    return "numeric" if isinstance(t, T.NumericType) else "categorical"


def path_features(df: DataFrame, path: Path, functions: Sequence[FeatureFunction] | None = None, grain: str = "top", max_hops: int | None = None) -> DataFrame:
    """One row for each anchor value, a column for each subpath and choice of functions: variable__f@level__g@anchor.

    grain top: a variable whose path stays below a node counts once for each value of that node; row: once for each row.
    """
    anchor = path.levels[-1]
    ways = [w for w in subpaths(path) if max_hops is None or len(w) <= max_hops]
    base = df.select(*dict.fromkeys([path.variable, *path.levels]))
    if grain == "top" and not path.through_root:
        base = base.distinct()
    kind = _kind(df.schema[path.variable].dataType)
    numeric = [f for f in (functions or NUMERIC_FUNCS) if f.kind == "numeric"]
    first = numeric if kind == "numeric" else [f for f in (functions or CATEGORICAL_FUNCS) if f.kind == "categorical"]
    later = numeric or list(NUMERIC_FUNCS)
    out: DataFrame | None = None
    # Ways that begin with one level share its aggregation.
    stages: dict[tuple[str, ...], tuple[DataFrame, list[str]]] = {}

    def stage(way: tuple[str, ...], rest: tuple[str, ...]) -> tuple[DataFrame, list[str]]:
        """Aggregate along way; keys of the levels in rest stay."""
        key = way
        if key not in stages:
            if len(way) == 1:
                source, values, fs = base, [path.variable], first
            else:
                source, values = stage(way[:-1], rest)
                fs = later
            keys = list(dict.fromkeys([way[-1], *[x for x in path.levels[path.levels.index(way[-1]) + 1 :]]]))
            made = [(f"{v}__{f.name}@{way[-1]}", f.build(F.col(f"`{v}`"))) for v in values for f in fs]
            stages[key] = source.groupBy(*keys).agg(*[c.alias(n) for n, c in made]), [n for n, _ in made]
        return stages[key]

    for way in ways:
        got, names = stage(way, ())
        got = got.select(anchor, *[F.col(f"`{n}`") for n in names])
        out = got if out is None else out.join(got, anchor, "full")
    return out


def build_features(
    df: DataFrame, tree: SchemaTree, anchor: str, targets: Sequence[str] | None = None, functions: Sequence[FeatureFunction] | None = None,
    max_hops: int | None = None, grain: str = "top", equivalents: Sequence[str] = (), max_features: int = 1000,
) -> DataFrame:
    """Direct and aggregated features of all targets, one row for each anchor value."""
    direct = direct_columns(tree, anchor, equivalents)
    wanted = list(targets if targets is not None else [c for c in tree.columns if c != anchor])
    out = df.select(anchor).distinct()
    own = [c for c in wanted if c in direct]
    if own:
        out = out.join(df.groupBy(anchor).agg(*[F.any_value(F.col(c)).alias(c) for c in own]), anchor, "left")
    for t in wanted:
        if t not in direct and t != anchor:
            path = simplify_path(df, aggregation_path(tree, t, anchor))
            out = out.join(path_features(df, path, functions, grain, max_hops), anchor, "left")
            if len(out.columns) > max_features:
                raise ValueError(f"more than {max_features} features: lower max_hops, or name fewer functions or targets")
    return out


def shallow_features(df: DataFrame, anchor: str, targets: Sequence[str], functions: Sequence[FeatureFunction] | None = None) -> DataFrame:
    """Baseline on a known, flat schema: one level of aggregates over rows."""
    made = []
    for t in targets:
        kind = _kind(df.schema[t].dataType)
        fs = [f for f in (functions or (*NUMERIC_FUNCS, *CATEGORICAL_FUNCS)) if f.kind == kind]
        made += [f.build(F.col(t)).alias(f"{t}__{f.name}@{anchor}") for f in fs]
    return df.groupBy(anchor).agg(*made)


def asof(left: DataFrame, right: DataFrame, on: str, ts: str, value: str) -> DataFrame:
    """Each row of left with the last value of right of the same key up to its time; one sort of the union, no range join."""
    a = left.withColumns({"side_": F.lit(1), f"last_{value}": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(on, ts, F.lit(0).alias("side_"), F.col(value).alias(f"last_{value}"))
    w = Window.partitionBy(on).orderBy(ts, "side_").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    return both.withColumn(f"last_{value}", F.last(f"last_{value}", ignorenulls=True).over(w)).where("side_ = 1").drop("side_")


def rolling(df: DataFrame, keys: Sequence[str], order: str, value: str, rows: int) -> DataFrame:
    """Mean and greatest of the last so many rows of each key, and the step from the row before."""
    w = Window.partitionBy(*keys).orderBy(order)
    last = w.rowsBetween(-(rows - 1), 0)
    made = {f"{value}_mean": F.avg(value).over(last), f"{value}_max": F.max(value).over(last), f"{value}_step": F.col(value) - F.lag(value).over(w)}
    return df.withColumns(made)


def top_k(df: DataFrame, by: str, k: int, ties: Sequence[str] = ()) -> DataFrame:
    return df.orderBy(F.desc(by), *ties).limit(k)
