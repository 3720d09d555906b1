"""Feature functions: each builds an aggregate expression from a column, so all stay in generated code."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class FeatureFunction:
    name: str
    kind: str  # numeric or categorical
    build: Callable[[Column], Column]


def interval_probability(lo: float, hi: float, name: str | None = None) -> FeatureFunction:
    """Share of values in [lo, hi); NULLs do not count."""
    inside = lambda c: F.avg(F.when(c.isNotNull(), F.when((c >= lo) & (c < hi), 1.0).otherwise(0.0)))
    return FeatureFunction(name or f"in_{lo:g}_{hi:g}", "numeric", inside)


def quantile(p: float, exact: bool = True) -> FeatureFunction:
    build = (lambda c: F.percentile(c, p)) if exact else (lambda c: F.percentile_approx(c, p))
    return FeatureFunction(f"q{round(100 * p)}", "numeric", build)


def n_distinct(nulls: str = "skip") -> FeatureFunction:
    """Number of values; nulls: skip them, or value: NULL is one."""
    extra = (lambda c: F.when(F.count_if(c.isNull()) > 0, 1).otherwise(0)) if nulls == "value" else (lambda c: F.lit(0))
    return FeatureFunction("n_distinct", "categorical", lambda c: F.count_distinct(c) + extra(c))


MAX = FeatureFunction("max", "numeric", F.max)
MEAN = FeatureFunction("mean", "numeric", F.avg)
STD = FeatureFunction("std", "numeric", F.stddev_samp)
N_DISTINCT = n_distinct()

NUMERIC_FUNCS: Sequence[FeatureFunction] = (MAX, MEAN, STD)
CATEGORICAL_FUNCS: Sequence[FeatureFunction] = (N_DISTINCT,)
