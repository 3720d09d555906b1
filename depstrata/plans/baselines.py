"""Baselines: elimination, exhaustive, levelwise, row-wise, hybrid, cube, grid, restarts, windows of columns."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from fractions import Fraction
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depstrata.functions.columns import canonical, digest
from depstrata.operators.counting import ROW, DistinctCounter, cuboids
from depstrata.plans.forward import random_forward
from depstrata.plans.problem import Problem, SearchResult
from depstrata.plans.shortest import shortest_within_error


def backward_search(p: Problem, order: Sequence[str] | None = None, limit: int | None = None) -> SearchResult:
    """Drop columns from the end of the order while the rest passes."""
    began, left = p.evaluations, [c for c in (order or p.pool) if c in set(p.pool)]
    if not p.ok(left):
        return SearchResult(False, (), p.evaluations - began)
    for c in reversed(list(left)):
        rest = [x for x in left if x != c]
        if p.ok(rest):
            left = rest
    found = limit is None or len(left) <= limit
    return SearchResult(found, tuple(left) if found else (), p.evaluations - began)


def brute_force(p: Problem, limit: int, minimal: bool = True) -> list[tuple[str, ...]]:
    """All (minimal) answers of at most limit columns, by size; every size is one batch."""
    found: list[frozenset[str]] = []
    for size in range(limit + 1):
        sets = [frozenset(c) for c in combinations(p.pool, size)]
        sets = [s for s in sets if not (minimal and any(f < s for f in found))]
        found += [s for s, good in zip(sets, p.counter.test_many(sets, p.target, p.eps, p.measure)) if good]
    return sorted((tuple(sorted(f)) for f in found), key=lambda t: (len(t), t))


def levelwise(counter: DistinctCounter, limit: int, eps: float | Fraction = 0) -> list[tuple[tuple[str, ...], str]]:
    """All minimal lhs -> column with at most limit columns on the left, level by level through the lattice of sets.

    A level is one batch of counts; a set is extended only while it is neither a key nor holds a column that the rest of it determines.
    """
    found: list[tuple[frozenset[str], str]] = []
    level = [frozenset()]
    for size in range(limit + 1):
        sets = [*level, *[s | {y} for s in level for y in counter.columns if y not in s]]
        r = counter.count_many([*sets, counter.columns])
        counter.meter.evaluations += len(sets)
        total = r[frozenset(counter.columns)]
        for s in level:
            for y in counter.columns:
                if y not in s and not any(lhs <= s and rhs == y for lhs, rhs in found):
                    if r[s | {y}] - r[s] <= eps * r[s | {y}]:
                        found.append((s, y))
        # With an error bound a set that holds a dependency can still be part of a minimal one.
        redundant = lambda s: eps == 0 and any(y in s and lhs <= s - {y} for lhs, y in found)
        grow = [s for s in level if not (eps == 0 and r[s] == total)]
        level = list({s | {c}: None for s in grow for c in counter.columns if c not in s})
        level = [s for s in level if not redundant(s)]
        if size == limit:
            break
    return sorted((tuple(sorted(lhs)), y) for lhs, y in found)


def agree_sets(df: DataFrame, target: str = ROW) -> list[frozenset[str]]:
    """Maximal sets of columns in which two rows agree that differ in the target.

    A set of two columns or more is found among the rows with equal values in two of its columns, so only those are paired; for single columns and
    the empty set it is enough to count.
    """
    rows = canonical(df).distinct().withColumn("row_", F.monotonically_increasing_id())
    goal = "row_" if target == ROW else target
    cols = [c for c in df.columns if c != goal]
    rows = rows.cache()
    try:
        if rows.select(digest([goal])).distinct().limit(2).count() < 2:
            return []
        found = {frozenset()}
        if cols:
            keyed = lambda sets: F.inline(F.array(*[F.struct(F.lit(i).alias("set_"), digest(s).alias("key_")) for i, s in enumerate(sets)]))
            singles = rows.select(digest([goal]).alias("goal_"), keyed([[c] for c in cols])).groupBy("set_", "key_").agg(F.count_distinct("goal_").alias("n"))
            found |= {frozenset({cols[r.set_]}) for r in singles.where("n > 1").select("set_").distinct().collect()}
        # Only columns in which rows agree at all can be two of a set.
        two = list(combinations(sorted(c for s in found for c in s), 2))
        if two:
            keys = rows.select("*", keyed(two))
            a, b = keys.alias("a"), keys.alias("b")
            same = lambda c: F.col(f"a.`{c}`").eqNullSafe(F.col(f"b.`{c}`"))
            mask = F.concat(*[F.when(same(c), "1").otherwise("0") for c in cols])
            pairs = a.join(b, (F.col("a.set_") == F.col("b.set_")) & (F.col("a.key_") == F.col("b.key_")) & (F.col("a.row_") < F.col("b.row_")) & ~same(goal))
            found |= {frozenset(c for i, c in enumerate(cols) if r.m[i] == "1") for r in pairs.select(mask.alias("m")).distinct().collect()}
    finally:
        rows.unpersist()
    return [s for s in found if not any(s < t for t in found)]


def minimal_hitting_sets(families: Iterable[frozenset[str]], limit: int | None = None) -> list[frozenset[str]]:
    """Minimal sets that share a column with every family, one family after the other."""
    out: list[frozenset[str]] = [frozenset()]
    for f in sorted(families, key=len):
        hit = [s for s in out if s & f]
        grown = {s | {c} for s in out if not s & f for c in f}
        grown = {s for s in grown if (limit is None or len(s) <= limit) and not any(h <= s for h in hit)}
        out = hit + [s for s in grown if not any(t < s for t in grown)]
    return sorted(out, key=lambda s: (len(s), sorted(s)))


def _answers_from(agreements: Iterable[frozenset[str]], columns: Sequence[str], target: str, limit: int | None) -> list[tuple[str, ...]]:
    if target == ROW:
        differences = [frozenset(columns) - a for a in agreements]
    else:
        differences = [frozenset(columns) - a - {target} for a in agreements if target not in a]
    return [tuple(sorted(s)) for s in minimal_hitting_sets(differences, limit)]


def row_wise(df: DataFrame, target: str = ROW, limit: int | None = None) -> list[tuple[str, ...]]:
    """All minimal exact answers from the columns in which pairs of rows differ."""
    return _answers_from(agree_sets(df, target), df.columns, target, limit)


def hybrid_search(p: Problem, limit: int, rows: int = 200, k: int = 10, seed: int = 3) -> list[tuple[str, ...]]:
    """Candidates from a sample of rows, tested on the table; conflicting rows join the sample until all candidates pass.  Exact answers only."""
    from depstrata.operators.dependency import witnesses

    df = p.counter.df.select(*p.counter.columns)
    share = min(1.0, 1.2 * rows / max(1, p.counter.rows))
    known = df.sample(fraction=share, seed=seed).limit(rows).collect()
    target = p.target if isinstance(p.target, str) else p.target[0]
    while True:
        agreements = set()
        for i, a in enumerate(known):
            for b in known[:i]:
                if (a != b) if target == ROW else (a[target] != b[target]):
                    agreements.add(frozenset(c for c in df.columns if a[c] == b[c]))
        agreements = [s for s in agreements if not any(s < t for t in agreements)]
        candidates = _answers_from(agreements, list(p.pool) + ([] if target == ROW else [target]), target, limit)
        failed = [c for c, good in zip(candidates, p.ok_many(candidates)) if not good]
        if not failed:
            return sorted(candidates, key=lambda t: (len(t), t))
        for c in failed[:8]:
            known += witnesses(df, list(c), ROW if target == ROW else [target], k).collect()


def cube_keys(df: DataFrame, limit: int) -> list[tuple[str, ...]]:
    """Minimal uniques of at most limit columns from one cube; for up to about ten columns."""
    cols, total = df.columns, df.distinct().count()
    found: list[frozenset[str]] = []
    sets = [(frozenset(c for i, c in enumerate(cols) if not r.set_id >> (len(cols) - 1 - i) & 1), r.r) for r in cuboids(df, cols, "cube").collect()]
    for s, r in sorted(sets, key=lambda x: len(x[0])):
        if r == total and len(s) <= limit and not any(f <= s for f in found):
            found.append(s)
    return sorted((tuple(sorted(f)) for f in found), key=lambda t: (len(t), t))


def grid_min_error(p: Problem, grid: Sequence[float | Fraction], limit: int, failures: int = 10, seed: int = 0) -> SearchResult:
    """The repeated search at each error of a grid, ascending; the first that has an answer wins."""
    began = p.evaluations
    for e in sorted(grid):
        got = shortest_within_error(p.with_eps(Fraction(str(e))), limit, failures, seed)
        if got.found:
            return SearchResult(True, got.columns, p.evaluations - began, p.error(got.columns))
    return SearchResult(False, (), p.evaluations - began)


def restart_enumeration(p: Problem, runs: int, limit: int | None = None, seed: int = 0) -> list[tuple[str, ...]]:
    """Distinct answers of independent runs."""
    found = {tuple(sorted(g.columns)) for i in range(runs) if (g := random_forward(p, limit, seed + i)).found}
    return sorted(found, key=lambda t: (len(t), t))


def adjacent_keys(p: Problem, limit: int) -> list[tuple[str, ...]]:
    """Keys among runs of neighbouring columns."""
    n = len(p.pool)
    windows = [p.pool[i : i + d] for d in range(1, limit + 1) for i in range(n - d + 1)]
    return [tuple(w) for w, good in zip(windows, p.ok_many(windows)) if good]
