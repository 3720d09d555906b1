"""Repeated forward addition: the shortest answer within an error bound, and the shortest of those with least error."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence
from fractions import Fraction
from itertools import combinations, count
from math import comb

from depstrata.operators.counting import ROW
from depstrata.plans.forward import essential_columns, forward_search, prefetch, random_forward
from depstrata.plans.problem import Problem, SearchResult, permute


def shortest_within_error(
    p: Problem, limit: int, failures: int = 10, seed: int = 0, initial: Sequence[str] | None = None, essential: str = "none", sweep: str = "auto"
) -> SearchResult:
    """Runs on new orders, each asked for a strictly shorter answer, until a number of them in a row fails.

    initial: an answer to start from.  essential: none; first, columns that all answers need lead every run; after_first, only those of the first answer are tested.
    """
    began, best, failed = p.evaluations, tuple(initial) if initial is not None else None, 0
    # With a part of the rows at hand few tests need a job, and what one run learns saves the next ones more than a common job does.
    batched = isinstance(p, Problem) and p.monotone and sweep in ("auto", "bisect") and not p.counter.part
    required: Sequence[str] = essential_columns(p) if essential == "first" else ()
    for run in count():
        if failed >= failures or (best is not None and len(best) <= max(1, len(required))):
            break
        most = limit if best is None else len(best) - 1
        if failed == 0 and isinstance(p, Problem) and p.excluded(most):
            break
        if failed == 0 and batched:
            # The runs up to the next failure limit, in step; the loop below replays them from what is known then.
            prefetch(p, [permute(p.pool, seed + i) for i in range(run, run + failures)], most, required)
        got = random_forward(p, most, seed + run, required, sweep)
        if got.found:
            best, failed = got.columns, 0
            if essential == "after_first" and not required:
                required = essential_columns(p, within=best)
        else:
            failed += 1
    return SearchResult(best is not None, best or (), p.evaluations - began)


def settled(p: Problem, columns: Sequence[str], limit: int, most: int = 256) -> tuple[str, ...]:
    """A set within the error that is shorter than the one given, which failures in a row may miss, or else that one; none given: one of up to limit columns.

    Each smaller number of columns is gone through as a whole, unless it has more than most sets.
    """
    for size in range(1, len(columns) if columns else limit + 1):
        if comb(len(p.pool), size) > most:
            continue
        left = [s for s in combinations(p.pool, size) if p.known(frozenset(s)) is not False]
        if p.target == ROW and p.counter.part:
            left = [s for s, no in zip(left, p.counter.refuted([frozenset(s) for s in left], p.eps)) if not no]
            found = next((s for s in left if p.ok(s)), None)
        else:
            found = next((s for s, good in zip(left, p.ok_many(left)) if good), None)
        if found:
            return found
    return tuple(columns)


def least_error(p: Problem, columns: Sequence[str], most: int = 256) -> tuple[str, ...]:
    """Of the sets of as many columns within the error the one with the least, and of equal ones the first in the order of the pool, whatever set is given: all of them are tested, unless there are more than most."""
    best, error = tuple(columns), p.error(columns)
    if comb(len(p.pool), len(best)) > most:
        return best
    every = list(combinations(p.pool, len(best)))
    at = next(i for i, s in enumerate(every) if set(s) == set(best))
    # A set before the one that is given wins with the same error, one after it only with less.
    others = every[:at] + (every[at + 1 :] if error else [])
    if p.target == ROW and p.counter.part:
        left = [s for s, no in zip(others, p.counter.refuted([frozenset(s) for s in others], error)) if not no]
    else:
        left = [s for s, good in zip(others, p.with_eps(error).ok_many(others)) if good]
    before, moved = set(every[:at]), False
    for s in left:
        same = s in before and not moved
        if (same or error) and p.with_eps(error if same else error * (1 - Fraction(1, 10**30))).ok(s):
            best, error, moved = s, p.error(s), True
    return best


def extend_columns(p: Problem, columns: Iterable[str], limit: int, policy: str = "greedy", order: Sequence[str] | None = None) -> tuple[tuple[str, ...], Fraction]:
    """Add columns that lower the error, limit in all; greedy: the best each time, sequential: any that helps, in order."""
    out = list(columns)
    error = p.error(out)
    if policy == "sequential":
        for c in order or p.pool:
            if error == 0 or len(out) >= limit:
                break
            if c not in out and (e := p.error([*out, c])) < error:
                out, error = [*out, c], e
        return tuple(out), error
    while error > 0 and len(out) < limit:
        rest = [c for c in (order or p.pool) if c not in out]
        tried = [(p.error([*out, c]), i, c) for i, c in enumerate(rest)]
        if not tried or min(tried)[0] >= error:
            break
        error, _, c = min(tried)
        out.append(c)
    return tuple(out), error


def shortest_min_error(p: Problem, limit: int, failures: int = 10, seed: int = 0, policy: str = "greedy") -> SearchResult:
    """Least error first: each run starts from the least error known and is extended; then the shortest at that error.

    With the ratio error only columns that the target determines take part, as adding others may raise it.
    """
    p = p.below_target()
    began = p.evaluations
    best: tuple[str, ...] | None = None
    error, failed = p.eps, 0
    for run in count():
        if failed >= failures or error == 0:
            break
        order = permute(p.pool, seed + run)
        got = forward_search(p.with_eps(error), order, limit)
        if got.found:
            columns, e = extend_columns(p, got.columns, limit, policy, order)
            if best is None or e < error:
                best, error, failed = columns, e, 0
                continue
        failed += 1
    if p.eps and best is None:
        return SearchResult(False, (), p.evaluations - began)
    last = shortest_within_error(p.with_eps(error), limit, failures, seed + 1000, initial=best)
    if not last.found:
        return SearchResult(False, (), p.evaluations - began)
    return SearchResult(True, last.columns, p.evaluations - began, p.error(last.columns))


def next_solution(p: Problem, known: Iterable[str], limit: int | None, seed: int) -> SearchResult:
    """Another answer, if there is one: the known one comes last in the order."""
    known = tuple(known)
    rest = [c for c in p.pool if c not in known]
    got = forward_search(p, [*permute(rest, seed), *permute(known, seed)], limit)
    return SearchResult(False, (), got.evaluations) if got.found and set(got.columns) == set(known) else got


def _hitting_sets(answers: Sequence[frozenset[str]]) -> Iterator[frozenset[str]]:
    """Sets that share a column with each answer, minimal ones first."""
    columns = sorted(set().union(*answers)) if answers else []
    found: list[frozenset[str]] = []
    for size in range(len(columns) + 1):
        for c in map(frozenset, combinations(columns, size)):
            if all(c & a for a in answers) and not any(f <= c for f in found):
                found.append(c)
                yield c


def enumerate_solutions(p: Problem, limit: int | None = None, most: int | None = None) -> list[tuple[str, ...]]:
    """All minimal answers (within limit), or the first most ones: each new one avoids a hitting set of those known.

    Answers above limit are used on the way and left out at the end.
    """
    found: list[frozenset[str]] = []
    while most is None or len(found) < most:
        for out in _hitting_sets(found):
            order = [c for c in p.pool if c not in out]
            got = forward_search(p, order, None)
            if got.found:
                found.append(frozenset(got.columns))
                break
        else:
            break
    return sorted((tuple(sorted(f)) for f in found if limit is None or len(f) <= limit), key=lambda t: (len(t), t))
