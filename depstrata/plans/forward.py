"""Forward addition: one minimal column set that determines a target, in few counts.

Columns are added in a given order until the test first passes.  The column that made it pass is needed: it is
kept, the columns after it are dropped, and the sweep starts again before it, until the kept columns pass alone.
The answer is the minimal set whose positions, from the largest down, are lexicographically least.

A sweep only has to find the first prefix that passes; there are several ways.
    linear    one test for each prefix
    bisect    the test is monotone, so halving does
    kary      several prefixes in one job of grouping sets
    rollup    all prefix counts from one rollup
    sorted    all prefix counts from one sort
    sketch    a guess from mergeable sketches in one pass, then exact tests around it
    sample    a lower bound from sampled rows; every failed exact test adds its witnesses to the sample

Where the error can rise with a column added (the ratio error outside the columns that the target determines), nothing follows from a test of
the whole pool: prefixes are then tested one after the other (linear, or the profiles), and a sweep may find none.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator, Sequence

from depstrata.operators import counting
from depstrata.operators.counting import ROW
from depstrata.operators.dependency import witnesses
from depstrata.plans.problem import Problem, SearchResult, permute

#: Number of columns of the pool that pass with those kept; None if no prefix does.
Sweep = Callable[[Problem, list[str], list[str]], int | None]


def _linear(p: Problem, kept: list[str], pool: list[str]) -> int | None:
    return next((h for h in range(1, len(pool) + 1) if p.ok(kept + pool[:h])), None)


def _bisect(p: Problem, kept: list[str], pool: list[str], lo: int = 1, hi: int | None = None) -> int:
    hi = len(pool) if hi is None else hi  # passes
    while lo < hi:
        mid = (lo + hi) // 2
        if p.ok(kept + pool[:mid]):
            hi = mid
        else:
            lo = mid + 1
    return lo


def _kary(p: Problem, kept: list[str], pool: list[str], k: int = 4) -> int:
    lo, hi = 0, len(pool)  # lo fails, hi passes
    while hi - lo > 1:
        probes = sorted({lo + (hi - lo) * i // (k + 1) for i in range(1, k + 1)} - {lo, hi}) or [lo + 1]
        passed = p.ok_many([kept + pool[:h] for h in probes])
        hi = next((h for h, good in zip(probes, passed) if good), hi)
        lo = max([h for h, good in zip(probes, passed) if not good and h < hi], default=lo)
    return hi


def _by_profile(profile: Callable) -> Sweep:
    """First hit from the counts of all prefixes, with and without the target."""

    def sweep(p: Problem, kept: list[str], pool: list[str]) -> int | None:
        order, y = kept + pool, [] if p.target == ROW else [p.target] if isinstance(p.target, str) else list(p.target)
        if y and p.eps and p.measure == "rows":
            return _bisect(p, kept, pool)  # counts alone do not give this error
        df, meter = p.counter.df, p.counter.meter
        alone = profile(df, order)
        meter.jobs += 1
        meter.evaluations += len(pool)
        if y:
            both = profile(df, y + order)[len(y) :]
            meter.jobs += 1
        else:
            both = [p.counter.rows] * len(order)
        n = len(kept)
        for h in range(1, len(pool) + 1):
            r, t = alone[n + h - 1], both[n + h - 1]
            p.counter._r.setdefault(frozenset(order[: n + h]), r)
            if t - r <= p.eps * t:
                return h
        return None

    return sweep


def _sketch(p: Problem, kept: list[str], pool: list[str], rsd: float = 0.02) -> int:
    order, y = kept + pool, [] if p.target == ROW else [p.target] if isinstance(p.target, str) else list(p.target)
    p.counter.meter.jobs += 1
    near = counting.prefix_sketch(p.counter.df, order, rsd)
    goal = [p.counter.rows] * len(order) if not y else counting.prefix_sketch(p.counter.df, y + order, rsd)[len(y) :]
    slack = 1 - 3 * rsd - float(p.eps)
    guess = next((h for h in range(1, len(pool) + 1) if near[len(kept) + h - 1] >= slack * goal[len(kept) + h - 1]), len(pool))
    lo, hi, step = 1, len(pool), 1
    if p.ok(kept + pool[:guess]):
        hi = guess
        while hi > 1 and p.ok(kept + pool[: max(1, hi - step)]):
            hi, step = max(1, hi - step), 2 * step
        lo = max(1, hi - step + 1) if hi > 1 else 1
    else:
        lo = guess + 1
        while lo + step < len(pool) and not p.ok(kept + pool[: lo + step]):
            lo, step = lo + step + 1, 2 * step
        hi = min(len(pool), lo + step)
    return _bisect(p, kept, pool, min(lo, hi), hi)


def sample_sweep(rows: int = 2000, k: int = 20, seed: int = 7) -> Sweep:
    """For error 0: rows on the driver refute prefixes, the table confirms one."""
    seen: dict[int, list[dict]] = {}

    def sweep(p: Problem, kept: list[str], pool: list[str]) -> int:
        if p.eps:
            return _bisect(p, kept, pool)
        df, y = p.counter.df, list(p.counter.columns) if p.target == ROW else [p.target] if isinstance(p.target, str) else list(p.target)
        if id(p.counter) not in seen:
            share = min(1.0, 1.2 * rows / max(1, p.counter.rows))
            seen.clear()
            seen[id(p.counter)] = [r.asDict() for r in df.sample(fraction=share, seed=seed).limit(rows).collect()]
        known = seen[id(p.counter)]

        def refuted(columns: Sequence[str]) -> bool:
            first: dict[tuple, tuple] = {}
            return any(first.setdefault(tuple(_key(r[c]) for c in columns), v) != v for r in known if (v := tuple(_key(r[c]) for c in y)) is not None)

        while True:
            lo, hi = 1, len(pool)
            while lo < hi:
                mid = (lo + hi) // 2
                lo, hi = (mid + 1, hi) if refuted(kept + pool[:mid]) else (lo, mid)
            if lo == len(pool) or p.ok(kept + pool[:lo]):
                return lo
            known += [r.asDict() for r in witnesses(df, kept + pool[:lo], p.target if p.target == ROW else y, k).collect()]
            p.counter.meter.jobs += 1

    return sweep


def _key(v):
    return repr(v) if isinstance(v, (list, dict)) or v != v else v


SWEEPS: dict[str, Sweep] = {
    "linear": _linear,
    "bisect": _bisect,
    "kary": _kary,
    "rollup": _by_profile(counting.prefix_rollup),
    "sorted": _by_profile(counting.sorted_profile),
    "sketch": _sketch,
    "sample": sample_sweep(),
}


#: Sweeps that look at every prefix, so that the test need not be monotone.
_EVERY_PREFIX = ("linear", "rollup", "sorted")


def forward_search(p: Problem, order: Sequence[str] | None = None, limit: int | None = None, required: Iterable[str] = (), sweep: str | Sweep = "auto") -> SearchResult:
    """At most limit columns, required ones among them, that pass; found is False if there are none in this order.

    The answer is minimal if the test is monotone and nothing was required; else minimal is None, and is_minimal() tells.
    """
    began = p.evaluations
    kept = list(required)
    pool = [c for c in (order if order is not None else p.pool) if c in set(p.pool) - set(kept)]
    if sweep == "auto":
        sweep = "bisect" if p.monotone else "linear"
    if isinstance(sweep, str) and not p.monotone and sweep not in _EVERY_PREFIX:
        raise ValueError(f"the error may rise with a column added: sweep {sweep} would miss answers; use {', '.join(_EVERY_PREFIX)}, or below_target()")
    find = SWEEPS[sweep] if isinstance(sweep, str) else sweep
    sure = True if p.monotone and not required else None
    done = lambda found: SearchResult(found, tuple(kept) if found else (), p.evaluations - began, None, sure if found else None)
    if p.ok(kept):
        return done(limit is None or len(kept) <= limit)
    if p.monotone and not p.ok(kept + pool):
        return done(False)
    while limit is None or len(kept) < limit:
        h = find(p, kept, pool)
        if h is None:
            return done(False)
        kept.append(pool[h - 1])
        pool = pool[: h - 1]
        if p.ok(kept):
            return done(True)
    return done(False)


def _halving(kept: list[str], pool: list[str], limit: int | None) -> Iterator[list[str]]:
    """The sets that a run with halving asks for; it is sent whether each passes."""
    if (yield kept) or not (yield kept + pool):
        return
    while limit is None or len(kept) < limit:
        lo, hi = 1, len(pool)
        while lo < hi:
            mid = (lo + hi) // 2
            if (yield kept + pool[:mid]):
                hi = mid
            else:
                lo = mid + 1
        kept, pool = [*kept, pool[lo - 1]], pool[: lo - 1]
        if (yield kept):
            return


def prefetch(p: Problem, orders: Iterable[Sequence[str]], limit: int | None, required: Iterable[str] = ()) -> None:
    """Walk several orders in step, so that what they ask at one time is one batch of counts; runs on these orders then find all answers known.

    Tests count as evaluations when a run asks for them, not here.
    """
    runs, required = {}, list(required)
    meter = p.counter.meter
    asked, hits = meter.evaluations, meter.memo_hits
    for i, order in enumerate(orders):
        g = _halving(required, [c for c in order if c not in required], limit)
        runs[i] = g, next(g)
    while runs:
        passed = p.ok_many([s for _, s in runs.values()])
        for i, good in zip(list(runs), passed):
            try:
                runs[i] = runs[i][0], runs[i][0].send(good)
            except StopIteration:
                del runs[i]
    meter.ahead += meter.evaluations - asked
    meter.evaluations, meter.memo_hits = asked, hits


def forward_key(p: Problem, order: Sequence[str] | None = None, limit: int | None = None, sweep: str = "auto") -> SearchResult:
    """Forward addition for a minimal unique."""
    return forward_search(p, order, limit, sweep=sweep)


def random_forward(p: Problem, limit: int | None, seed: int, required: Iterable[str] = (), sweep: str = "auto") -> SearchResult:
    return forward_search(p, permute(p.pool, seed), limit, required, sweep)


def essential_columns(p: Problem, within: Iterable[str] | None = None) -> list[str]:
    """Columns that every answer needs: the pool without one of them fails.  within: only these are tested."""
    pool = frozenset(p.pool)
    tested = [c for c in p.pool if within is None or c in set(within)]
    if not p.ok(pool):
        return []
    return [c for c, good in zip(tested, p.ok_many([pool - {c} for c in tested])) if not good]
