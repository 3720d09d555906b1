"""What the searches ask: whether a set of columns passes, by data or by a given family of answers."""

from __future__ import annotations

import random
from collections.abc import Iterable, Sequence
from dataclasses import dataclass
from fractions import Fraction
from itertools import combinations
from math import comb

from depstrata.operators.counting import ROW, DistinctCounter, exact
from depstrata.operators.dependency import descendants


_WIDE = 64


@dataclass(frozen=True)
class SearchResult:
    found: bool
    columns: tuple[str, ...] = ()
    evaluations: int = 0
    error: Fraction | None = None
    minimal: bool | None = None  # whether no column can go; None if nothing says so

    @property
    def size(self) -> int:
        return len(self.columns)


class Problem:
    """columns -> target within an error bound, on a table."""

    def __init__(self, counter: DistinctCounter, target: Iterable[str] | str = ROW, eps: float | Fraction = 0, measure: str = "rows", pool: Sequence[str] | None = None):
        self.counter, self.measure, self.eps = counter, measure, exact(eps)
        self.target = target if isinstance(target, str) else tuple(target)
        y = set() if self.target == ROW else {target} if isinstance(target, str) else set(target)
        self.pool = tuple(c for c in (pool if pool is not None else counter.columns) if c not in y)
        # Sets known to pass or fail settle their supersets and subsets where the test is monotone.
        self.monotone = measure == "rows" or self.eps == 0 or self.target == ROW
        self._pass: set[frozenset[str]] = set()
        self._fail: set[frozenset[str]] = set()
        self._single: dict[str, int] | None = None

    def with_eps(self, eps: Fraction) -> Problem:
        out = Problem(self.counter, self.target, eps, self.measure, self.pool)
        out.monotone |= self.monotone
        return out

    def below_target(self) -> Problem:
        """The same among the columns that the target determines: there the ratio error falls with every column added."""
        if self.monotone:
            return self
        inside = descendants(self.counter.df.select(*self.counter.columns), self.target, self.pool)
        out = Problem(self.counter, self.target, self.eps, self.measure, [c for c in self.pool if c in inside])
        out.monotone = True
        return out

    @property
    def evaluations(self) -> int:
        return self.counter.meter.evaluations

    def known(self, s: frozenset[str]) -> bool | None:
        if s in self._pass or (self.monotone and any(p <= s for p in self._pass)):
            return True
        if s in self._fail or (self.monotone and any(s <= p for p in self._fail)):
            return False
        return False if self._too_few(s) else None

    def _too_few(self, s: frozenset[str]) -> bool:
        """r(C) is at most the product of its columns' counts: no job for a set that can't have rows enough.

        Not for wide tables, where a count for each column is more than a search takes, nor where a part of the rows tells as much.
        """
        if self.target != ROW or self.counter.weight or self.counter.part or len(self.pool) > _WIDE:
            return False
        if self._single is None:
            r = self.counter.count_many([[c] for c in self.pool] + [self.counter.columns])
            self._single = {c: r[frozenset([c])] for c in self.pool}
        most = 1
        for c in s:
            most *= self._single.get(c, self.counter.rows)
        return self.counter.rows - most > self.eps * self.counter.rows

    def excluded(self, size: int, most: int = 256) -> bool:
        """Whether a part of the rows shows that no set of so many columns passes; of more sets than most it is not asked."""
        if self.target != ROW or not self.counter.part or comb(len(self.pool), size) > most:
            return False
        sets = [s for s in map(frozenset, combinations(self.pool, size)) if self.known(s) is not False]
        return True not in map(self.known, sets) and all(self.counter.refuted(sets, self.eps))

    def ok_many(self, sets: Sequence[Iterable[str]]) -> list[bool]:
        sets = [frozenset(s) for s in sets]
        new = [s for s in dict.fromkeys(sets) if self.known(s) is None]
        self.counter.meter.evaluations += len(sets) - len(new)
        self.counter.meter.memo_hits += len(sets) - len(new)
        for s, good in zip(new, self.counter.test_many(new, self.target, self.eps, self.measure) if new else []):
            (self._pass if good else self._fail).add(s)
        return [bool(self.known(s)) for s in sets]

    def ok(self, s: Iterable[str]) -> bool:
        return self.ok_many([s])[0]

    def error(self, s: Iterable[str]) -> Fraction:
        self.counter.meter.evaluations += 1
        return self.counter.stats(s, self.target).of(self.measure)


class FamilyProblem:
    """A problem given by its minimal answers: no data, for laws and simulations."""

    monotone = True

    def __init__(self, pool: Sequence[str], answers: Iterable[Iterable[str]]):
        self.pool, self.answers, self.evaluations = tuple(pool), [frozenset(a) for a in answers], 0
        self.eps, self.target, self.measure, self.counter = Fraction(0), ROW, "rows", None

    def ok_many(self, sets: Sequence[Iterable[str]]) -> list[bool]:
        self.evaluations += len(sets)
        return [any(a <= frozenset(s) for a in self.answers) for s in sets]

    def ok(self, s: Iterable[str]) -> bool:
        return self.ok_many([s])[0]


def permute(columns: Sequence[str], seed: int) -> tuple[str, ...]:
    out = list(columns)
    random.Random(seed).shuffle(out)
    return tuple(out)
