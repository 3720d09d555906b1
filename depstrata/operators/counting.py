"""Distinct row counts: the only thing the searches ask of the data.

A DistinctCounter is the one gate to Spark jobs.  It remembers every count, meters evaluations (as the cost theory counts them) and
jobs, and answers batches of counts in one job.  Counts are over values: NULL is a value equal to
itself, so (NULL, 1) and (1, NULL) differ.

Of a large table a Part may be given as well.  Some rows have at most as many rows too many as the table, so a set that has more of them there than the error allows in the
table fails, and is not counted in the table; all others are.

A row goes to the shuffle as one number of 128 bits for each set of the batch, whatever the set's columns are: a text is
read once and never shuffled, and a batch may cover any number of columns.  Two different rows share such a number with a probability of 2^-128.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterable, Iterator, Sequence
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from depstrata.functions.columns import canonical, value_keys, value_parts

#: The virtual row id as a target: it is never a physical column.
ROW = "<row>"


@dataclass
class Meter:
    evaluations: int = 0  # tests that the search asked for, each once
    jobs: int = 0
    memo_hits: int = 0
    ahead: int = 0  # tests run before they were asked for, to share a job


@dataclass(frozen=True)
class Stats:
    """Counts behind a dependency lhs -> rhs, and its two errors."""

    r_lhs: int
    r_both: int
    kept: int  # rows that stay when each lhs keeps its most frequent rhs
    rows: int

    @property
    def error(self) -> Fraction:
        return 1 - Fraction(self.kept, self.rows) if self.rows else Fraction(0)

    @property
    def ratio(self) -> Fraction:
        return 1 - Fraction(self.r_lhs, self.r_both) if self.r_both else Fraction(0)

    def of(self, measure: str) -> Fraction:
        return {"rows": self.error, "ratio": self.ratio}[measure]


#: Equal numbers of 64 bits of different values that a part may hold: at a million rows even one has a probability of 2^-25.
CHANCE = 8


class Part:
    """Some rows of a table as numbers of 64 bits, stored; counts are of the rows of each of its tasks, added up, without a shuffle.

    Rows that agree in a set of columns agree in the table too, so what a part shows to be no key, or no dependency, is none; it never shows that something holds.
    """

    #: Rows of one task; shares of a table at most; rows that a part has at least.
    TASK_ROWS, SHARES, LEAST = 1 << 20, 32, 1 << 13

    def __init__(self, df: DataFrame, columns: Sequence[str]):
        self.df, self.place = df, {c: i for i, c in enumerate(columns)}
        self._r: dict[frozenset[str], int] = {}

    @staticmethod
    def of(df: DataFrame, store: Callable[[DataFrame], DataFrame]) -> Part | None:
        """By the hash of the column that varies most in the first rows: rows that share it stay together.  None of a small table."""
        rows = df.count()
        shares = min(Part.SHARES, rows // Part.LEAST)
        if shares < 2:
            return None
        values = {c: value_keys(c, df.schema[c].dataType, f"k{i}_")[0] for i, c in enumerate(df.columns)}
        r = df.limit(10_000).agg(*[F.approx_count_distinct(v).alias(c) for c, v in values.items()]).first().asDict()
        whole = [c for c in df.columns if df.schema[c].dataType.typeName() in ("integer", "long", "string")]
        by = next((c for c in whole if 2 * r[c] >= max(r.values())), max(r, key=r.get))
        every = [v for c in df.columns for v in value_parts(c, df.schema[c].dataType)]
        part = df.where(F.pmod(values[by], F.lit(shares)) == 0).select(*values.values(), F.xxhash64(*every).alias("row_"))
        return Part(store(part.repartition(-(-rows // (shares * Part.TASK_ROWS)))), df.columns)

    def counts(self, sets: Iterable[Iterable[str]]) -> dict[frozenset[str], int]:
        """Distinct rows over each set in each task; of the empty set over all columns."""
        wanted = list(dict.fromkeys(map(frozenset, sets)))
        new = [s for s in wanted if s not in self._r]
        if new:
            used = sorted({self.place[c] for s in new for c in s})
            names = [*(f"k{i}_0" for i in used), "row_"]
            at = [[used.index(self.place[c]) for c in s] for s in new]

            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                parts = [[c.to_numpy() for c in b.columns] for b in batches]
                if parts:
                    x = [np.concatenate(c) for c in zip(*parts)]
                    odd = np.random.default_rng(5).integers(0, 1 << 62, len(x)) * 2 + 1
                    found = [len(np.unique(sum(x[i] * odd[i] for i in own) if own else x[-1])) for own in at]
                    yield pa.RecordBatch.from_arrays([pa.array([found], pa.list_(pa.int64()))], names=["r"])

            rows = self.df.select(*names).mapInArrow(run, "r array<long>").collect()
            self._r |= {s: sum(x.r[i] for x in rows) for i, s in enumerate(new)}
        return {s: self._r[s] for s in wanted}

    def may_determine(self, node: str) -> list[str]:
        """Columns that nothing here shows not to be determined by a column."""
        r = self.counts([[node], *([node, c] for c in self.place)])
        return [c for c in self.place if c != node and r[frozenset([node, c])] - r[frozenset([node])] <= CHANCE]

    def may_be_equivalent(self, columns: Sequence[str]) -> list[str]:
        """Columns of which nothing here shows that they have no equivalent among the others."""
        one = self.counts([[c] for c in columns])
        pairs = [(a, b) for i, a in enumerate(columns) for b in columns[:i] if abs(one[frozenset([a])] - one[frozenset([b])]) <= CHANCE]
        both = self.counts(pairs)
        near = [(a, b) for a, b in pairs if both[frozenset([a, b])] - min(one[frozenset([a])], one[frozenset([b])]) <= CHANCE]
        return [c for c in columns if any(c in x for x in near)]


class Twins:
    """Columns that another one determines, of a wide table that is not stored: a count need not see them beside it.

    Some rows propose which columns go together; one pass over all rows and columns settles that the first of a class determines the others, and no column is taken out that it
    does not determine.  A column of a class stands for the first as well if it has as many values, which is counted when it is asked for.
    """

    #: Rows that propose classes.
    ROWS = 1 << 13

    def __init__(self, df: DataFrame):
        self.df = canonical(df)
        self._keys = [value_keys(c, self.df.schema[c].dataType, f"k{i}_") for i, c in enumerate(df.columns)]
        self.below = {own[0]: tuple(own[1:]) for own in self._settled(self._proposed())}
        self._same: dict[str, bool] = {}

    def _patterns(self, df: DataFrame) -> list[tuple[int, int]]:
        """Of each column which of so many rows agree in it, as a number, and its values among them."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            parts = [[c.to_numpy() for c in b.columns] for b in batches]
            found = []
            for x in map(np.concatenate, zip(*parts)):
                _, first, at = np.unique(x, return_index=True, return_inverse=True)
                found.append((int.from_bytes(hashlib.blake2b(first[at].tobytes(), digest_size=8).digest(), "little", signed=True), len(first)))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(list(v), pa.int64()) for v in zip(*found)], names=["code", "n"])

        rows = df.limit(Twins.ROWS).select(*[k for k, _ in self._keys]).coalesce(1).mapInArrow(run, "code long, n long").collect()
        return [(r.code, r.n) for r in rows]

    def _proposed(self) -> list[list[str]]:
        rows, columns = self.df.count(), self.df.columns
        if not rows:
            return []
        code = self._patterns(self.df)
        most = min(rows, Twins.ROWS)
        # Columns of almost as many values as rows agree in few of the first rows: rows that share a value tell them apart.
        for i in [i for i, (own, n) in enumerate(code) if 10 * n > 9 * most and own not in [o for o, _ in code[:i]]]:
            near = self.df.where(F.pmod(self._keys[i][1], F.lit(max(1, rows // Twins.ROWS))) == 0)
            code = [(hash((a, b)), n) for (a, n), (b, _) in zip(code, self._patterns(near))]
        by: dict[int, list[str]] = {}
        for c, (own, _) in zip(columns, code):
            by.setdefault(own, []).append(c)
        self._values = {c: n for c, (_, n) in zip(columns, code)}
        return [own for own in by.values() if len(own) > 1]

    def _settled(self, classes: list[list[str]]) -> list[list[str]]:
        if not classes:
            return []
        place = {c: i for i, c in enumerate(self.df.columns)}
        used = list(dict.fromkeys(c for own in classes for c in own))
        at = {c: i for i, c in enumerate(used)}
        wide = self.df.select(*[self._keys[place[c]][0] for c in used], *[self._keys[place[own[0]]][1] for own in classes])
        heads, rest = [at[own[0]] for own in classes], [[at[c] for c in own[1:]] for own in classes]
        few = [4 * self._values[own[0]] < Twins.ROWS for own in classes]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            odd = np.random.default_rng(5).integers(0, 1 << 62, (2, len(used))) * 2 + 1
            for b in batches:
                x, out = [c.to_numpy() for c in b.columns], []
                for k, (head, own) in enumerate(zip(heads, rest)):
                    r = np.stack([np.full(b.num_rows, k), x[head], x[len(used) + k], *[sum(x[i] * o[i] for i in own) for o in odd]], axis=1)
                    out.append(np.unique(r, axis=0) if few[k] else r)
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in np.concatenate(out).T], names=["k", "a0", "a1", "h0", "h1"])

        rows = wide.mapInArrow(run, "k long, a0 long, a1 long, h0 long, h1 long").groupBy("k", "a0", "a1")
        one = rows.agg(*[(F.min(f"h{h}") == F.max(f"h{h}")).alias(f"o{h}") for h in (0, 1)])
        good = {r.k: r.good for r in one.groupBy("k").agg(F.bool_and(F.col("o0") & F.col("o1")).alias("good")).collect()}
        out = [own for k, own in enumerate(classes) if good[k]]
        for own in (own for k, own in enumerate(classes) if not good[k]):
            # The rows that proposed the class were too few: what its first column does determine stays, the others are proposed again without it.
            from depstrata.operators.dependency import determined

            left, found = list(own), []
            while len(left) > 1:
                down = determined(self.df.select(*left), [left[0]], left)[left[0]]
                found.append([left[0], *[c for c in left[1:] if c in down]])
                left = [c for c in left[1:] if c not in down]
            out += [f for f in found if len(f) > 1]
        return out

    def without(self, sets: Sequence[frozenset[str]], count: Callable) -> dict[frozenset[str], frozenset[str]]:
        """Of each set one of as many distinct rows."""
        asked: dict[str, str] = {}
        for s in sorted(sets, key=len):
            for head, own in self.below.items():
                have = [c for c in own if c in s] if head not in s else []
                if have and not any(c in asked or self._same.get(c) for c in have) and (c := next((c for c in have if c not in self._same), None)):
                    asked[c] = head
        if asked:
            r = count([frozenset([c]) for pair in asked.items() for c in pair])
            self._same |= {c: r[frozenset([c])] == r[frozenset([head])] for c, head in asked.items()}
        out = {}
        for s in sets:
            left = s
            for head, own in self.below.items():
                if head in s:
                    left = left - frozenset(own)
                elif any(self._same.get(c) and c in s for c in own):
                    left = left - frozenset(own) | {head}
            out[s] = left
        return out


class DistinctCounter:
    def __init__(self, df: DataFrame, columns: Sequence[str] | None = None, weight: str | None = None, batch: int = 16, part: Part | None = None, twins: Twins | None = None, known: dict[frozenset[str], int] | None = None):
        """known: counts of the same columns of the same rows, shared with other counters."""
        self.columns = tuple(columns or [c for c in df.columns if c != weight])
        self.weight = weight
        self.df = canonical(df.select(*self.columns, *([weight] if weight else [])))
        self.batch = batch
        self.part = part
        self.twins = twins
        self.meter = Meter()
        self._r = known if known is not None else {}
        self._stats: dict[tuple, Stats] = {}

    # -- counts -----------------------------------------------------------
    def count(self, columns: Iterable[str]) -> int:
        """Distinct rows over a set of columns; of the empty set 1, if there is a row."""
        return self.count_many([columns])[frozenset(columns)]

    @property
    def rows(self) -> int:
        return self.count(self.columns)

    def count_many(self, sets: Iterable[Iterable[str]]) -> dict[frozenset[str], int]:
        """Counts of several sets; those not known yet in as few jobs as the batch size allows."""
        wanted = list(dict.fromkeys(map(frozenset, sets)))
        if not self.twins:
            return self._counted(wanted)
        alike = self.twins.without(wanted, self._counted)
        r = self._counted(alike.values())
        return {s: r[alike[s]] for s in wanted}

    def _counted(self, sets: Iterable[frozenset[str]]) -> dict[frozenset[str], int]:
        wanted = list(dict.fromkeys(sets))
        new = [s for s in wanted if s not in self._r]
        self.meter.memo_hits += len(wanted) - len(new)
        if frozenset() in new:
            new.remove(frozenset())
            self.meter.jobs += 1
            self._r[frozenset()] = self.df.limit(1).count()
        for at in range(0, len(new), self.batch):
            self._run(new[at : at + self.batch])
        return {s: self._r[s] for s in wanted}

    def _run(self, sets: list[frozenset[str]]) -> None:
        self.meter.jobs += 1
        kinds = self.df.schema
        if len(sets) == 1:
            values = [v for c in self._ordered(sets[0]) for v in value_parts(c, kinds[c].dataType)]
            self._r[sets[0]] = self.df.select(*[F.xxhash64(F.lit(h), *values).alias(f"h{h}") for h in (0, 1)]).distinct().count()
            return
        # Each column is hashed once for all sets of the batch.
        used = self._ordered(frozenset().union(*sets))
        keys = {c: f"k{i}_" for i, c in enumerate(used)}
        each = self.df.select(*[k for c in used for k in value_keys(c, kinds[c].dataType, keys[c])])
        key = lambda i, s: F.struct(F.lit(i).alias("set_id"), *[F.xxhash64(F.lit(h), *[f"{keys[c]}{h}" for c in self._ordered(s)]).alias(f"h{h}") for h in (0, 1)])
        rows = each.select(F.explode(F.array(*[key(i, s) for i, s in enumerate(sets)])).alias("k")).select("k.*")
        found = {r.set_id: r["count"] for r in rows.distinct().groupBy("set_id").count().collect()}
        for i, s in enumerate(sets):
            self._r[s] = found.get(i, 0)

    def _ordered(self, s: Iterable[str]) -> list[str]:
        s = set(s)
        return [c for c in self.columns if c in s]

    # -- dependencies -----------------------------------------------------
    def stats(self, lhs: Iterable[str], rhs: Iterable[str] | str) -> Stats:
        """Both counts and both errors of lhs -> rhs in one job."""
        lhs = frozenset(lhs)
        if rhs == ROW:
            r, total = self.count(lhs), self.rows
            return Stats(r, total, r, total) if not self.weight else self._weighted(lhs, frozenset(self.columns))
        return self._weighted(lhs, frozenset([rhs] if isinstance(rhs, str) else rhs))

    def _weighted(self, lhs: frozenset[str], rhs: frozenset[str]) -> Stats:
        key = lhs, rhs - lhs
        if key in self._stats:
            self.meter.memo_hits += 1
            return self._stats[key]
        self.meter.jobs += 1
        n = F.sum(self.weight) if self.weight else F.count("*")
        pairs = self.df.groupBy(*map(_q, self._ordered(lhs | rhs))).agg(n.alias("n_"))
        each = pairs.groupBy(*map(_q, self._ordered(lhs))).agg(F.max("n_").alias("most_"), F.sum("n_").alias("all_"), F.count("*").alias("kinds_"))
        got = each.agg(F.count_if(F.col("kinds_") > 0).alias("a"), F.sum("kinds_").alias("b"), F.sum("most_").alias("k"), F.sum("all_").alias("t")).first()
        out = Stats(got.a or 0, got.b or 0, int(got.k or 0), int(got.t or 0))
        self._stats[key] = out
        self._r.setdefault(lhs, out.r_lhs)
        self._r.setdefault(lhs | rhs, out.r_both)
        return out

    def refuted(self, sets: Sequence[frozenset[str]], eps: Fraction | float = 0) -> list[bool]:
        """Whether the part alone shows that a set's error as a key is above eps."""
        if not self.part:
            return [False] * len(sets)
        new, most = [s for s in sets if s not in self._r], exact(eps) * self.rows
        few = self.part.counts([*new, frozenset()])
        return [s in few and s not in self._r and few[frozenset()] - few[s] - CHANCE > most for s in sets]

    def test_many(self, sets: Sequence[Iterable[str]], target: Iterable[str] | str, eps: Fraction | float = 0, measure: str = "rows") -> list[bool]:
        """Whether the error of each set -> target is at most eps; one evaluation each."""
        sets = [frozenset(s) for s in sets]
        self.meter.evaluations += len(sets)
        eps = exact(eps)
        if target == ROW and not self.weight:
            r = self.count_many([*(s for s, no in zip(sets, self.refuted(sets, eps)) if not no), self.columns])
            total = r[frozenset(self.columns)]
            return [s in r and total - r[s] <= eps * total for s in sets]
        if target != ROW and (measure == "ratio" or eps == 0):
            y = frozenset([target] if isinstance(target, str) else target)
            r = self.count_many([x for s in sets for x in (s, s | y)])
            return [r[s | y] - r[s] <= eps * r[s | y] for s in sets]
        return [self.stats(s, target).of(measure) <= eps for s in sets]


def exact(eps: Fraction | float) -> Fraction:
    """The decimal number that was meant, so that 1/8 <= 0.125 holds."""
    return eps if isinstance(eps, Fraction) else Fraction(str(eps))


def _q(c: str):
    return F.col(f"`{c}`")


def cuboids(df: DataFrame, columns: Sequence[str], kind: str = "rollup") -> DataFrame:
    """(set_id, r): distinct counts of all prefixes (rollup) or all subsets (cube) in one job."""
    grouped = getattr(canonical(df.select(*columns)), kind)(*columns).agg(F.grouping_id().alias("set_id"))
    return grouped.groupBy("set_id").agg(F.count("*").alias("r"))


def prefix_rollup(df: DataFrame, order: Sequence[str]) -> list[int]:
    """Counts of the prefixes of 1, 2, ... columns from one rollup."""
    found = {r.set_id: r.r for r in cuboids(df, order, "rollup").collect()}
    n = len(order)
    return [found.get((1 << (n - i)) - 1, 0) for i in range(1, n + 1)]


def prefix_sketch(df: DataFrame, order: Sequence[str], rsd: float = 0.02) -> list[int]:
    """Estimated counts of all prefixes in one pass: a sketch for each on a hash with NULL mask."""
    df = canonical(df.select(*order))
    made = []
    for i in range(1, len(order) + 1):
        cols = [_q(c) for c in order[:i]]
        mask = F.concat(F.lit(""), *[F.when(c.isNull(), "1").otherwise("0") for c in cols])
        made.append(F.approx_count_distinct(F.xxhash64(mask, *cols), rsd).alias(f"p{i}"))
    return list(df.agg(*made).first())


def sorted_profile(df: DataFrame, order: Sequence[str], partitions: int | None = None) -> list[int]:
    """Counts of all prefixes of a column order from one sort.

    Any order will do that puts equal rows side by side, so each column is sorted by the 128 bits of its values.  A prefix of i columns then has one distinct
    value more wherever two neighbours agree in fewer than i columns.  Neighbours are compared as batches of numbers as they come from the sort; each
    partition sends a histogram of their agreements with its first and last row, and the borders are patched on the driver.  Histogram and
    border rows come from one job, as range bounds are sampled anew by each.
    """
    df = canonical(df.select(*order))
    n = len(order)
    df = df.select(*[k for i, c in enumerate(order) for k in value_keys(c, df.schema[c].dataType, f"c{i}_")])
    names = df.columns
    parts = df.repartitionByRange(partitions, *names) if partitions else df.repartitionByRange(*names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hist, first, last = np.zeros(n + 1, np.int64), None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.stack([c.to_numpy() for c in batch.columns], axis=1).reshape(batch.num_rows, n, 2)
            first = x[0] if first is None else first
            x = x if last is None else np.concatenate([last[None], x])
            same = (x[1:] == x[:-1]).all(2)
            hist += np.bincount(np.logical_and.accumulate(same, axis=1).sum(1), minlength=n + 1)
            last = x[-1]
        if last is not None:
            yield pa.RecordBatch.from_arrays([pa.array([v.ravel().tolist()], pa.list_(pa.int64())) for v in (hist, first, last)], names=["hist", "first", "last"])

    found = parts.sortWithinPartitions(*names).mapInArrow(run, "hist array<long>, first array<long>, last array<long>").withColumn("part", F.spark_partition_id())
    rows = sorted(found.collect(), key=lambda r: r.part)
    if not rows:
        return [0] * n
    hist = np.sum([r.hist for r in rows], axis=0)
    for a, b in zip(rows, rows[1:]):
        hist[next((i // 2 for i, (x, y) in enumerate(zip(a["last"], b["first"])) if x != y), n)] += 1
    return (1 + np.cumsum(hist)[:n]).tolist()
