"""Schema trees: skeleton by recursive splits, leaves, layers, and what can be read off a tree.

A node is a column; the root is the virtual row id.  A split of a node is a shortest set of columns below it that determines it,
so node and split determine each other.  The columns of a split are its children.  Columns left over hang on the deepest node that
determines them.  Each column appears once.

A combination of some, but not all, columns of a split can be a node of its own, named "a + b": it stands beside its columns, below the parent of their split, and what
hangs on it is determined by the columns together.

Searches below a node run on the distinct rows of the node and the columns that it determines: as many rows as the node has
values, which shrink from level to level.
"""

from __future__ import annotations

import json
from collections.abc import Sequence
from dataclasses import dataclass, field, replace
from fractions import Fraction
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depstrata.functions.columns import canonical, decimal_columns
from depstrata.operators.counting import ROW, DistinctCounter, Part
from depstrata.operators.dependency import Below, collapse_equivalents, descendants
from depstrata.plans.problem import Problem
from depstrata.plans.shortest import least_error, settled, shortest_min_error, shortest_within_error
from depstrata.sources import staged


@dataclass
class Split:
    parent: str
    children: tuple[str, ...]
    error: Fraction


@dataclass
class SchemaTree:
    columns: tuple[str, ...]
    splits: list[Split] = field(default_factory=list)
    leaves: dict[str, str] = field(default_factory=dict)  # column -> node
    eps: Fraction = Fraction(0)
    combinations: dict[str, tuple[str, ...]] = field(default_factory=dict)  # name of a node -> its columns

    # -- shape ------------------------------------------------------------
    @property
    def skeleton(self) -> list[str]:
        return [ROW, *[c for s in self.splits for c in s.children], *self.combinations]

    def key(self, node: str) -> tuple[str, ...]:
        """Columns of a node; none of the row id."""
        return () if node == ROW else self.combinations.get(node, (node,))

    def parent(self, column: str) -> str | None:
        if column == ROW:
            return None
        column = self.key(column)[0]
        return self.leaves.get(column) or next(s.parent for s in self.splits if column in s.children)

    def path_up(self, column: str) -> list[str]:
        """The column and the nodes above it, to the root."""
        out = [column]
        while (p := self.parent(out[-1])) is not None:
            out.append(p)
        return out

    def depth(self, column: str) -> int:
        return len(self.path_up(column)) - 1

    def split_of(self, node: str) -> Split | None:
        return next((s for s in self.splits if s.parent == node), None)

    def below(self, node: str) -> list[str]:
        return [c for c in self.columns if c != node and node in self.path_up(c)]

    def signature(self) -> tuple:
        """Equal for equal trees."""
        return tuple(sorted((s.parent, tuple(sorted(s.children))) for s in self.splits)), tuple(sorted(self.leaves.items())), tuple(sorted(self.combinations))

    def rows(self) -> list[tuple]:
        out = [(ROW, None, 0, "root", None, None)]
        for i, s in enumerate(self.splits):
            out += [(c, s.parent, self.depth(c), "skeleton", i, float(s.error)) for c in s.children]
        out += [(c, self.parent(c), self.depth(c), "combination", None, None) for c in self.combinations]
        return out + [(c, n, self.depth(c), "leaf", None, None) for c, n in sorted(self.leaves.items())]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), "node string, parent string, depth int, kind string, split_id int, error double")

    def relations(self, spark: SparkSession) -> DataFrame:
        """lhs, rhs, kind: joint relations in both directions where exact, and one-way relations of leaves."""
        out = []
        for s in self.splits:
            out.append((" ".join(sorted(s.children)), " ".join(self.key(s.parent)) or ROW, "both" if s.error == 0 else "approximate", float(s.error)))
        out += [(" ".join(self.key(n)) or ROW, c, "one-way", 0.0) for c, n in sorted(self.leaves.items())]
        return spark.createDataFrame(out, "lhs string, rhs string, kind string, error double")

    def stats(self) -> dict[str, int]:
        return {
            "nodes": len(self.columns) + 1,
            "skeleton": len(self.skeleton),
            "splits": len(self.splits),
            "leaves": len(self.leaves),
            "depth": max((self.depth(c) for c in self.columns), default=0),
        }

    def render(self, fmt: str = "text") -> str:
        if fmt == "json":
            splits = [{"parent": s.parent, "children": list(s.children), "error": str(s.error)} for s in self.splits]
            return json.dumps({"columns": list(self.columns), "splits": splits, "leaves": self.leaves, "eps": str(self.eps), "combinations": self.combinations})
        if fmt == "dot":
            edges = [f'  "{self.parent(c)}" -> "{c}"' + (" [style=dashed]" if c in self.leaves else "") + ";" for c in [*self.columns, *self.combinations] if c in self.leaves or c in self.skeleton]
            return "digraph tree {\n" + "\n".join(edges) + "\n}"
        lines: list[str] = []

        def walk(node: str, level: int) -> None:
            lines.append("  " * level + node + ("  (leaf)" if node in self.leaves else ""))
            s = self.split_of(node)
            for c in s.children if s else ():
                walk(c, level + 1)
            for c in sorted(c for c, n in self.leaves.items() if n == node):
                walk(c, level + 1)
            for c in [c for c in self.combinations if self.parent(c) == node]:
                walk(c, level + 1)

        walk(ROW, 0)
        return "\n".join(lines)

    @staticmethod
    def from_json(text: str) -> SchemaTree:
        d = json.loads(text)
        splits = [Split(s["parent"], tuple(s["children"]), Fraction(s["error"])) for s in d["splits"]]
        return SchemaTree(tuple(d["columns"]), splits, d["leaves"], Fraction(d["eps"]), {n: tuple(c) for n, c in d.get("combinations", {}).items()})

    # -- data -------------------------------------------------------------
    @staticmethod
    def discover(df: DataFrame, stage: bool = True, **how) -> SchemaTree:
        """Skeleton and leaves.  stage: write the table once, as it is read for every count; no, if it is a stored table."""
        df = staged(canonical(df), "table") if stage else canonical(df)
        how["memo"] = how.get("memo") if how.get("memo") is not None else {}
        tree = build_skeleton(df, **how)
        attach_columns(df, tree, how["memo"]["below"])
        return tree

    def layers(self) -> dict[str, tuple[str, ...]]:
        """Columns of the layer table of each node that has children: the node, its leaves and its split."""
        out = {}
        for node in self.skeleton:
            s = self.split_of(node)
            own = [*(s.children if s else ()), *sorted(c for c, n in self.leaves.items() if n == node)]
            if own or node == ROW:
                out[node] = (*self.key(node), *own)
        return out

    def decompose(self, df: DataFrame) -> dict[str, DataFrame]:
        return {n: canonical(df).select(*c).distinct() for n, c in self.layers().items()}

    def recompose(self, layers: dict[str, DataFrame]) -> DataFrame:
        """Join the layers again, NULL matching NULL."""
        out, left = layers[ROW], [n for n in self.skeleton[1:] if n in layers]
        while left:
            # A combination waits for its columns, and what is below it for the combination.
            node = next(n for n in left if set(self.key(n)) <= set(out.columns))
            left.remove(node)
            right, on = layers[node], []
            for i, c in enumerate(self.key(node)):
                right = right.withColumnRenamed(c, f"key__{i}")
                on.append(F.col(f"`{c}`").eqNullSafe(F.col(f"key__{i}")))
            out = out.join(right, on).drop(*[f"key__{i}" for i in range(len(on))])
        return out.select(*self.columns)

    def compression(self, df: DataFrame) -> float:
        """Cells of all layers as a share of the cells of the table."""
        cells = sum(t.count() * len(t.columns) for t in self.decompose(df).values())
        return cells / max(1, df.distinct().count() * len(self.columns))

    def broken_edges(self, df: DataFrame) -> list[tuple[str, str]]:
        """(node, column) of edges whose node no longer determines the column."""
        out = []
        for node, cols in self.layers().items():
            if node != ROW:
                own = [c for c in cols if c not in self.key(node)]
                kept = descendants(df, self.key(node), own)
                out += [(node, c) for c in own if c not in kept]
        return out


def node_table(df: DataFrame, node: str, pool: Sequence[str], weighted: bool) -> DataFrame:
    """Distinct rows of a node and its pool; with the number of rows of each where an error in rows is asked for."""
    cols = list(dict.fromkeys([*([] if node == ROW else [node]), *pool]))
    if not weighted:
        return df.select(*cols).distinct()
    return df.groupBy(*cols).agg(F.count("*").alias("weight__"))


def build_skeleton(
    df: DataFrame, D: int = 3, eps: float = 0.0, finder: str = "shortest", decimals: str = "value", split_combinations: bool = False, seed: int = 0,
    failures: int = 10, measure: str = "rows", sweep: str = "auto", set_aside: Sequence[str] = (), memo: dict | None = None, twins: str = "collapse",
) -> SchemaTree:
    """Depth-first splits from the row id.  finder: shortest (within eps; of equally short splits the one with the least error) or min_error (least error first).

    twins: of columns that determine each other one takes part in splits (collapse), or all do (keep); the others hang below it as leaves.
    memo: node tables and their counts, kept for further trees of the same table.
    """
    df, memo = canonical(df), {} if memo is None else memo
    tree = SchemaTree(tuple(df.columns), eps=Fraction(str(eps)))
    if "below" not in memo:
        memo["part", ROW] = Part.of(df, lambda t: staged(t, "part"))
        memo["below"] = Below(df, memo["part", ROW])
    below: Below = memo["below"]
    fractions = decimal_columns(df, decimals)
    used: set[str] = set(fractions) | set(set_aside)
    if twins == "collapse":
        if "twins" not in memo:
            memo["twins"] = collapse_equivalents(df, [c for c in tree.columns if c not in set_aside], memo["part", ROW], fractions if decimals == "value" else None)
        used |= set(memo["twins"])

    def find(target: Sequence[str] | str, table: DataFrame, pool: list[str], key: tuple):
        weighted = "weight__" in table.columns
        columns = [c for c in table.columns if c != "weight__"]
        if ("counter", *key) not in memo:
            part = None if weighted or isinstance(target, tuple) else memo["part", ROW] if target == ROW else Part.of(table, lambda t: staged(t, "part"))
            memo["counter", *key] = DistinctCounter(table, columns, "weight__" if weighted else None, 16 if part is None else 1, part)
        counter = memo["counter", *key]
        # A table reduced to a node and what it determines has one row for each of its values: the node is its row id.
        p = Problem(counter, target if weighted or not isinstance(target, str) else ROW, eps, measure, pool)
        search = shortest_within_error if finder == "shortest" or not eps else shortest_min_error
        got = search(p, D, failures, seed) if search is shortest_min_error else search(p, D, failures, seed, sweep=sweep)
        if search is shortest_within_error and (got.columns or not got.found):
            columns = settled(p, got.columns, D)
            got = replace(got, found=bool(columns), columns=columns)
        if got.found and search is shortest_within_error and eps:
            got = replace(got, columns=least_error(p, got.columns))
        return got, (p.error(got.columns) if got.found else None)

    def split(node: str, table: DataFrame) -> None:
        pool = [c for c in tree.columns if c not in used and c != node and c in table.columns]
        if node != ROW and pool:
            pool = [c for c in pool if c in below.of(node)]
        if not pool:
            return
        # The root counts distinct rows over all columns; below, the weight is only needed for an error in rows.
        weighted = node != ROW and eps > 0 and measure == "rows"
        key = (node, frozenset(pool), weighted)
        if node != ROW and key not in memo:
            memo[key] = staged(node_table(table, node, pool, weighted), "node")
        own = table if node == ROW else memo[key]
        got, error = find(node, own, pool, key)
        if not got.found or not got.columns:
            return
        children = tuple(c for c in tree.columns if c in got.columns)
        tree.splits.append(Split(node, children, error))
        used.update(children)
        # For the children counts of rows of the whole table matter where the error is one of rows.
        base = df if weighted or (eps > 0 and measure == "rows") else own
        for c in children:
            split(c, base)
        if split_combinations:
            for combo in (c for size in range(2, len(children)) for c in combinations(children, size)):
                left = [c for c in tree.columns if c not in used and c in base.columns]
                left = [c for c in left if c in descendants(base.select(*combo, *left), list(combo), left)] if left else []
                if left:
                    got, error = find(combo, base.select(*combo, *left).distinct(), left, (combo, frozenset(left), False))
                    # The combination has to determine what is found, or layers would not join without loss: so left is what it determines.
                    if got.found and got.columns:
                        name = " + ".join(combo)
                        tree.combinations[name] = combo
                        tree.splits.append(Split(name, tuple(c for c in tree.columns if c in got.columns), error))
                        used.update(got.columns)
                        for c in tree.splits[-1].children:
                            split(c, base)

    split(ROW, df)
    return tree


def attach_columns(df: DataFrame, tree: SchemaTree, below: Below | None = None) -> None:
    """Hang each column outside the skeleton on the deepest node that determines it; one job for each node that is not known yet.

    Of nodes equally deep the one with fewest values wins, then the first by name; they are counted where a column could hang on several.
    """
    df = canonical(df)
    below = below or Below(df)
    left = [c for c in tree.columns if c not in tree.skeleton]
    nodes = [n for n in tree.skeleton if n != ROW]
    for depth in sorted({tree.depth(n) for n in nodes}, reverse=True):
        if not left:
            break
        level = sorted(n for n in nodes if tree.depth(n) == depth)
        down = {n: below.of(n) & set(left) if n not in tree.combinations else descendants(df.select(*dict.fromkeys([*tree.key(n), *left])), tree.key(n), left) for n in level}
        rivals = [n for n in level if any(down[n] & down[m] for m in level if m != n)]
        keys = list(dict.fromkeys(c for n in rivals for c in tree.key(n)))
        r = DistinctCounter(df, keys).count_many([tree.key(n) for n in rivals]) if rivals else {}
        for node in sorted(level, key=lambda n: (r.get(frozenset(tree.key(n)), 0), n)):
            for c in sorted(down[node] & set(left)):
                tree.leaves[c] = node
                left.remove(c)
    tree.leaves.update({c: ROW for c in left})


def discover_many(df: DataFrame, seeds: Sequence[int], **how) -> dict[tuple, SchemaTree]:
    """Different trees by signature."""
    out: dict[tuple, SchemaTree] = {}
    memo: dict = {}
    df = staged(canonical(df), "table")
    for s in seeds:
        t = SchemaTree.discover(df, stage=False, seed=s, memo=memo, **how)
        out.setdefault(t.signature(), t)
    return out


def rank_solutions(df: DataFrame, solutions: Sequence[Sequence[str]], prefer: Sequence[str] = ("string", "integer", "time", "double")) -> list[tuple[str, ...]]:
    """Answers by how natural a key they make: short, then kinds of columns in order of preference, varied kinds first."""
    kind = lambda t: "string" if t == "string" else "time" if t.startswith(("timestamp", "date")) else "double" if t.startswith(("double", "float", "decimal")) else "integer"
    kinds = {c: kind(t) for c, t in df.dtypes}
    score = lambda s: (len(s), -len({kinds[c] for c in s}), sum(prefer.index(kinds[c]) for c in s), tuple(sorted(s)))
    return sorted((tuple(s) for s in solutions), key=score)


def same_rows(a: DataFrame, b: DataFrame) -> bool:
    """Whether two tables hold the same rows as often."""
    cols = a.columns
    return not a.exceptAll(b.select(*cols)).limit(1).count() and not b.select(*cols).exceptAll(a).limit(1).count()


def join_trees(trees: dict[str, tuple[DataFrame, SchemaTree]], links: Sequence[tuple[str, str, str, str]]) -> list[tuple[str, str]]:
    """(table.column, table.column) of links (table, column, table, column) where the right column is a key of its table that covers the left."""
    out = []
    for a, x, b, y in links:
        left, right = trees[a][0].select(F.col(x).alias("k")).distinct(), trees[b][0].select(F.col(y).alias("k"))
        unique = right.distinct().count() == trees[b][0].distinct().count()
        covered = not left.join(right, "k", "left_anti").where("k is not null").limit(1).count()
        if unique and covered:
            out.append((f"{a}.{x}", f"{b}.{y}"))
    return out
