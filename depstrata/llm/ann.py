"""Nearest neighbours by largest inner product, with a vantage-point tree for each shard.

One more coordinate turns the largest inner product into the smallest Euclidean distance, so the triangle inequality holds
and prunes: a part whose distances to a vantage point lie in [lo, hi] has nothing nearer to a query at
distance d than max(lo - d, d - hi).  This bound is multiplied by a factor: 1 gives exact search, more prunes more.

The top of one vantage-point tree, fitted on a bounded sample (sample_rows, max_leaves), cuts the rows into leaves; every row goes to its leaf, and the ranges
of distances are of all rows of a leaf.  A leaf of more than shard_rows rows is dealt to several shards, each with a tree of its own.
A query first searches the shards of its own leaf.  Its k-th best there bounds the rest: leaves beyond the bound are never visited, and the trees of the others prune
from the start.  Queries travel in blocks of neighbours and meet a shard in one task.

Rows with one and the same vector are one point of a tree; before they are dealt, all but the k + 1 smallest vec_ids go, as no others can be among the k
nearest.  So a vector that a third of all rows have is a few rows.

Edge cases: vectors that are NULL, all zero, or hold NULL or non-finite components take no part; queries meet vectors of their own dimension
only; rows with the query's vec_id are never its candidates; of repeated rows with one vec_id and different vectors, all are candidates and the smallest vector is the query;
rows with a NULL vec_id take no part; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from depstrata.llm.common import staged

_SLACK = 12  # points kept beyond k, so that rounding in the matrix products can't cost one


def usable(e: Column) -> Column:
    finite = F.forall(e, lambda x: F.coalesce((F.abs(x) < float("inf")) & ~F.isnan(x), F.lit(False)))
    return e.isNotNull() & finite & F.exists(e, lambda x: x != 0)


def _lifted(x: np.ndarray, top: float) -> np.ndarray:
    """Points whose distances to a query (with 0 as last coordinate) fall as inner products grow; top: the largest squared length."""
    x = x.astype(np.float64)
    return np.hstack([x, np.sqrt(np.maximum(top - (x * x).sum(1), 0))[:, None]])


def _vantage(p: np.ndarray) -> np.ndarray:
    """Far from a fixed point: vantage points near the border spread the distances."""
    return p[np.argmax(((p - p[0]) ** 2).sum(1))]


def _distance(p: np.ndarray, v: np.ndarray) -> np.ndarray:
    return np.sqrt(((p - v) ** 2).sum(1))


class Router:
    """The top of a vantage-point tree: levels of vantage points with the median distance of a sample."""

    def __init__(self, sample: np.ndarray, top: float, levels: int):
        self.top, self.levels = top, levels
        self.vantage: list[np.ndarray] = []
        self.cut: list[np.ndarray] = []
        parts = [_lifted(sample, top)] if levels else []
        for _ in range(levels):
            v = np.array([_vantage(p) if len(p) else np.zeros(sample.shape[1] + 1) for p in parts])
            d = [_distance(p, x) for p, x in zip(parts, v)]
            cut = np.array([np.median(x) if len(x) else 0.0 for x in d])
            parts = [p[side] for p, x, c in zip(parts, d, cut) for side in (x <= c, x > c)]
            self.vantage.append(v)
            self.cut.append(cut)

    def route(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Leaf of each point, and its distances to the vantage points on the way."""
        leaf = np.zeros(len(points), np.int64)
        d = np.zeros((len(points), self.levels))
        for i, (v, c) in enumerate(zip(self.vantage, self.cut)):
            d[:, i] = np.sqrt(((points - v[leaf]) ** 2).sum(1))
            leaf = 2 * leaf + (d[:, i] > c[leaf])
        return leaf, d

    def bounds(self, queries: np.ndarray, leaf: int, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Least distances that rows of a leaf can have to queries, from the ranges of its rows."""
        out = np.zeros(len(queries))
        for i, v in enumerate(self.vantage):
            d = _distance(queries, v[leaf >> (self.levels - i)])
            out = np.maximum(out, np.maximum(lo[i] - d, d - hi[i]))
        return out


class Tree:
    """Vantage-point tree over the distinct vectors of a shard."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int, leaf: int = 256, top: float | None = None):
        order = np.argsort(ids, kind="stable")
        ids, x = ids[order], np.ascontiguousarray(x[order], dtype=np.float32)
        _, first, group = np.unique((x + 0.0).view(np.dtype((np.void, x.shape[1] * 4))).ravel(), return_index=True, return_inverse=True)
        by = np.argsort(group, kind="stable")
        start = np.searchsorted(group[by], np.arange(len(first)))
        rank = np.arange(len(by)) - start[group[by]]
        self.ids = ids[by[rank <= k]]  # k + 1 smallest ids of each vector: one may be the query
        sizes = np.bincount(group[by[rank <= k]], minlength=len(first))
        x = x[first].astype(np.float64)
        self.top = float((x * x).sum(1).max()) if top is None else top
        points = _lifted(x, self.top)
        self.order = np.arange(len(x))
        self.nodes: list[tuple] = []
        self._build(points, 0, len(x), leaf)
        self.x = x[self.order].astype(np.float32)
        self.start = (np.cumsum(sizes) - sizes)[self.order]
        self.size = sizes[self.order]

    def _build(self, p: np.ndarray, lo: int, hi: int, leaf: int) -> int:
        here = len(self.nodes)
        self.nodes.append((lo, hi))
        own = self.order[lo:hi]
        if hi - lo > leaf:
            v = _vantage(p[own])
            d = _distance(p[own], v)
            half = (hi - lo) // 2
            by = np.argpartition(d, half)
            self.order[lo:hi] = own[by]
            d = d[by]
            a, b = d[:half], d[half:]
            left = self._build(p, lo, lo + half, leaf)
            right = self._build(p, lo + half, hi, leaf)
            self.nodes[here] = (lo, hi, v, (left, a.min(), a.max()), (right, b.min(), b.max()))
        return here

    def search(self, q: np.ndarray, k: int, factor: float = 1.0, least: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Points (places in self.x) of the largest inner products with each query, -1 where there are fewer, the products, and the number of points scored.

        least: inner products below which nothing is asked for.
        """
        q = q.astype(np.float64)
        x, k = self.x.astype(np.float64), k + _SLACK
        best = np.full((len(q), k), -np.inf)
        at = np.full((len(q), k), -1)
        least = np.full(len(q), -np.inf) if least is None else least
        scored = np.zeros(len(q), np.int64)
        norm = (q * q).sum(1)
        points = np.hstack([q, np.zeros((len(q), 1))])
        slack = 1e-6 * np.sqrt(norm.max(initial=0) + self.top + 1e-30)

        def far(own: np.ndarray) -> np.ndarray:
            return np.sqrt(np.maximum(norm[own] + self.top - 2 * np.maximum(best[own, -1], least[own]), 0)) + slack

        def walk(node: int, own: np.ndarray) -> None:
            lo, hi, *inner = self.nodes[node]
            if not inner:
                scored[own] += hi - lo
                s = np.hstack([best[own], q[own] @ x[lo:hi].T])
                where = np.hstack([at[own], np.broadcast_to(np.arange(lo, hi), (len(own), hi - lo))])
                top = np.argpartition(-s, k - 1, axis=1)[:, :k]
                s, where = np.take_along_axis(s, top, 1), np.take_along_axis(where, top, 1)
                by = np.argsort(-s, axis=1, kind="stable")
                best[own], at[own] = np.take_along_axis(s, by, 1), np.take_along_axis(where, by, 1)
                return
            v, *children = inner
            d = _distance(points[own], v)
            bound = [np.maximum(np.maximum(a - d, d - b), 0) * factor for _, a, b in children]
            nearer = (bound[1] < bound[0]) | ((bound[1] == bound[0]) & (d > (children[0][2] + children[1][1]) / 2))
            for first in (True, False):
                for side in (0, 1):
                    want = (nearer == bool(side)) == first
                    go = own[want]
                    if len(go):
                        go = go[bound[side][want] <= far(go)]
                        if len(go):
                            walk(children[side][0], go)

        if len(q):
            walk(0, np.arange(len(q)))
        return at, best, scored

    def nearest(self, query_ids: np.ndarray, q: np.ndarray, k: int, factor: float, least: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
        """query_id, vec_id and exact score of the k rows nearest to each query, and the points scored for the query."""
        at, _, scored = self.search(q, k, factor, least)
        row, col = np.nonzero(at >= 0)
        point = at[row, col]
        # A running sum adds the products from left to right, as a plain loop does.
        score = np.concatenate([
            np.cumsum(q[row[i : i + 65536]].astype(np.float64) * self.x[point[i : i + 65536]].astype(np.float64), axis=1)[:, -1] for i in range(0, len(row), 65536)
        ] or [np.zeros(0)])
        n = self.size[point]
        rep = np.repeat(np.arange(len(row)), n)
        place = np.arange(len(rep)) - np.repeat(np.cumsum(n) - n, n)
        ids, qs, score, scored = self.ids[self.start[point][rep] + place], query_ids[row[rep]], score[rep], scored[row[rep]]
        keep = np.nonzero(ids != qs)[0]
        by = keep[np.lexsort([ids[keep], -score[keep], qs[keep]])]
        ids, qs, score, scored = ids[by], qs[by], score[by], scored[by]
        new = np.r_[True, qs[1:] != qs[:-1]] if len(qs) else np.zeros(0, bool)
        rank = np.arange(len(qs)) - np.maximum.accumulate(np.where(new, np.arange(len(qs)), 0)) if len(qs) else np.zeros(0, int)
        return qs[rank < k], ids[rank < k], score[rank < k], scored[rank < k]


def _stack(c: pa.ChunkedArray | pa.Array) -> np.ndarray:
    return np.array(c.to_pylist(), dtype=np.float32)


def _ids(c: pa.ChunkedArray | pa.Array) -> np.ndarray:
    return np.array(c.to_pylist(), dtype=np.int64)


@dataclass
class Index:
    """Routers and tops by dimension, ranges of the leaves by dimension and leaf (chunks, lo, hi), and the shards' trees."""

    routers: dict[int, Router]
    leaves: dict[int, dict[int, tuple[int, np.ndarray, np.ndarray]]]
    trees: DataFrame  # dim, leaf, chunk, tree
    shards: int


def _route(vectors: DataFrame, routers: dict[int, Router]) -> DataFrame:
    """The same rows with leaf and d, the distances to the vantage points on the way; queries have 0 as last coordinate."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = batch.column(2).to_numpy()
            for dim in np.unique(dims):
                part = batch.take(pa.array(np.nonzero(dims == dim)[0]))
                router = routers[int(dim)]
                leaf, d = router.route(_lifted(_stack(part.column(1)), router.top)) if router.levels else (np.zeros(part.num_rows, np.int64), np.zeros((part.num_rows, 0)))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(leaf), pa.array(d.tolist(), pa.list_(pa.float64()))], names=["vec_id", "e", "dim", "leaf", "d"])

    return vectors.mapInArrow(run, "vec_id long, e array<float>, dim int, leaf long, d array<double>")


def build_index(vectors: DataFrame, k: int, shard_rows: int = 8_192, max_leaves: int = 4_096, sample_rows: int = 16_384) -> Index:
    """Cut usable vectors (vec_id, e, dim) into leaves, and those into shards with a tree each."""
    # More than k + 1 rows of one vector are never needed.
    one = W.partitionBy("e").orderBy("vec_id")
    vectors = staged(vectors.withColumn("rank", F.row_number().over(one)).where(F.col("rank") <= k + 1).drop("rank"), "vectors")
    squared = F.aggregate("e", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    dims = vectors.groupBy("dim").agg(F.count("*").alias("n"), F.max(squared).alias("top")).collect()
    routers: dict[int, Router] = {}
    for r in dims:
        levels = max(0, int(np.ceil(np.log2(max(1, min(r.n / shard_rows, max_leaves))))))
        sample = np.zeros((0, r.dim))
        if levels:
            picked = vectors.where(F.col("dim") == r.dim).orderBy(F.xxhash64("e"), "vec_id").limit(sample_rows)
            sample = _stack(picked.select("e").toArrow().column(0))
        routers[r.dim] = Router(sample, r.top, levels)
    depth = max((r.levels for r in routers.values()), default=0)
    routed = staged(_route(vectors, routers), "routed")
    ranges = [f(F.get("d", F.lit(i))).alias(f"{n}{i}") for i in range(depth) for n, f in (("lo", F.min), ("hi", F.max))]
    leaves: dict[int, dict[int, tuple[int, np.ndarray, np.ndarray]]] = {r.dim: {} for r in dims}
    sizes = []
    for r in routed.groupBy("dim", "leaf").agg(F.count("*").alias("n"), *ranges).collect():  # max_leaves rows for each dimension at most
        levels, chunks = range(routers[r.dim].levels), -(-r.n // shard_rows)
        leaves[r.dim][r.leaf] = chunks, np.array([r[f"lo{i}"] for i in levels]), np.array([r[f"hi{i}"] for i in levels])
        sizes.append((r.dim, r.leaf, chunks))
    shards = sum(c for _, _, c in sizes)
    of = F.broadcast(routed.sparkSession.createDataFrame(sizes, "dim int, leaf long, chunks long"))
    dealt = routed.join(of, ["dim", "leaf"]).withColumn("chunk", F.pmod(F.xxhash64("e"), "chunks")).select("dim", "leaf", "chunk", "vec_id", "e")
    tops = {d: r.top for d, r in routers.items()}

    def build(t: pa.Table) -> pa.Table:
        tree = Tree(_ids(t.column("vec_id")), _stack(t.column("e")), k, top=tops[t.column("dim")[0].as_py()])
        return pa.table({c: t.column(c)[:1] for c in ("dim", "leaf", "chunk")} | {"tree": pa.array([pickle.dumps(tree.__dict__, 5)], pa.binary())})

    trees = staged(dealt.repartition(max(1, min(2 * shards, 20_000)), "dim", "leaf", "chunk").groupBy("dim", "leaf", "chunk").applyInArrow(build, "dim int, leaf long, chunk long, tree binary"), "vp-trees")
    return Index(routers, leaves, trees, shards)


_FOUND = "query_id long, vec_id long, score double, scored long, shard long"


def _visit(index: Index, blocks: DataFrame, k: int, factor: float, first: bool) -> DataFrame:
    """query_id, vec_id, score, scored, shard: the nearest rows of the shards that blocks of queries have to visit.

    first: shards of the queries' own leaf only; else of all other leaves within reach of the k-th best.
    """
    routers, leaves = index.routers, index.leaves

    def ways(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for dim, home, blob in zip(*(batch.column(i).to_pylist() for i in range(3))):
                ids, q, least = pickle.loads(blob)
                router = routers[dim]
                points = np.hstack([q.astype(np.float64), np.zeros((len(q), 1))])
                norm = (points * points).sum(1)
                reach = np.sqrt(np.maximum(norm + router.top - 2 * least, 0)) + 1e-6 * np.sqrt(norm + router.top)
                for leaf, (chunks, lo, hi) in leaves[dim].items():
                    if (leaf == home) != first:
                        continue
                    go = np.ones(len(ids), bool) if first else router.bounds(points, leaf, lo, hi) * factor <= reach
                    if go.any():
                        part = pickle.dumps((ids[go], q[go], least[go]), 5)
                        columns = [pa.array([dim] * chunks, pa.int32()), pa.array([leaf] * chunks, pa.int64()), pa.array(range(chunks), pa.int64()), pa.array([part] * chunks, pa.binary())]
                        yield pa.RecordBatch.from_arrays(columns, names=["dim", "leaf", "chunk", "queries"])

    at, n = ("dim", "leaf", "chunk"), max(1, min(2 * index.shards, 20_000))
    visits = blocks.select("dim", "leaf", "queries").mapInArrow(ways, "dim int, leaf long, chunk long, queries binary").repartition(n, *at)
    tasks = visits.join(index.trees.repartition(n, *at), list(at)).select("tree", "queries", F.xxhash64(*at).alias("shard"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, tree = None, None
        for batch in batches:
            for i in range(batch.num_rows):
                shard = batch.column(2)[i].as_py()
                if shard != last:
                    last, tree = shard, Tree.__new__(Tree)
                    tree.__dict__ = pickle.loads(batch.column(0)[i].as_buffer())
                ids, q, least = pickle.loads(batch.column(1)[i].as_buffer())
                found = tree.nearest(ids, q, k, factor, least)
                yield pa.RecordBatch.from_arrays([*map(pa.array, found), pa.array([shard] * len(found[0]), pa.int64())], names=[c.split()[0] for c in _FOUND.split(", ")])

    return tasks.mapInArrow(run, _FOUND)


def _blocks(queries: DataFrame, block_rows: int) -> DataFrame:
    """dim, leaf, queries: blocks of the queries of a leaf."""

    def pack(t: pa.Table) -> pa.Table:
        blob = pickle.dumps((_ids(t.column("vec_id")), _stack(t.column("e")), np.array([-np.inf if x is None else x for x in t.column("least").to_pylist()])), 5)
        return pa.table({"dim": t.column("dim")[:1], "leaf": t.column("leaf")[:1], "queries": pa.array([blob], pa.binary())})

    sizes = queries.groupBy("dim", "leaf").agg(F.ceil(F.count("*") / block_rows).cast("long").alias("blocks"))
    dealt = queries.join(F.broadcast(sizes), ["dim", "leaf"]).withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(3)), "blocks"))
    return dealt.groupBy("dim", "leaf", "block").applyInArrow(pack, "dim int, leaf long, queries binary")


def search(embeddings: DataFrame, k: int = 20, every: int = 20, factor: float = 1.0, shard_rows: int = 8_192, block_rows: int = 4_096, with_work: bool = False, **index) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest rows of each row whose vec_id is divisible by every.

    with_work: and scored, the number of points whose inner product with the query was taken.
    """
    e = F.transform(F.col("embedding").cast("array<float>"), lambda x: x + F.lit(0.0).cast("float"))  # one zero
    vectors = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), e.alias("e")).where(usable(F.col("e")) & F.col("vec_id").isNotNull())
    vectors = vectors.withColumn("dim", F.size("e"))
    index = build_index(vectors, k, shard_rows, **index)
    queries = vectors.where(F.col("vec_id") % every == 0).groupBy("dim", "vec_id").agg(F.min("e").alias("e"))
    queries = queries.groupBy("vec_id").agg(F.min(F.struct("dim", "e")).alias("q")).select("vec_id", "q.e", "q.dim")
    queries = staged(_route(queries, index.routers).drop("d"), "queries")
    near = staged(_visit(index, _blocks(queries.withColumn("least", F.lit(None).cast("double")), block_rows), k, factor, True), "near")
    # The k-th best of a query's own leaf; NULL, no bound, where there are fewer.
    best = W.partitionBy("query_id").orderBy(F.desc("score"))
    kth = near.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).groupBy("query_id").agg(F.min("score").alias("least"), F.count("*").alias("n")).where(F.col("n") == k)
    bounded = queries.join(kth.drop("n"), F.col("vec_id") == F.col("query_id"), "left").select("vec_id", "e", "dim", "leaf", "least")
    found = near.unionByName(_visit(index, _blocks(bounded, block_rows), k, factor, False))
    # A query has k rows from each shard that it visits at most.
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    out = found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
    if with_work:
        work = found.groupBy("query_id", "shard").agg(F.max("scored").alias("n")).groupBy("query_id").agg(F.sum("n").alias("scored"))
        out = out.join(work, "query_id")
    return out
