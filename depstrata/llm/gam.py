"""Quality classifier: a generalised additive model with pairwise interactions.

Shallow trees are boosted in turn, one feature after the other, each on the bins of its feature alone; then on the bins of
the pairs that explain most of what is left.  What is learnt is a lookup table for each feature and pair, so a score
is a sum of table entries, taken for a whole batch at once.

The model is fitted on at most max_train labelled rows (a parameter; those with the smallest hash of doc_id), none of them held out.
Features come from the text alone.

Edge cases: NULL and empty texts have all features 0 and get a score; rows with a NULL label or doc_id are not learnt from; without labelled
rows every score is 0.5; repeated rows are scored each by itself; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FEATURES = ("log_words", "word_length", "symbols", "upper", "digits", "exclaims", "stops", "distinct", "adjacent", "line_repeats", "line_words", "longest")
_UPPER, _LOWER, _DIGITS = (bytes(range(a, b)) for a, b in ((65, 91), (97, 123), (48, 58)))


def features(text: str | None) -> list[float]:
    """Numbers that do not depend on the language."""
    b = (text or "").encode("utf-8", "replace")
    words = b.split()
    if not words:
        return [0.0] * len(FEATURES)
    n, size = len(words), len(b)
    share = lambda chars: (size - len(b.translate(None, chars))) / size
    lines = [x for x in b.split(b"\n") if x.strip()]
    return [
        float(np.log1p(n)),
        sum(map(len, words)) / n,
        share(b"#*$%&|<>{}[]_=~^"),
        share(_UPPER),
        share(_DIGITS),
        share(b"!?"),
        share(b".,;:"),
        len(set(words)) / n,
        sum(map(eq, words, words[1:])) / n,
        1 - len(set(lines)) / len(lines),
        n / len(lines),
        float(np.log1p(max(map(len, words)))),
    ]


@dataclass
class Model:
    base: float = 0.0
    cuts: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int, np.ndarray]] = field(default_factory=list)
    coarse: list[np.ndarray] = field(default_factory=list)  # fine bin -> bin of the pair tables

    def score(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.base)
        bins = [np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(self.cuts)]
        for b, t in zip(bins, self.tables):
            total += t[b]
        for i, j, t in self.pairs:
            total += t[self.coarse[i][bins[i]], self.coarse[j][bins[j]]]
        return 1.0 / (1.0 + np.exp(-np.clip(total, -35, 35)))


def _gain(g: np.ndarray, h: np.ndarray, reg: float) -> np.ndarray:
    return g * g / (h + reg)


def _tree(g: np.ndarray, h: np.ndarray, depth: int, reg: float, least: float) -> np.ndarray:
    """Values by bin of a small tree on sums of gradients and Hessians by bin."""
    gs, hs = g.sum(), h.sum()
    out = np.full(len(g), gs / (hs + reg))
    if depth and len(g) > 1:
        cg, ch = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
        gain = _gain(cg, ch, reg) + _gain(gs - cg, hs - ch, reg)
        gain[(ch < least) | (hs - ch < least)] = -1
        k = int(np.argmax(gain)) + 1
        if gain[k - 1] > _gain(gs, hs, reg) + 1e-9:
            out[:k] = _tree(g[:k], h[:k], depth - 1, reg, least)
            out[k:] = _tree(g[k:], h[k:], depth - 1, reg, least)
    return out


def _cross(g: np.ndarray, h: np.ndarray, reg: float) -> tuple[float, np.ndarray]:
    """Gain and values of the best pair of cuts of a grid, one on each side: four leaves."""
    best, out = 0.0, np.zeros_like(g)
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    a, b = cg[:-1, :-1], ch[:-1, :-1]
    quarters = [(a, b), (cg[:-1, -1:] - a, ch[:-1, -1:] - b), (cg[-1:, :-1] - a, ch[-1:, :-1] - b)]
    quarters.append((cg[-1, -1] - sum(q[0] for q in quarters), ch[-1, -1] - sum(q[1] for q in quarters)))
    gain = sum(_gain(x, y, reg) for x, y in quarters)
    if gain.size:
        i, j = np.unravel_index(int(np.argmax(gain)), gain.shape)
        best = float(gain[i, j] - _gain(cg[-1, -1], ch[-1, -1], reg))
        v = [x[i, j] / (y[i, j] + reg) for x, y in quarters]
        out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = v
    return best, out


def fit(x: np.ndarray, y: np.ndarray, bins: int = 64, rounds: int = 120, rate: float = 0.15, n_pairs: int = 6, reg: float = 1.0) -> Model:
    if not len(y):
        return Model(cuts=[np.array([]) for _ in FEATURES], tables=[np.zeros(1) for _ in FEATURES], coarse=[np.zeros(1, int) for _ in FEATURES])
    m = Model()
    rate_1 = min(max(y.mean(), 1e-3), 1 - 1e-3)
    m.base = float(np.log(rate_1 / (1 - rate_1)))
    for j in range(x.shape[1]):
        m.cuts.append(np.unique(np.quantile(x[:, j], np.arange(1, bins) / bins)))
        m.tables.append(np.zeros(len(m.cuts[-1]) + 1))
    b = [np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(m.cuts)]
    m.coarse = [np.arange(len(t)) * 12 // len(t) for t in m.tables]
    total = np.full(len(y), m.base)
    slope = lambda: (y - (p := 1 / (1 + np.exp(-total))), np.maximum(p * (1 - p), 1e-6))
    for _ in range(rounds):
        for j, t in enumerate(m.tables):
            g, h = slope()
            step = rate * _tree(np.bincount(b[j], g, len(t)), np.bincount(b[j], h, len(t)), 2, reg, 1.0)
            t += step
            total += step[b[j]]

    def grid(i: int, j: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        g, h = slope()
        cell = m.coarse[i][b[i]] * 12 + m.coarse[j][b[j]]
        return np.bincount(cell, g, 144).reshape(12, 12), np.bincount(cell, h, 144).reshape(12, 12), cell

    width = range(x.shape[1])
    ranked = sorted(((-_cross(*grid(i, j)[:2], reg)[0], i, j) for i in width for j in width if i < j))
    m.pairs = [(i, j, np.zeros((12, 12))) for _, i, j in ranked[:n_pairs]]
    for _ in range(rounds // 4):
        for i, j, t in m.pairs:
            g, h, cell = grid(i, j)
            step = rate * _cross(g, h, reg)[1]
            t += step
            total += step.ravel()[cell]
    # Centred tables: each has mean 0 over the rows learnt from.
    for j, t in enumerate(m.tables):
        mean = float(t[b[j]].mean())
        t -= mean
        m.base += mean
    return m


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string")) % 5 == 0


def _matrix(texts: list[str | None]) -> np.ndarray:
    return np.array([features(t) for t in texts], float).reshape(len(texts), len(FEATURES))


def train(docs: DataFrame, labels: DataFrame, max_train: int = 20_000, **how) -> Model:
    """Fit on the labelled rows that are not held out, max_train of them at most."""
    picked = (
        labels.select(F.col("doc_id").cast("long").alias("id"), F.col("quality").cast("int").alias("y"))
        .where("id is not null and y is not null").where(~held_out(F.col("id"))).distinct()
        .orderBy(F.xxhash64("id"), "id", "y").limit(max_train)
    )
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = rows.join(F.broadcast(picked), F.col("doc_id") == F.col("id")).select("doc_id", "y", "text")

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [features(t) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(x, pa.list_(pa.float64()))], names=["doc_id", "y", "x"])

    # Rows that share a doc_id and a label count once, so no more than max_train rows come to the driver.
    got = rows.mapInArrow(measure, "doc_id long, y int, x array<double>").groupBy("doc_id", "y").agg(F.min("x").alias("x")).toPandas()
    if not len(got):
        return fit(np.zeros((0, len(FEATURES))), np.zeros(0))
    x = np.stack(got["x"].to_numpy())
    order = np.lexsort([*x.T, got["y"].to_numpy(), got["doc_id"].to_numpy()])
    return fit(x[order], (got["y"].to_numpy()[order] == 1).astype(float), **how)


def classify(docs: DataFrame, model: Model, threshold: float = 0.3, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns keep, score and predicted, for every document."""
    base = docs.select(*keep, F.col("text").cast("string").alias("text_"))
    schema = base.select(*keep).withColumns({"score": F.lit(0.0), "predicted": F.lit(0)}).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                s = model.score(_matrix(part.column(part.num_columns - 1).to_pylist()))
                columns = part.columns[:-1] + [pa.array(s), pa.array((s >= threshold).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(columns, names=schema.names)

    return base.mapInArrow(run, schema)


def keep_good(docs: DataFrame, model: Model, threshold: float = 0.3) -> DataFrame:
    """The rows whose score is at least threshold, with the columns they have."""
    place = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                yield part.filter(pa.array(model.score(_matrix(part.column(place).to_pylist())) >= threshold))

    return docs.mapInArrow(run, docs.schema)
