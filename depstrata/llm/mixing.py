"""Mixing sources to target weights by pivotal dependent rounding.

Every document of a source is to be taken target / size times on average.  The whole part is taken; the fractions
are rounded by duels: two fractions meet, mass moves at random from one to the other until one is 0 or 1, and the other goes on to the next duel.
The sum of the fractions never changes, and documents of like size meet, so the words taken stay near the target.
Documents duel in chunks of bounded size; each leaves one fraction at most, and these meet again in chunks of chunks
until one a source is left, which is rounded at random.  Draws come from a hash of the ids: reruns agree.

Edge cases: a NULL text has size 0; a NULL source is a source of its own, the last; a source of size 0 has target 0 and its documents are
taken 0 times; repeated rows and rows without a doc_id are separate documents, and a chunk that they fill too much is dealt anew by row; an
empty table gives an empty result; other columns stay aside.
"""

from __future__ import annotations

import random
from collections.abc import Sequence
from fractions import Fraction

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import WORD, apart, staged

_ROWS = "doc_id long, th long, source string, size long, source_size long, target double, chunk long, chunks long, whole int, part double, copies int"


def targets(sizes: dict[str | None, int], weights: Sequence[int] = (5, 2, 1), most: int = 3) -> dict[str | None, float]:
    """Target of each source: its weighted share of all sizes, never above most times its size."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, open_, out = Fraction(sum(sizes.values())), list(names), {}
    while open_:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > most * sizes[s]]
        for s in over or open_:
            out[s] = Fraction(most * sizes[s]) if over else left * weight[s] / total
        left -= sum(out[s] for s in over)
        open_ = [s for s in open_ if s not in out] if over else []
    return {s: float(x) for s, x in out.items()}


def many_targets(found: DataFrame, weights: Sequence[int], most: int) -> DataFrame:
    """s, target: targets() of sources (source, n) that are too many for the driver; each round of capping is an aggregation."""
    ordered = staged(found.select("source", "n").orderBy(F.asc_nulls_last("source")).withColumn("at", F.monotonically_increasing_id()), "ordered")
    part = F.shiftright("at", 33)
    counts = sorted((r.p, r["count"]) for r in ordered.groupBy(part.alias("p")).count().collect())  # a row for each partition
    before, rows = 0, []
    for p, k in counts:
        rows.append((p, before))
        before += k
    offset = F.broadcast(found.sparkSession.createDataFrame(rows, "p long, before long"))
    place = F.col("before") + F.col("at").bitwiseAND((1 << 33) - 1)
    own = ordered.join(offset, part == F.col("p")).withColumn("w", F.get(F.array(*map(F.lit, weights)), (place % len(weights)).cast("int")))
    own = staged(own.select(F.col("source").alias("s"), "n", "w", F.lit(None).cast("double").alias("target")), "weighed")
    left = float(own.agg(F.sum("n").alias("n")).first().n or 0)
    while True:
        total = own.where("target is null").agg(F.sum("w").alias("w")).first().w
        if not total:
            return own.select("s", "target")
        share, cap = F.lit(left) * F.col("w") / F.lit(float(total)), most * F.col("n").cast("double")
        over = F.col("target").isNull() & (share > cap)
        taken = own.where(over).agg(F.sum(cap).alias("n")).first().n
        if taken is None:
            return own.select("s", F.coalesce("target", share).alias("target"))
        own = staged(own.withColumn("target", F.when(over, cap).otherwise(F.col("target"))), "weighed")
        left -= taken


def duel(t: pa.Table, last: bool) -> pa.Table:
    """Round all fractions of one chunk but one; that one too if last."""
    t = t.sort_by([("size", "descending"), ("doc_id", "ascending"), ("th", "ascending")])
    parts, whole = t.column("part").to_pylist(), t.column("whole").to_pylist()
    ids = t.column("doc_id").to_pylist()
    draw = random.Random(f"{ids[0]}:{ids[-1]}:{len(ids)}:{last}").random if ids else None
    copies: list[int | None] = [None] * len(ids)
    held = -1
    for i, p in enumerate(parts):
        if p <= 0.0 or p >= 1.0:
            copies[i] = whole[i] + int(p >= 1.0)
            continue
        if held < 0:
            held = i
            continue
        q = parts[held]
        both = p + q
        if both < 1.0:
            win, lose = (i, held) if draw() * both < p else (held, i)
            copies[lose], parts[win], held = whole[lose], both, win
        else:
            win, lose = (i, held) if draw() * (2.0 - both) < 1.0 - q else (held, i)
            copies[win], parts[lose], held = whole[win] + 1, both - 1.0, lose
            if parts[lose] <= 0.0:
                copies[lose], held = whole[lose], -1
    if last and held >= 0:
        copies[held] = whole[held] + int(draw() < parts[held])
    t = t.set_column(t.schema.get_field_index("part"), "part", pa.array(parts, pa.float64()))
    return t.set_column(t.schema.get_field_index("copies"), "copies", pa.array(copies, pa.int32()))


def _duels(last: bool):
    return lambda t: duel(t, last)


def mix(docs: DataFrame, weights: Sequence[int] = (5, 2, 1), most: int = 3, chunk_rows: int = 2048, fan: int = 64, max_broadcast: int = 100_000) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken; one row for each document."""
    return mixed(docs, weights, most, chunk_rows, fan, max_broadcast).drop("th")


def mixed(docs: DataFrame, weights: Sequence[int] = (5, 2, 1), most: int = 3, chunk_rows: int = 2048, fan: int = 64, max_broadcast: int = 100_000) -> DataFrame:
    """The rows of mix(), and th, a hash of the text."""
    spark = docs.sparkSession
    sized = staged(
        docs.select(
            F.col("doc_id").cast("long").alias("doc_id"),
            F.col("source").cast("string").alias("source"),
            F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
            F.xxhash64(F.col("text").cast("string")).alias("th"),
        ),
        "sized",
    )
    found = staged(sized.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("rows")), "sources")
    n_sources = found.count()
    if not n_sources:
        return sized.selectExpr("doc_id", "th", "source", "size", "0L source_size", "0D target", "0 copies", "0L taken")
    if n_sources <= max_broadcast:
        goal = targets({r.source: r.n for r in found.select("source", "n").collect()}, weights, most)
        goals = spark.createDataFrame(list(goal.items()), "s string, target double")
    else:
        goals = many_targets(found, weights, most)
    sources = found.join(goals, F.col("source").eqNullSafe(F.col("s")))
    rate = F.when(F.col("n") > 0, F.least(F.lit(float(most)), F.try_divide("target", "n"))).otherwise(0.0)
    sources = sources.select("s", F.col("n").alias("source_size"), "target", F.ceil(F.col("rows") / chunk_rows).cast("long").alias("chunks"), F.floor(rate).cast("int").alias("whole"), (rate - F.floor(rate)).alias("part"))
    sources = staged(sources, "targets")
    widest = sources.agg(F.max("chunks").alias("n")).first().n
    sources = F.broadcast(sources) if n_sources <= max_broadcast else sources
    rows = sized.join(sources, F.col("source").eqNullSafe(F.col("s"))).withColumn("chunk", F.pmod(F.xxhash64("doc_id", "th", F.lit(17)), "chunks"))
    # Rows that are alike land in one chunk: where they are too many they are spread over all chunks of their source.
    full = staged(rows.groupBy(F.col("source").alias("fs"), F.col("chunk").alias("fc")).count().where(F.col("count") > 4 * chunk_rows).drop("count"), "full-chunks")
    if full.limit(1).count():
        full = F.broadcast(full) if full.count() <= max_broadcast else full
        rows = rows.join(full, F.col("source").eqNullSafe(F.col("fs")) & (F.col("chunk") == F.col("fc")), "left")
        rows = rows.withColumn("chunk", F.when(F.col("fc").isNotNull(), F.pmod(F.xxhash64(F.monotonically_increasing_id()), "chunks")).otherwise(F.col("chunk")))
    rows = rows.withColumn("copies", F.lit(None).cast("int")).select(*[c.split()[0] for c in _ROWS.split(", ")])
    done = []
    while True:
        last = widest == 1
        rows = rows.groupBy("source", "chunk").applyInArrow(_duels(last), _ROWS)
        if last:
            done.append(rows)
            break
        rows = staged(rows, "duels")
        done.append(rows.where("copies is not null"))
        rows = rows.where("copies is null").withColumn("chunk", F.expr(f"chunk div {fan}"))
        widest = -(-widest // fan)
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out.select("doc_id", "th", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def repeat(docs: DataFrame, **how) -> DataFrame:
    """Each document as often as the mix takes it, with the columns it has; documents are told apart by doc_id, source and text."""
    taken = mixed(docs, **how).select(*_key(F.col("doc_id"), F.col("th"), F.col("source")), "copies").groupBy(*_KEY).agg(F.sum("copies").cast("int").alias("mix__copies"))
    own, back = apart(docs)
    key = _key(F.col("doc_id").cast("long"), F.xxhash64(F.col("text").cast("string")), F.col("source").cast("string"))
    # Keys without NULLs: one shuffle serves the distinct rows and the join.
    known = docs.select(*own, *key).dropDuplicates(_KEY).join(taken.where("mix__copies > 0"), _KEY)
    return known.select(*back, F.explode(F.array_repeat(F.lit(0), F.col("mix__copies"))).alias("mix__n")).select(*[F.col(f"`{c}`") for c in docs.columns])


_KEY = ["mix__dn", "mix__d", "mix__t", "mix__sn", "mix__s"]


def _key(doc_id: Column, th: Column, source: Column) -> list[Column]:
    values = (doc_id.isNull(), F.coalesce(doc_id, F.lit(0)), th, source.isNull(), F.coalesce(source, F.lit("")))
    return [v.alias(n) for v, n in zip(values, _KEY)]
