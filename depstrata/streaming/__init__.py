"""Dependencies over evolving data, with Structured Streaming.

ts columns without time zone have to be cast to timestamp before a watermark: with_watermark does it.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depstrata.operators.dependency import descendants
from depstrata.plans.tree import SchemaTree


def with_watermark(stream: DataFrame, ts: str = "ts", delay: str = "1 hour") -> DataFrame:
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def monitor(stream: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> DataFrame:
    """Groups of lhs with more than one rhs so far (update or complete mode).  More rows can only break an exact dependency, so a first violation is final.

    State: two digests for each value of lhs.
    """
    y = F.xxhash64(*[x for c in rhs for x in (F.col(c), F.col(c).isNull())])
    return stream.groupBy(*lhs).agg(F.min(y).alias("lo"), F.max(y).alias("hi"), F.count("*").alias("n")).where("lo <> hi").select(*lhs, "n")


def windowed_error(stream: DataFrame, lhs: Sequence[str], rhs: Sequence[str], ts: str = "ts", width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Both errors of lhs -> rhs in each window: two aggregations in a chain (append mode, after with_watermark)."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    pairs = stream.groupBy(w.alias("w"), *lhs, *rhs).agg(F.count("*").alias("n"))
    each = pairs.groupBy("w", *lhs).agg(F.max("n").alias("most"), F.sum("n").alias("total"), F.count("*").alias("kinds"))
    out = each.groupBy("w").agg(F.sum("most").alias("kept"), F.sum("total").alias("n_rows"), F.count("*").alias("r_lhs"), F.sum("kinds").alias("r_both"))
    return out.select(
        F.col("w.start").alias("start"), "n_rows", "r_lhs", "r_both",
        F.round(1 - F.col("kept") / F.col("n_rows"), 6).alias("error"), F.round(1 - F.col("r_lhs") / F.col("r_both"), 6).alias("ratio"),
    )


def sessions(stream: DataFrame, key: str, ts: str = "ts", gap: str = "30 minutes") -> DataFrame:
    """Rows and kinds of event of each session of a key."""
    s = F.session_window(ts, gap)
    return stream.groupBy(key, s.alias("s")).agg(F.count("*").alias("n"), F.approx_count_distinct("event_type").alias("kinds")).select(key, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n", "kinds")


def dedupe(stream: DataFrame, columns: Sequence[str]) -> DataFrame:
    """The table without duplicate rows that the searches assume; state ends with the watermark."""
    return stream.dropDuplicatesWithinWatermark(list(columns))


def enrich(stream: DataFrame, static: DataFrame, left: str, right: str) -> DataFrame:
    """Stream joined with a table."""
    return stream.join(static, F.col(left) == F.col(right)).drop(right)


def revalidate(tree: SchemaTree, table: list[DataFrame], broken: set[tuple[str, str]]):
    """A foreachBatch function: tests each edge of the tree on each batch; edges that break are collected, to rebuild below their nodes only.

    An edge can also break across batches: table[0], if given, is the data so far, and is tested with the batch on the keys of the batch alone.
    """

    def run(batch: DataFrame, _: int) -> None:
        for node, cols in tree.layers().items():
            rest = [c for c in cols if c != node]
            if not rest or len(cols) == len(rest):
                continue
            rows = batch.select(*cols)
            if table:
                keys = rows.select(F.col(node).alias("key__")).distinct()
                rows = rows.unionByName(table[0].select(*cols).join(keys, F.col(node).eqNullSafe(F.col("key__")), "left_semi"))
            kept = descendants(rows, node, rest)
            broken.update((node, c) for c in rest if c not in kept)

    return run


def sketch_state(states: list[DataFrame], sets: Sequence[Sequence[str]]):
    """A foreachBatch function: keeps a mergeable sketch of r(C) for each set of columns, to watch how it drifts."""

    def sketches(df: DataFrame) -> DataFrame:
        made = [F.hll_sketch_agg(F.xxhash64(*[x for c in s for x in (F.col(c), F.col(c).isNull())])).alias(f"s{i}") for i, s in enumerate(sets)]
        return df.agg(*made)

    def run(batch: DataFrame, _: int) -> None:
        new = sketches(batch)
        rows = [r for s in (*states, new) for r in s.collect()]  # one small row for each state
        merged = batch.sparkSession.createDataFrame(rows, new.schema).agg(*[F.hll_union_agg(f"s{i}").alias(f"s{i}") for i in range(len(sets))])
        states[:] = [batch.sparkSession.createDataFrame(merged.collect(), merged.schema)]

    return run


def estimates(state: DataFrame) -> list[int]:
    return list(state.select(*[F.hll_sketch_estimate(c) for c in state.columns]).first())


def replay(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream, oldest first."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def collected(stream: DataFrame, name: str, mode: str) -> DataFrame:
    """Run a stream over what is there and return the table of its output."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
