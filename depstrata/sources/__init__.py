"""Reading tables, the no-duplicates policy, and sinks."""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterator, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depstrata.functions.columns import canonical


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, fmt: str, infer: bool = True, **options: str) -> DataFrame:
    """A file of unknown schema: csv, json, orc, text or parquet."""
    reader = spark.read.format(fmt).options(**options)
    if fmt == "csv":
        reader = reader.options(header=options.get("header", "true"), inferSchema=str(infer).lower())
    return reader.load(path)


def from_rows(spark: SparkSession, rows: Sequence, schema: str) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


def table(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)


def enforce_set(df: DataFrame, policy: str = "drop") -> DataFrame:
    """A table without duplicate rows.

    drop: one row of each is left; weight: the same, with the number of rows in a column weight; reject: an error if there is a duplicate.
    """
    df = canonical(df)
    if policy == "drop":
        return df.distinct()
    grouped = df.groupBy(*df.columns).agg(F.count("*").alias("weight"))
    if policy == "weight":
        return grouped
    if policy != "reject":
        raise ValueError(f"no such policy: {policy}")
    if grouped.where("weight > 1").limit(1).count():
        raise ValueError("the table has duplicate rows")
    return df


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share.  Where none is set, a temporary one in local mode (tests) and an error on a cluster."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        at = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = at.get() if at.isDefined() else None
    if not found and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not found:
        found = f"file://{tempfile.mkdtemp(prefix='depstrata-')}"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def staged(df: DataFrame, name: str = "stage") -> DataFrame:
    """Write once to the shared folder and read back: later jobs read this table, whatever executors are lost."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextlib.contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Within it files of a shuffle go when their query ends, not when the driver happens to collect garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(name)
        else:
            spark.conf.set(name, before)


def save_layers(layers: dict[str, DataFrame], path: str) -> None:
    for name, df in layers.items():
        df.write.mode("overwrite").parquet(f"{path}/{name}")


def save_features(df: DataFrame, path: str, partition_by: Sequence[str] = ()) -> None:
    df.write.mode("overwrite").partitionBy(*partition_by).parquet(path)


def save_bucketed(df: DataFrame, name: str, keys: Sequence[str], buckets: int) -> None:
    """A catalog table bucketed by a key: later counts of supersets of the key, and joins on it, need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)


def sample(df: DataFrame, fraction: float, seed: int = 7) -> DataFrame:
    return df.sample(fraction=fraction, seed=seed)


def save_tree(tree, path: str) -> None:
    with open(path, "w", encoding="utf-8") as f:
        f.write(tree.render("json"))
