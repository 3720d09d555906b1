"""Helpers shared by the training-data operators."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A run of characters that are not space, tab, LF, VT, FF or CR.
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


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


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write df once as Parquet in the shared folder and read it back.

    Cuts the lineage: a lost executor costs no recomputation of what came before, and rows that hold
    generated ids are the same for every later reader.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete staged tables once what was made of them is staged itself."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df._staged_at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def apart(df: DataFrame) -> tuple[list[Column], list[Column]]:
    """All columns of a table under names that cannot clash, and the way back to their own names."""
    return [F.col(f"`{c}`").alias(f"own__{i}") for i, c in enumerate(df.columns)], [F.col(f"own__{i}").alias(c) for i, c in enumerate(df.columns)]


def words(text: Column) -> Column:
    """Array of the words of a text; empty for NULL."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), GAP), "")


def held(df: DataFrame, **made: Column) -> DataFrame:
    """Add columns that later expressions read as values: Catalyst does not inline through a generator."""
    row = F.struct(*[c.alias(n) for n, c in made.items()])
    return df.select("*", F.inline(F.array(row)))


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of frames that are no longer in use, instead of at some later collection."""
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)
