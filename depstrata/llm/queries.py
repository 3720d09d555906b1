"""The queries of the training-data operators: thin views of what the operators return."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depstrata.llm.common import load


def op1_vp_tree_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import ann

    return ann.search(load(spark, sf_dir, "embeddings"))


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import packing

    return packing.pack(packing.pieces(load(spark, sf_dir, "documents")))


def op4_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import mixing

    return mixing.mix(load(spark, sf_dir, "documents")).drop("source")


def op3_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import html

    return html.main_text(load(spark, sf_dir, "pages"))


def op5_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import line_rules

    return line_rules.judge(load(spark, sf_dir, "documents"))


def op6_quality_gam(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import gam

    docs = load(spark, sf_dir, "documents")
    model = gam.train(docs, load(spark, sf_dir, "labels"))
    scored = gam.classify(docs, model).withColumn("doc_id", F.col("doc_id").cast("long"))
    return scored.select("doc_id", gam.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import pii

    return pii.digest(pii.scan(load(spark, sf_dir, "documents")))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import neardup

    return neardup.near_duplicates(load(spark, sf_dir, "documents"))


def op9_repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import pfp

    return pfp.dedup(load(spark, sf_dir, "documents"), with_bytes=False).drop("kept")


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from depstrata.llm import licenses

    return licenses.scan(load(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {n: f for n, f in globals().items() if n.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    from depstrata.llm import oracles

    return oracles.ORACLES
