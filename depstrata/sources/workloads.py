"""The experiment tables, built from the given ones."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depstrata.functions.columns import value_parts
from depstrata.sources import load


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W1: one row for each order and part, with attributes of order, customer and part."""
    line = load(spark, sf_dir, "lineitem").groupBy("l_orderkey", "l_partkey")
    line = line.agg(F.sum("l_quantity").cast("long").alias("qty"), F.round(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")), 2).cast("double").alias("amount"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority", "o_orderstatus")
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_nationkey", "c_mktsegment", "c_acctbal")
    part = load(spark, sf_dir, "part")
    out = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return out.join(part, F.col("l_partkey") == F.col("p_partkey")).drop("o_orderkey", "c_custkey", "p_partkey")


def kpi_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W2: measures of user, day and quarter of a day, with attributes of the user and a text twin of the day."""
    events = load(spark, sf_dir, "events")
    day = F.to_date("ts")
    each = events.select("user_id", day.alias("day"), F.floor(F.hour("ts") / 6).cast("int").alias("slot"), "event_type", "value").groupBy("user_id", "day", "slot")
    each = each.agg(
        F.count("*").alias("n_events"),
        F.count_if(F.col("event_type") == "error").alias("n_err"),
        F.round(F.avg("value"), 6).alias("mean_value"),
        F.max("value").alias("max_value"),
    )
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_nationkey", "c_mktsegment")
    nation = load(spark, sf_dir, "nation")
    out = each.join(customer, F.col("user_id") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return out.select("user_id", "day", F.date_format("day", "'d'DDD").alias("day_no"), "slot", "c_name", "c_nationkey", "n_name", "n_regionkey", "c_mktsegment", "n_events", "n_err", "mean_value", "max_value")


def sales_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W4: lineitem with everything around it, 31 columns.  Nation and region have a fixed, small size."""
    t = lambda n: load(spark, sf_dir, n)
    orders = t("orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
    out = t("lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    out = out.join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    out = out.join(t("part"), F.col("l_partkey") == F.col("p_partkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return out.drop("o_orderkey", "c_custkey", "n_nationkey", "r_regionkey", "p_partkey", "s_suppkey")


def sales_keys(spark: SparkSession, sf_dir: str, pool: Sequence[str]) -> DataFrame:
    """W4 for searches among some columns of lineitem: these, and 128 bits for the values of all the others, rest0 and rest1.  What is joined goes by its numbers, not by its columns."""

    def short(df: DataFrame, keep: Sequence[str], name: str) -> DataFrame:
        values = [v for c in df.columns if c not in keep for v in value_parts(c, df.schema[c].dataType)]
        return df.select(*keep, *[F.xxhash64(F.lit(h), *values).alias(f"{name}{h}") for h in (0, 1)])

    t = lambda n: load(spark, sf_dir, n)
    orders = t("orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
    customer = t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    around = short(orders.join(short(customer, ["c_custkey"], "c"), F.col("o_custkey") == F.col("c_custkey")), ["o_orderkey"], "o")
    out = short(t("lineitem"), pool, "l").join(around, F.col("l_orderkey") == F.col("o_orderkey"))
    out = short(out.drop("o_orderkey"), pool, "lo").join(short(t("part"), ["p_partkey"], "p"), F.col("l_partkey") == F.col("p_partkey"))
    out = short(out.drop("p_partkey"), pool, "lop").join(short(t("supplier"), ["s_suppkey"], "s"), F.col("l_suppkey") == F.col("s_suppkey"))
    return short(out.drop("s_suppkey"), pool, "rest")


def widened(base: DataFrame, n: int, seed: int = 1) -> DataFrame:
    """W5: hash buckets of the base columns up to n columns."""
    have = base.columns
    made = [F.pmod(F.xxhash64(F.lit(seed + i), F.col(have[i % len(have)])), F.lit(2 + i % 7)).cast("int").alias(f"x{i}") for i in range(n - len(have))]
    return base.select("*", *made)


def twinned(base: DataFrame, n: int) -> DataFrame:
    """W5: twins of the base columns up to n columns, x<i> of column i modulo their number: as many answers as a wide table has, all known by rule."""
    have = base.columns
    return base.select("*", *[F.xxhash64(F.lit(i), F.col(have[i % len(have)])).alias(f"x{i}") for i in range(n - len(have))])


def pages_parsed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W8: pages with host and path of the url."""
    part = lambda p: F.parse_url(F.col("url"), F.lit(p))
    return load(spark, sf_dir, "pages").select("page_id", part("HOST").alias("host"), part("PATH").alias("path"), F.length("html").alias("n_html"))


def events_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W8: events with the fields of their JSON."""
    e = load(spark, sf_dir, "events")
    return e.select("event_id", "user_id", "event_type", F.from_json("props", "map<string,string>").alias("props"))
