"""Quality rules by cross-document line frequency, in DataFrame operations only.

A line is lower-cased, its white space folded and its digit runs made one 0, then hashed.  For each host (here the
column source) the distinct documents that hold a line are counted; documents with one and the same text count as one.  Lines in more documents than the limit
(an absolute floor and a share of the host's distinct documents) are removed, and a document that keeps too few words, or
too small a share of them, is rejected.  Rules on single texts (base_failed) come first.

Edge cases: NULL or empty texts have no words, hence fail; a NULL source is a host of its own; repeated rows are judged each
by itself; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import GAP, held, staged, words

SYMBOLS = r"[#*$%&|<>]"


def normal_line(line: Column) -> Column:
    return F.lower(F.regexp_replace(F.array_join(words(line), " "), "[0-9]+", "0"))


def text_stats(docs: DataFrame, host: str = "source", span: int = 5) -> DataFrame:
    """doc_id, host, the five counts, and the lines of each text as (hash, words)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(host).cast("string").alias("host"), text.alias("text"))
    df = held(df, words=words(F.col("text")), full=F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    at = lambda i, k: F.get("words", i + k)
    windows = F.transform(F.sequence(F.lit(0), F.size("words") - span), lambda i: F.xxhash64(*[at(i, k) for k in range(span)]))
    df = held(
        df,
        h=F.when(F.size("words") >= span, windows).otherwise(F.array().cast("array<long>")),
        lines=F.transform("full", lambda x: F.struct(F.xxhash64(normal_line(x)).alias("h"), F.size(words(x)).alias("n"))),
        n_words=F.size("words").cast("long"),
        word_chars=F.length(F.regexp_replace("text", GAP, "")).cast("long"),
        n_symbols=F.regexp_count("text", F.lit(SYMBOLS)).cast("long"),
        n_dup_lines=(F.size("full") - F.size(F.array_distinct("full"))).cast("long"),
        text_hash=F.xxhash64("text"),
    ).drop("text", "words", "full")
    # Only texts with a window that comes again sort their windows.
    again = F.size(F.array_distinct("h")) < F.size("h")
    df = held(df, sorted=F.when(again, F.sort_array(F.transform("h", lambda x, i: F.struct(x.alias("x"), i.alias("i"))))))
    same = lambda j, k: F.coalesce(F.get("sorted", j)["x"] == F.get("sorted", j + k)["x"], F.lit(False))
    twice = F.filter(F.transform("sorted", lambda s, j: F.when(same(j, -1) | same(j, 1), s["i"])), lambda i: i.isNotNull())
    df = held(df, starts=F.sort_array(twice))
    covered = F.aggregate(
        "starts",
        F.struct(F.lit(0).alias("end"), F.lit(0).alias("n")),
        lambda a, i: F.struct((i + span).alias("end"), (a["n"] + i + span - F.greatest(i, a["end"])).alias("n")),
        lambda a: a["n"],
    )
    return df.select(
        "doc_id", "host", "n_words", "word_chars", "n_symbols", "n_dup_lines",
        F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"), "text_hash", "lines",
    )


def frequent_lines(rows: DataFrame, floor: int = 20, share: float = 0.01) -> DataFrame:
    """(host, h) of the lines above the limit.  A host has at most 1 / share times its mean number of lines a document of them."""
    each = rows.select("host", "text_hash", F.explode(F.array_distinct(F.col("lines.h"))).alias("h")).distinct()
    counts = each.groupBy("host", "h").count().where(F.col("count") > floor)
    hosts = rows.select("host", "text_hash").distinct().groupBy("host").agg(F.count("*").alias("n_docs")).withColumnRenamed("host", "of")
    return counts.join(hosts, F.col("host").eqNullSafe(F.col("of"))).where(F.col("count") > share * F.col("n_docs")).select("host", "h")


def judge(docs: DataFrame, host: str = "source", floor: int = 20, share: float = 0.01, least_words: int = 10, least_share: float = 0.3, max_broadcast: int = 200_000) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, n_removed_words."""
    rows = staged(text_stats(docs, host).withColumn("row", F.monotonically_increasing_id()), "text-stats")
    hot = staged(frequent_lines(rows, floor, share), "frequent-lines").withColumnRenamed("host", "of")
    hot = F.broadcast(hot) if hot.count() <= max_broadcast else hot
    lines = rows.select("row", "host", F.inline("lines"))
    gone = lines.join(hot.withColumnRenamed("h", "hot"), (F.col("h") == F.col("hot")) & F.col("host").eqNullSafe(F.col("of")))
    gone = gone.groupBy("row").agg(F.sum("n").alias("n_removed_words"))
    out = rows.drop("lines").join(gone, "row", "left").withColumn("n_removed_words", F.coalesce("n_removed_words", F.lit(0)).cast("long"))
    left = F.col("n_words") - F.col("n_removed_words")
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    depleted = reduce(lambda a, b: a | b, (left < least_words, left < least_share * F.col("n_words")))
    return out.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        failed.alias("base_failed"), (~failed & ~depleted).alias("kept"), "n_removed_words",
    )
