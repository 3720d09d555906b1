"""Column profiles, decimals, canonical and digested keys."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_FRACTIONAL = (T.DoubleType, T.FloatType, T.DecimalType)


def canonical_column(name: str, kind: T.DataType) -> Column:
    """An expression that Spark can group by, equal for equal values."""
    c = F.col(f"`{name}`")
    if isinstance(kind, T.MapType):
        return F.when(c.isNotNull(), F.to_json(F.array_sort(F.map_entries(c)))).alias(name)
    if isinstance(kind, T.IntervalType if hasattr(T, "IntervalType") else ()) or type(kind).__name__.endswith("IntervalType"):
        return c.cast("string").alias(name)
    return c


def canonical(df: DataFrame, expand_structs: bool = False) -> DataFrame:
    """Maps and intervals as text; structs as one column for each field if wanted."""
    out: list[Column] = []
    for f in df.schema.fields:
        if expand_structs and isinstance(f.dataType, T.StructType):
            out += [F.col(f"`{f.name}`.`{g.name}`").alias(f"{f.name}_{g.name}") for g in f.dataType.fields]
        else:
            out.append(canonical_column(f.name, f.dataType))
    return df.select(*out)


def digest(columns: Sequence[str], bits: int = 128) -> Column:
    """A short key of a column set: hashes with independent seeds, and a mask of NULLs, which hashes skip."""
    cols = [F.col(f"`{c}`") for c in columns]
    mask = F.concat(F.lit(""), *[F.when(c.isNull(), "1").otherwise("0") for c in cols])
    return F.struct(*[F.xxhash64(F.lit(i), *cols).alias(f"h{i}") for i in range(bits // 64)], mask.alias("nulls"))


def value_parts(name: str, kind: T.DataType) -> tuple[Column, Column]:
    """What a hash has to see of a column, as hashes skip NULLs: whether it is NULL, and its value; what nests goes by its JSON."""
    c = F.col(f"`{name}`")
    if isinstance(kind, (T.ArrayType, T.StructType)):
        c = F.to_json(F.struct(c), {"ignoreNullFields": "false"})
    return F.col(f"`{name}`").isNull(), c


def value_keys(name: str, kind: T.DataType, alias: str) -> list[Column]:
    """Two numbers for a column's value, alias0 and alias1, with independent seeds; NULL has numbers of its own."""
    return [F.xxhash64(F.lit(2 + h), *value_parts(name, kind)).alias(f"{alias}{h}") for h in (0, 1)]


def _is_decimal(c: Column) -> Column:
    d = c.cast("double")
    return F.coalesce(F.bool_or(~F.isnan(d) & (F.abs(d) < float("inf")) & (d != F.floor(d))), F.lit(False))


def decimal_columns(df: DataFrame, mode: str = "value") -> list[str]:
    """Numeric columns with fractions.  value: some finite value has one; type: by type alone; off: none."""
    cols = [f.name for f in df.schema.fields if isinstance(f.dataType, _FRACTIONAL)]
    cols = [c for c in cols if not (isinstance(df.schema[c].dataType, T.DecimalType) and df.schema[c].dataType.scale == 0)]
    if mode == "off" or not cols:
        return []
    if mode == "type":
        return cols
    found = df.agg(*[_is_decimal(F.col(f"`{c}`")).alias(c) for c in cols]).first()
    return [c for c in cols if found[c]]


def profile(df: DataFrame, exact: bool = False, rsd: float = 0.02) -> DataFrame:
    """One row for each column: column_name, type, r, nulls, min, max, is_decimal, is_constant.  One pass, if not exact."""
    df = canonical(df)
    parts = []
    for f in df.schema.fields:
        c = F.col(f"`{f.name}`")
        orderable = not isinstance(f.dataType, (T.ArrayType, T.StructType, T.BinaryType))
        r = F.count_distinct(c) if exact else F.approx_count_distinct(c, rsd)
        parts.append(
            F.struct(
                F.lit(f.name).alias("column_name"),
                F.lit(f.dataType.simpleString()).alias("type"),
                (r + F.when(F.count(c) < F.count("*"), 1).otherwise(0)).cast("long").alias("r"),
                F.count_if(c.isNull()).alias("nulls"),
                (F.min(c).cast("string") if orderable else F.lit(None).cast("string")).alias("min"),
                (F.max(c).cast("string") if orderable else F.lit(None).cast("string")).alias("max"),
                (_is_decimal(c) if isinstance(f.dataType, _FRACTIONAL) else F.lit(False)).alias("is_decimal"),
            )
        )
    out = df.agg(F.array(*parts).alias("p")).select(F.inline("p"))
    return out.withColumn("is_constant", F.col("r") <= 1)
