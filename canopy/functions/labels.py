"""Typed columns as node labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def cat_label(column: str, name: str | None = None) -> Column:
    """``name=value``; null stays null."""
    return F.concat(F.lit(f"{name or column}="), F.col(column).cast("string"))


def width_label(column: str, low: float, high: float, n: int, name: str | None = None) -> Column:
    """One of n buckets of equal width, 0 and n + 1 outside."""
    return F.concat(F.lit(f"{name or column}="), F.width_bucket(F.col(column).cast("double"), F.lit(float(low)), F.lit(float(high)), F.lit(n)).cast("string"))


def quantile_edges(df: DataFrame, column: str, n: int) -> list[float]:
    got = df.agg(F.percentile_approx(column, [k / n for k in range(1, n)], 10_000).alias("q")).first()["q"]
    return sorted(set(got or []))


def quantile_label(column: str, edges: list[float], name: str | None = None) -> Column:
    """The number of edges at or below the value."""
    return F.concat(F.lit(f"{name or column}=q"), sum(((F.col(column) >= e).cast("int") for e in edges), F.lit(0)).cast("string"))


def date_label(column: str, part: str = "month", name: str | None = None) -> Column:
    form = {"year": "yyyy", "month": "yyyy-MM", "day": "yyyy-MM-dd", "hour": "yyyy-MM-dd HH"}[part]
    return F.concat(F.lit(f"{name or column}="), F.date_format(F.date_trunc(part, F.col(column)), form))


def json_label(column: str, path: str) -> Column:
    return F.get_json_object(F.col(column), path)


def text_len_label(column: str | Column) -> Column:
    """``len=``: the number of digits of the text's length, 0 for none."""
    size = F.coalesce(F.length(column), F.lit(0))
    return F.concat(F.lit("len="), F.when(size > 0, F.length(size.cast("string"))).otherwise(F.lit(0)).cast("string"))


def array_children(df: DataFrame, key: str, column: str, name: str) -> DataFrame:
    """``(id, parent, label, o)``: a child for each element of an array, below its row's key."""
    each = df.select(F.col(key).alias("parent"), F.posexplode(column).alias("o", "value"))
    return each.select((F.col("parent") * 100_000 + F.col("o")).alias("id"), "parent", F.concat(F.lit(f"{name}="), F.col("value").cast("string")).alias("label"), F.col("o").cast("long").alias("o"))


def map_children(df: DataFrame, key: str, column: str) -> DataFrame:
    """``(id, parent, label, o)``: a child ``key=value`` for each entry of a map."""
    entries = df.select(F.col(key).alias("parent"), F.posexplode(F.array_sort(F.map_entries(column))).alias("o", "e"))
    return entries.select((F.col("parent") * 100_000 + F.col("o")).alias("id"), "parent", F.concat_ws("=", F.col("e.key").cast("string"), F.col("e.value").cast("string")).alias("label"), F.col("o").cast("long").alias("o"))
