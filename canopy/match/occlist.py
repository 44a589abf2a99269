"""Occurrence lists of patterns, as rows or as bitmaps over inverted lists."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.pattern.model import Pattern


def lists_of(occ: DataFrame, p: Pattern) -> DataFrame:
    """``(pos, tree_id, begin)``: the distinct images of each pattern node."""
    images = F.array(*(F.struct(F.lit(n).alias("pos"), F.col(f"b{n}").alias("begin")) for n in range(p.size)))
    return occ.select("tree_id", F.explode(images).alias("x")).select("x.pos", "tree_id", "x.begin").distinct()


def to_bitmaps(rows: DataFrame, lists: DataFrame, keys: list[str], label: str = "label") -> DataFrame:
    """Lists of ``(*keys, label, tree_id, begin)`` as ``(*keys, label, bucket, bits)``; a bit is a place in the label's list."""
    placed = rows.join(lists.select("label", "tree_id", "begin", "ord"), ["label", "tree_id", "begin"])
    bucket = F.bitmap_bucket_number(F.col("ord")).alias("bucket")
    return placed.groupBy(*keys, label, bucket).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("ord"))).alias("bits"))


def bit_or(bitmaps: DataFrame, keys: list[str]) -> DataFrame:
    return bitmaps.groupBy(*keys, "bucket").agg(F.bitmap_or_agg("bits").alias("bits"))


def bit_and(bitmaps: DataFrame, keys: list[str], of: int) -> DataFrame:
    """The intersection of ``of`` bitmaps for each key; a bucket that one of them lacks is empty."""
    got = bitmaps.groupBy(*keys, "bucket").agg(F.bitmap_and_agg("bits").alias("bits"), F.count(F.lit(1)).alias("n"))
    return got.where(F.col("n") == of).drop("n")


def bit_count(bitmaps: DataFrame, keys: list[str]) -> DataFrame:
    return bitmaps.groupBy(*keys).agg(F.sum(F.bitmap_count("bits")).alias("n"))


def unpack(bitmaps: DataFrame, lists: DataFrame, keys: list[str], entry: list[str] = ["label", "tree_id", "begin"]) -> DataFrame:  # noqa: B006
    """Bitmaps as rows again: entries of the label's list whose bit is set."""
    entries = lists.withColumn("bucket", F.bitmap_bucket_number(F.col("ord"))).withColumn("bit", F.bitmap_bit_position(F.col("ord")))
    both = bitmaps.join(entries, ["label", "bucket"])
    byte = F.expr("cast(conv(hex(substring(bits, cast(bit div 8 as int) + 1, 1)), 16, 10) as int)")
    return both.where(byte.bitwiseAND(F.expr("shiftleft(1, cast(bit % 8 as int))")) != 0).select(*keys, *entry)


def equal_by_count(counts: DataFrame, whole: str, part: str) -> DataFrame:
    """Lists whose subset has as many entries: equal lists, since one contains the other."""
    return counts.where(F.col(whole) == F.col(part))


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
