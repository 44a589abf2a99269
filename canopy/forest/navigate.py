"""Questions about nodes: relatives, paths, subtrees, depths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def some(nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    """The wanted ``(tree_id, begin)`` with their whole rows, columns prefixed by ``of_``."""
    return nodes.join(wanted.select("tree_id", "begin").distinct(), ["tree_id", "begin"]).select("tree_id", *(F.col(c).alias(f"of_{c}") for c in nodes.columns if c != "tree_id"))


def children(nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    return nodes.join(wanted.select("tree_id", F.col("begin").alias("parent")).distinct(), ["tree_id", "parent"])


def parent_of(nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    of = some(nodes, wanted)
    return nodes.join(of.select("tree_id", F.col("of_parent").alias("begin"), "of_begin"), ["tree_id", "begin"])


def ancestors_of(nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    of = some(nodes, wanted).select("tree_id", "of_begin", F.explode("of_anc").alias("begin"))
    return nodes.join(of, ["tree_id", "begin"])


def descendants_of(nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    deep = nodes.withColumn("of_begin", F.explode("anc"))
    return deep.join(wanted.select("tree_id", F.col("begin").alias("of_begin")).distinct(), ["tree_id", "of_begin"])


def siblings_of(nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    of = some(nodes, wanted).select("tree_id", "of_begin", F.col("of_parent").alias("parent"))
    return nodes.join(of, ["tree_id", "parent"]).where("begin != of_begin")


def lowest_common_ancestor(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """``pairs(tree_id, a, b)`` with ``lca``: the deepest node above or equal to both; null if there is none."""
    path = nodes.select("tree_id", "begin", F.concat("anc", F.array("begin")).alias("path"))
    left, right = path.toDF("tree_id", "a", "pa"), path.toDF("tree_id", "b", "pb")
    both = pairs.join(left, ["tree_id", "a"]).join(right, ["tree_id", "b"])
    return both.select("tree_id", "a", "b", F.array_max(F.array_intersect("pa", "pb")).alias("lca"))


def depth_histogram(nodes: DataFrame) -> DataFrame:
    return nodes.groupBy("level").agg(F.count(F.lit(1)).alias("n"))


def leaves(nodes: DataFrame) -> DataFrame:
    return nodes.where("end = begin + 1")


def roots(nodes: DataFrame) -> DataFrame:
    return nodes.where("level = 0")


def subtree(nodes: DataFrame, tree_id: int, begin: int) -> DataFrame:
    return nodes.where((F.col("tree_id") == tree_id) & ((F.col("begin") == begin) | F.array_contains("anc", F.lit(begin))))
