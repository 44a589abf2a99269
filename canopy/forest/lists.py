"""Inverted lists: the nodes of each label, in order, with their place in the list."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from canopy.forest.encode import preorder


def label_ids(nodes: DataFrame) -> DataFrame:
    """``(label, label_id)``: ids from 0 in label order; the dictionary holds one row for each label."""
    return nodes.select("label").distinct().withColumn("label_id", (F.dense_rank().over(Window.orderBy("label")) - 1).cast("int"))


def build(nodes: DataFrame) -> DataFrame:
    """``(label, tree_id, ord, begin, end, level)``; ``ord`` is the dense rank in the label's list, from 0.

    A label may hold most nodes, so the rank is a distributed one.
    """
    ranked = preorder(nodes.select("label", "tree_id", "begin", "end", "level"), ["tree_id", "begin"], group="label")
    return ranked.select("label", "tree_id", F.col("rank").alias("ord"), "begin", "end", "level")


def ordinals(nodes: DataFrame) -> DataFrame:
    """``nodes`` with ``ord``, the place in the label's list."""
    return preorder(nodes, ["tree_id", "begin"], group="label").withColumnRenamed("rank", "ord")


def label_counts(nodes: DataFrame) -> DataFrame:
    return nodes.groupBy("label").agg(F.count(F.lit(1)).alias("support"), F.count_distinct("tree_id").alias("trees"))


def frequent_labels(nodes: DataFrame, minsup: int) -> DataFrame:
    return label_counts(nodes).where(F.col("support") >= minsup)
