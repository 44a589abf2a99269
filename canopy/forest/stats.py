"""Statistics of a forest, as the experiments report them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def label_paths(nodes: DataFrame) -> DataFrame:
    """Each node with the labels on its path, root first."""
    links = nodes.select("tree_id", "begin", F.explode("anc").alias("a"))
    above = nodes.select("tree_id", F.col("begin").alias("a"), F.col("label").alias("above"))
    paths = links.join(above, ["tree_id", "a"]).groupBy("tree_id", "begin").agg(F.array_sort(F.collect_list(F.struct("a", "above"))).alias("p"))
    return nodes.join(paths, ["tree_id", "begin"], "left").select("tree_id", "begin", "label", F.coalesce(F.col("p.above"), F.array().cast("array<string>")).alias("above"))


def describe(nodes: DataFrame) -> DataFrame:
    """One row: nodes, trees, labels, depth, label paths and nodes below an equal label."""
    paths = label_paths(nodes)
    shape = nodes.agg(F.count(F.lit(1)).alias("n_nodes"), F.count_distinct("tree_id").alias("n_trees"), F.count_distinct("label").alias("n_labels"), F.max("level").cast("long").alias("max_depth"), F.sum("level").alias("sum_depth"))
    kinds = paths.agg(
        F.count_distinct(F.array_join(F.concat("above", F.array("label")), "/")).alias("n_paths"),
        F.sum(F.array_contains("above", F.col("label")).cast("long")).alias("n_recursive"),
    )
    return shape.crossJoin(kinds)  # one row each
