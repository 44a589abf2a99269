"""Ancestor-descendant joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.functions.region import is_ancestor

#: Levels above which exploding all ancestors costs more than a range join per tree.
DEEP = 64


def ancestor_pairs(nodes: DataFrame, above: DataFrame | None = None, below: DataFrame | None = None, how: str = "equi") -> DataFrame:
    """``(tree_id, a, a_end, a_label, d, d_end, d_label)`` of all ancestor-descendant pairs.

    ``above`` and ``below`` restrict the two ends by label (frames with a
    ``label`` column). ``equi`` explodes the ancestors of the lower node and
    joins on the key; ``range`` compares region codes inside a tree, which is
    the oracle and the way out for very deep trees.
    """
    upper = nodes if above is None else nodes.join(above.select("label").distinct(), "label", "left_semi")
    lower = nodes if below is None else nodes.join(below.select("label").distinct(), "label", "left_semi")
    a = upper.select("tree_id", F.col("begin").alias("a"), F.col("end").alias("a_end"), F.col("label").alias("a_label"))
    if how == "range":
        d = lower.select("tree_id", F.col("begin").alias("d"), F.col("end").alias("d_end"), F.col("label").alias("d_label"))
        return a.join(d, "tree_id").where(is_ancestor(F.col("a"), F.col("a_end"), F.col("d"), F.col("d_end")))
    d = lower.select("tree_id", F.explode("anc").alias("a"), F.col("begin").alias("d"), F.col("end").alias("d_end"), F.col("label").alias("d_label"))
    return a.join(d, ["tree_id", "a"]).select("tree_id", "a", "a_end", "a_label", "d", "d_end", "d_label")


def plan_join(nodes: DataFrame) -> str:
    """``equi``, or ``range`` if the deepest node has more than DEEP ancestors."""
    deepest = nodes.agg(F.max("level").alias("n")).first()["n"] or 0
    return "range" if deepest > DEEP else "equi"


def pair_table(nodes: DataFrame) -> DataFrame:
    """``(anc_label, desc_label, support, n_pairs)``; support counts distinct ancestors."""
    per_root = ancestor_pairs(nodes).groupBy("a_label", "d_label", "tree_id", "a").agg(F.count(F.lit(1)).alias("n"))
    return per_root.groupBy(F.col("a_label").alias("anc_label"), F.col("d_label").alias("desc_label")).agg(F.count(F.lit(1)).alias("support"), F.sum("n").alias("n_pairs"))
