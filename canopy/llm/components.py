"""Connected components of a link table, by repeated contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.storage import stage


def components(links: DataFrame) -> DataFrame:
    """``links(a, b)`` to ``(node, component)``: the smallest node it reaches.

    Every round sends each node to its smallest neighbour, relabels the links
    with those parents and drops the ones that became loops. A node that is no
    local minimum vanishes, so the number of nodes at least halves per round.
    Rounds are cut by written tables; only an emptiness test reaches the driver.
    Null or equal ends are ignored; an empty link table gives an empty result.
    """
    rest = stage(
        links.where(F.col("a") != F.col("b")).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(),
        "links",
    )
    labels = stage(rest.select(F.col("a").alias("node")).union(rest.select("b")).distinct().withColumn("component", F.col("node")), "labels")
    while not rest.isEmpty():
        both = rest.union(rest.select("b", "a"))
        parent = stage(both.groupBy("a").agg(F.min("b").alias("p")).select("a", F.least("a", "p").alias("p")), "parents")
        labels = stage(
            labels.join(parent, labels.component == parent.a, "left").select("node", F.coalesce("p", "component").alias("component")),
            "labels",
        )
        left, right = parent.toDF("a", "pa"), parent.toDF("b", "pb")
        rest = stage(
            rest.join(left, "a").join(right, "b").where("pa != pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(),
            "links",
        )
    return labels
