"""Occurrence-join miner: the baseline that stores and joins all occurrences.

Patterns grow by frequent 2-patterns instead of class members: an occurrence
is extended by every descendant of a node on its rightmost path, and checked
against all of its images. It finds the same frequent patterns, but joins
whole occurrences with the pair table again and again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.mine.engine import Mined, Search
from canopy.mine.miners import finished, options
from canopy.mine.result import MiningResult
from canopy.pattern.canonical import is_canonical
from canopy.storage import stage


def extend(search: Search, size: int, frequent: list[Mined], pairs: DataFrame) -> list[Mined]:
    """All rightmost extensions of the canonical patterns of ``size`` nodes."""
    root_leaves = {m.pattern.labels for m in search.mined.values() if m.size == 2 and m.support >= search.options.minsup}
    rows, new = [], []
    for m in frequent:
        for position in m.pattern.rightmost_path:
            for label in sorted({x for _, x in root_leaves}):
                if (m.pattern.labels[0], label) not in root_leaves:
                    continue
                q = m.pattern.add(position, label)
                if search.allowed(q):
                    new.append(Mined(len(search.mined), q, m.id, m.id, -1, "extend", canonical=is_canonical(q, search.rank)))
                    search.mined[new[-1].id] = new[-1]
                    below = [p for p in range(size) if p == position or p in q.ancestors[position]]
                    rows.append((new[-1].id, m.id, position, label, [p in below for p in range(size)]))
    if not rows:
        return []
    table = F.broadcast(search.spark.createDataFrame(rows, "q long, pattern_id long, position int, label string, above array<boolean>"))
    grown = search.occ[size].join(table, "pattern_id").withColumn("a", F.col("img")[F.col("position")])
    both = grown.join(pairs, ["tree_id", "a", "label"])
    # above the new node: on the path to it; else disjoint from it
    fits = F.forall(
        F.arrays_zip("img", "ends", "above"),
        lambda x: F.when(x["above"], (x["img"] < F.col("d")) & (F.col("d_end") < x["ends"])).otherwise((x["ends"] < F.col("d")) | (F.col("d_end") < x["img"])),
    )
    occ = both.where(fits).select(F.col("q").alias("pattern_id"), "tree_id", F.concat("img", F.array("d")).alias("img"), F.concat("ends", F.array("d_end")).alias("ends"), "w")
    return search.evaluated(size + 1, new, stage(occ, f"tuples{size + 1}"))


def mine_occurrence_join(nodes: DataFrame, minsup: float, **kw) -> MiningResult:
    """Frequent patterns by joining stored occurrences; same result as the list miner."""
    search = Search(nodes, options(nodes, minsup, {"compress": False, **kw}))
    frequent = search.seed()
    if frequent:
        first = search.occ[2]
        search.occ[2] = first.withColumn("ends", F.array("x_end", "y_end"))
    pairs = stage(nodes.select("tree_id", F.explode("anc").alias("a"), "label", F.col("begin").alias("d"), F.col("end").alias("d_end")), "pairs")
    size, most = 2, search.options.max_size
    while frequent and (most is None or size < most):
        frequent = extend(search, size, [m for m in frequent if m.canonical], pairs)
        size += 1
    return finished(search, "occurrence-join")
