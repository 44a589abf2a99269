"""Induced patterns: child edges and isomorphisms, for contrast with embedded ones."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.mine.closed import pair_blocks
from canopy.mine.engine import Mined, Search
from canopy.mine.miners import finished, options
from canopy.mine.result import MiningResult
from canopy.pattern.canonical import is_canonical
from canopy.pattern.model import single
from canopy.pattern.morph import root_images
from canopy.storage import stage


def mine_induced(nodes: DataFrame, minsup: float, **kw) -> MiningResult:
    """Frequent induced patterns by rightmost extension along child edges.

    Closed: no frequent isomorphic superpattern has the same support. Maximal:
    none is frequent. Support is by root images or, with
    ``support='document'``, by trees.
    """
    search = Search(nodes, options(nodes, minsup, kw))
    document = search.options.support == "document"
    # parent label and child label of frequent edges (by images of the parent, or trees)
    nodes = search.nodes
    up = nodes.select("tree_id", F.col("begin").alias("parent"), F.col("label").alias("up"))
    edges = stage(nodes.where("parent IS NOT NULL").select("tree_id", "parent", "label", F.col("begin").alias("d"), "w").join(up, ["tree_id", "parent"]), "edges")
    key = ["tree_id"] if document else ["tree_id", "parent"]
    counts = edges.groupBy("up", "label", *key).agg(F.lit(1).alias("one")).groupBy("up", "label").agg(F.count(F.lit(1)).alias("n")).collect()
    kinds = sorted((r["up"], r["label"]) for r in counts)
    below = {}
    for a, b in kinds:
        below.setdefault(a, []).append(b)
    labels = sorted({a for a, _ in kinds})
    search.labels = {-1 - k: x for k, x in enumerate(labels)}
    seeds, rows = [], []
    for k, a in search.labels.items():
        for b in below[a]:
            m = Mined(len(search.mined), single(a).add(0, b), k, k, -1, "seed")
            if search.allowed(m.pattern):
                search.mined[m.id] = m
                seeds.append(m)
                rows.append((m.id, a, b))
    if not rows:
        return finished(search, "induced")
    table = F.broadcast(search.spark.createDataFrame(rows, "pattern_id long, up string, label string"))
    occ = stage(edges.join(table, ["up", "label"]).select("pattern_id", "tree_id", F.array("parent", "d").alias("img"), "w"), "induced2")
    frequent, size, most = search.evaluated(2, seeds, occ), 2, search.options.max_size
    while frequent and (most is None or size < most):
        rows, new = [], []
        for m in frequent:
            if not m.canonical:
                continue
            for position in m.pattern.rightmost_path:
                for b in below.get(m.pattern.labels[position], ()):
                    q = m.pattern.add(position, b)
                    # a non-canonical extension has a canonical twin that grows elsewhere
                    if search.allowed(q) and is_canonical(q, search.rank):
                        new.append(Mined(len(search.mined), q, m.id, m.id, -1, "extend"))
                        search.mined[new[-1].id] = new[-1]
                        rows.append((new[-1].id, m.id, position, b))
        if not rows:
            break
        table = F.broadcast(search.spark.createDataFrame(rows, "q long, pattern_id long, position int, label string"))
        grown = search.occ[size].join(table, "pattern_id").withColumn("parent", F.col("img")[F.col("position")])
        both = grown.join(edges.select("tree_id", "parent", "label", "d"), ["tree_id", "parent", "label"]).where(~F.array_contains("img", F.col("d")))
        size += 1
        occ = stage(both.select(F.col("q").alias("pattern_id"), "tree_id", F.concat("img", F.array("d")).alias("img"), "w"), f"induced{size}")
        frequent = search.evaluated(size, new, occ)
    found = search.reported()
    for p, q in pair_blocks(found, found):
        if root_images(p.pattern, q.pattern, "iso"):
            p.maximal = False
            p.closed = p.closed and p.support != q.support
    return finished(search, "induced")
