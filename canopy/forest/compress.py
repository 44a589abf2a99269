"""Equal trees once, with a weight.

Mining with root support counts distinct root images. Trees that are equal as
unordered labelled trees contribute equal numbers, so one of them with a
weight stands for all. Before that, the forest is cut at its topmost possible
pattern roots, and nodes whose label no frequent 2-pattern has are left out;
neither changes an ancestor-descendant pair that a frequent pattern can use.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from hashlib import sha256
from itertools import groupby, islice

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import arrow_map
from canopy.storage import stage

#: Larger trees are not gathered in one place; each stays as it is, with weight 1.
MOST_NODES = 4096
NODE = "struct<b:bigint,e:bigint,x:string,w:bigint>"


def canonical_tree(rows: list[tuple[int, int, str]], copies: int | None = None) -> tuple[str, list[tuple[int, int, str]]]:
    """The code of an unordered tree of (begin, end, label) rows, and its nodes renumbered in canonical order."""
    code, out = counted_tree(rows, copies)
    return code, [x[:3] for x in out]


def counted_tree(rows: list[tuple[int, int, str]], copies: int | None = None) -> tuple[str, list[tuple[int, int, str, int]]]:
    """``canonical_tree`` with the number of nodes that each node stands for.

    ``copies`` keeps so many of equal subtrees side by side: a pattern of so many nodes below its root can use no more.
    A subtree that is left out adds its nodes to those of an equal one. The same nodes of the same patterns can be
    mapped to both, so sums over images stay exact.
    """
    rows = sorted(rows)
    children: dict[int, list[int]] = defaultdict(list)
    open_: list[int] = []
    for n, (begin, _, _) in enumerate(rows):
        while open_ and rows[open_[-1]][1] < begin:
            open_.pop()
        if open_:
            children[open_[-1]].append(n)
        open_.append(n)
    codes = [""] * len(rows)
    stands = [1] * len(rows)

    def add(kept: int, gone: int) -> None:
        both = [(kept, gone)]
        while both:
            to, n = both.pop()
            stands[to] += stands[n]
            both += zip(children[to], children[n])

    for n in range(len(rows) - 1, -1, -1):
        children[n].sort(key=codes.__getitem__)
        if copies:
            left = []
            for _, same in groupby(children[n], codes.__getitem__):
                left += (few := list(islice(same, copies)))
                for c in same:
                    add(few[0], c)
            children[n] = left
        inner = ",".join(codes[c] for c in children[n])
        codes[n] = f"{rows[n][2]}({inner})" if inner else rows[n][2]
    out: list[list] = []
    stack: list[tuple[int, int]] = [(0, -1)]
    clock = 0
    while stack:
        n, done = stack.pop()
        if done >= 0:
            out[done][1] = clock
        else:
            stack.append((n, len(out)))
            out.append([clock, 0, rows[n][2], stands[n]])
            stack += [(c, -1) for c in reversed(children[n])]
        clock += 1
    return codes[0], [tuple(x) for x in out]


def weighted(nodes: DataFrame) -> DataFrame:
    """``nodes`` with ``w``, the number of equal trees that a tree stands for: 1 unless given."""
    return nodes if "w" in nodes.columns else nodes.withColumn("w", F.lit(1).cast("long"))


def root_pairs(nodes: DataFrame, pairs: DataFrame, roots: list[str], labels: list[str], copies: int | None = None) -> tuple[DataFrame, DataFrame]:
    """``pairs`` of root label and lower node, and the nodes, over weighted distinct trees.

    ``pairs(tree_id, a, x_end, a_label, d, y_end, d_label, w)`` holds the pairs of
    the whole forest, whose trees may have weights already. The result has the same columns; its nodes are
    ``(tree_id, begin, end, label, anc, w)``. With ``copies``, nodes of one tree have weights of their own, and a
    pair has that of its root.
    """
    kept = nodes.where(F.col("label").isin(labels)).select("tree_id", "begin", "end", "label", "anc", "w")
    top = pairs.groupBy("tree_id", F.col("d").alias("begin")).agg(F.min("a").alias("above"))
    own = F.when(F.col("label").isin(roots), F.col("begin"))
    placed = stage(kept.join(top, ["tree_id", "begin"], "left").withColumn("top", F.coalesce("above", own)).where("top IS NOT NULL").drop("above"), "placed")
    sizes = placed.groupBy("tree_id", "top").agg(F.count(F.lit(1)).alias("n"))
    small = sizes.where(F.col("n") <= MOST_NODES).select("tree_id", "top")
    large = stage(sizes.where(F.col("n") > MOST_NODES).select("tree_id", "top").withColumn("id", -1 - F.monotonically_increasing_id()), "large")

    def make():
        def step(trees: list, counts: list) -> Iterator[tuple]:
            for tree, n in zip(trees, counts):
                code, rows = counted_tree([(r["b"], r["e"], r["x"]) for r in tree])
                yield code, [{"b": b, "e": e, "x": x, "w": w} for b, e, x, w in rows], n

        return step

    def make_few():
        def step(trees: list, counts: list) -> Iterator[tuple]:
            for tree, n in zip(trees, counts):
                code, rows = counted_tree([(r["b"], r["e"], r["x"]) for r in tree], copies)
                key = sha256(code.encode()).digest()
                for b, e, x, w in rows:
                    yield key, b, e, x, w * n

        return step

    gathered = placed.join(small, ["tree_id", "top"], "left_semi").groupBy("tree_id", "top").agg(F.array_sort(F.collect_list(F.struct(F.col("begin").alias("b"), F.col("end").alias("e"), F.col("label").alias("x")))).alias("tree"), F.max("w").alias("w"))
    # trees that are equal in their own order meet first, so each is put in canonical order once
    start = F.col("tree")[0]["b"]
    moved = gathered.select(F.transform("tree", lambda v: F.struct((v["b"] - start).alias("b"), (v["e"] - start).alias("e"), v["x"].alias("x"))).alias("tree"), "w")
    ordered = moved.groupBy("tree").agg(F.sum("w").alias("n"))
    if copies:  # trees that differ in their numbers of copies only are equal now, and are summed node by node
        each = arrow_map(ordered.select("tree", "n"), make_few, "code binary, b long, e long, x string, w long").groupBy("code", "b", "e", "x").agg(F.sum("w").alias("w"))
        shapes = each.groupBy("code").agg(F.array_sort(F.collect_list(F.struct("b", "e", "x", "w"))).alias("tree"))
    else:
        same = arrow_map(ordered.select("tree", "n"), make, f"code string, tree array<{NODE}>, n long").groupBy("code").agg(F.sum("n").alias("w"), F.first("tree").alias("tree"))
        shapes = same.select(F.transform("tree", lambda v: v.withField("w", F.col("w"))).alias("tree"))
    shapes = stage(shapes.select(F.monotonically_increasing_id().alias("tree_id"), "tree"), "shapes")
    upper = shapes.select("tree_id", "tree", F.explode("tree").alias("u"))
    both = upper.where(F.col("u.x").isin(roots)).select("tree_id", "u", F.explode(F.filter("tree", lambda v: (v["b"] > F.col("u.b")) & (v["e"] < F.col("u.e")))).alias("v"))
    out = both.select("tree_id", F.col("u.b").alias("a"), F.col("u.e").alias("x_end"), F.col("u.x").alias("a_label"), F.col("v.b").alias("d"), F.col("v.e").alias("y_end"), F.col("v.x").alias("d_label"), F.col("u.w").alias("w"))
    inside = placed.join(large, ["tree_id", "top"]).select("tree_id", F.col("begin").alias("d"), "id")
    rest = pairs.where(F.col("d_label").isin(labels)).join(inside, ["tree_id", "d"]).select(F.col("id").alias("tree_id"), "a", "x_end", "a_label", "d", "y_end", "d_label", "w")
    above = F.transform(F.filter("tree", lambda v: (v["b"] < F.col("u.b")) & (v["e"] > F.col("u.e"))), lambda v: v["b"])
    few = upper.select("tree_id", F.col("u.b").alias("begin"), F.col("u.e").alias("end"), F.col("u.x").alias("label"), above.alias("anc"), F.col("u.w").alias("w"))
    more = placed.join(large, ["tree_id", "top"]).select(F.col("id").alias("tree_id"), "begin", "end", "label", "anc", "w")
    return stage(out.unionByName(rest), "weighted"), few.unionByName(more)
