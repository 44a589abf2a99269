"""Matches of one pattern: homomorphisms, embeddings, isomorphisms.

Candidate lists are first reduced by left-semi joins up and down the pattern,
which drops every node that is in no homomorphism; tuples are built only
afterwards, and only if they are wanted.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.functions.region import is_ancestor, is_disjoint
from canopy.match.sibling import conflict_free
from canopy.pattern.codec import parse_edges
from canopy.pattern.model import Pattern

KINDS = ("hom", "emb", "iso")


def candidates(nodes: DataFrame, p: Pattern) -> list[DataFrame]:
    return [nodes.where(F.col("label") == x).select("tree_id", "begin", "end", "parent", "anc") for x in p.labels]


def links(lower: DataFrame, child: bool) -> DataFrame:
    """``(tree_id, up)``: the nodes that a node of the list can hang below."""
    return lower.select("tree_id", (F.col("parent") if child else F.explode("anc")).alias("up")).distinct()


def reduced_lists(nodes: DataFrame, p: Pattern, child: tuple[bool, ...] | None = None, down: bool = True) -> list[DataFrame]:
    """For each pattern node, its images under all homomorphisms (with ``down``; else only the root's list is exact)."""
    child, lists = child or (False,) * p.size, candidates(nodes, p)
    for n in range(p.size - 1, 0, -1):
        up = links(lists[n], child[n]).withColumnRenamed("up", "begin")
        lists[p.parent[n]] = lists[p.parent[n]].join(up, ["tree_id", "begin"], "left_semi")
    if down:
        for n in range(1, p.size):
            above = lists[p.parent[n]].select("tree_id", F.col("begin").alias("above"))
            if child[n]:
                lists[n] = lists[n].join(above.withColumnRenamed("above", "parent"), ["tree_id", "parent"], "left_semi")
            else:
                held = lists[n].select("tree_id", "begin", F.explode("anc").alias("above")).join(above, ["tree_id", "above"], "left_semi").select("tree_id", "begin").distinct()
                lists[n] = lists[n].join(held, ["tree_id", "begin"], "left_semi")
    return lists


def pair_condition(p: Pattern, m: int, n: int, kind: str) -> Column:
    """What the images of two nodes, neither the parent of the other, must satisfy; m < n."""
    bm, em, bn, en = (F.col(c) for c in (f"b{m}", f"e{m}", f"b{n}", f"e{n}"))
    if kind == "emb":
        return is_ancestor(bm, em, bn, en) if m in p.ancestors[n] else is_disjoint(bm, em, bn, en)
    # an isomorphism has no further edge and no node twice
    return (bm != bn) & ~F.coalesce(F.col(f"p{n}") == bm, F.lit(False)) & ~F.coalesce(F.col(f"p{m}") == bn, F.lit(False))


def occurrences(nodes: DataFrame, p: Pattern | str, kind: str = "emb", child: tuple[bool, ...] | None = None) -> DataFrame:
    """``(tree_id, b0, e0, b1, e1, ...)``: begin and end of every node's image, one row a match."""
    if isinstance(p, str):
        p, child = parse_edges(p)
    if kind not in KINDS:
        raise ValueError(f"kind is one of {KINDS}")
    child = (True,) * p.size if kind == "iso" else child or (False,) * p.size
    lists = reduced_lists(nodes, p, child)
    out = lists[0].select("tree_id", F.col("begin").alias("b0"), F.col("end").alias("e0"), F.col("parent").alias("p0"))
    for n in range(1, p.size):
        up = p.parent[n]
        new = lists[n].select("tree_id", F.col("begin").alias(f"b{n}"), F.col("end").alias(f"e{n}"), F.col("parent").alias(f"p{n}"), (F.col("parent") if child[n] else F.explode("anc")).alias(f"b{up}"))
        out = out.join(new, ["tree_id", f"b{up}"])
        if kind != "hom":
            for m in range(n):
                if m != up:
                    out = out.where(pair_condition(p, m, n, kind))
    return out.select("tree_id", *(c for n in range(p.size) for c in (f"b{n}", f"e{n}")))


def roots(nodes: DataFrame, p: Pattern | str, kind: str = "emb", nested_labels: set[tuple[str, str]] | None = None) -> DataFrame:
    """Distinct root images ``(tree_id, begin)``.

    Homomorphisms need semi-joins only; so do embeddings of a pattern without
    conflicts (see ``conflict_free``), if ``nested_labels`` tells which labels
    occur above which.
    """
    if isinstance(p, str):
        p, child = parse_edges(p)
    else:
        child = None
    if kind == "hom" or kind == "emb" and nested_labels is not None and conflict_free(p, nested_labels):
        return reduced_lists(nodes, p, child, down=False)[0].select("tree_id", "begin")
    return occurrences(nodes, p, kind, child).select("tree_id", F.col("b0").alias("begin")).distinct()


def find(nodes: DataFrame, text: str, kind: str = "emb", what: str = "roots") -> DataFrame:
    """The twig query: ``A(B,C//D)`` to its occurrences, root images or counts."""
    if what == "roots":
        return roots(nodes, text, kind)
    found = occurrences(nodes, text, kind)
    return found if what == "occurrences" else supports(found)


def supports(occ: DataFrame) -> DataFrame:
    """One row: root, occurrence and document frequency of an occurrence relation."""
    per_root = occ.groupBy("tree_id", "b0").agg(F.count(F.lit(1)).alias("n"))
    per_tree = per_root.groupBy("tree_id").agg(F.count(F.lit(1)).alias("roots"), F.sum("n").alias("n"))
    return per_tree.agg(F.coalesce(F.sum("roots"), F.lit(0)).alias("root_support"), F.coalesce(F.sum("n"), F.lit(0)).alias("occ_support"), F.count(F.lit(1)).alias("doc_support"))


def root_list(occ: DataFrame) -> DataFrame:
    return occ.select("tree_id", F.col("b0").alias("begin")).distinct()
