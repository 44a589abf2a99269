"""The sibling constraint: images of siblings are not on one path."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.functions.region import is_disjoint
from canopy.pattern.model import Pattern


def keep_embedded(occ: DataFrame, p: Pattern) -> DataFrame:
    """Homomorphic occurrences (b0, e0, ...) that are embeddings."""
    for siblings in p.children:
        for m, n in combinations(siblings, 2):
            occ = occ.where(is_disjoint(*(F.col(c) for c in (f"b{m}", f"e{m}", f"b{n}", f"e{n}"))))
    return occ


def nested_labels(nodes: DataFrame) -> set[tuple[str, str]]:
    """Pairs (upper, lower) of labels that occur above each other; bounded by the label dictionary squared."""
    from canopy.match.structural import ancestor_pairs

    return {(r["a_label"], r["d_label"]) for r in ancestor_pairs(nodes).select("a_label", "d_label").distinct().collect()}


def conflict_free(p: Pattern, above: set[tuple[str, str]]) -> bool:
    """Whether no two siblings can meet on a path.

    Siblings of different labels, of which neither ever occurs above the
    other, have disjoint images. Then homomorphisms are embeddings, and
    semi-joins give exact lists.
    """
    for siblings in p.children:
        for m, n in combinations(siblings, 2):
            a, b = p.labels[m], p.labels[n]
            if a == b or (a, b) in above or (b, a) in above:
                return False
    return True
