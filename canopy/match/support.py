"""Support of a pattern under three definitions."""

from __future__ import annotations

from pyspark.sql import DataFrame

from canopy.match.twig import occurrences, roots
from canopy.pattern.model import Pattern


def root(nodes: DataFrame, p: Pattern | str, kind: str = "emb") -> int:
    """Distinct images of the root; does not grow along prefixes."""
    return roots(nodes, p, kind).count()


def occurrence(nodes: DataFrame, p: Pattern | str, kind: str = "emb") -> int:
    """Matches; may grow along prefixes."""
    return occurrences(nodes, p, kind).count()


def document(nodes: DataFrame, p: Pattern | str, kind: str = "emb") -> int:
    """Trees with a match."""
    return roots(nodes, p, kind).select("tree_id").distinct().count()
