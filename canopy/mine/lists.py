"""Frequent patterns with list-based support."""

from __future__ import annotations

from pyspark.sql import DataFrame

from canopy.mine.miners import finished, grow, open_search
from canopy.mine.result import MiningResult


def mine_lists(nodes: DataFrame, minsup: float, lists: str = "rows", **kw) -> MiningResult:
    """Same patterns and supports as ``mine_frequent``, from lists in place of stored occurrences."""
    search = open_search(nodes, minsup, {"strategy": "lists", "lists": lists, **kw})
    grow(search)
    return finished(search, f"lists-{lists}")
