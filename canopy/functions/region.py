"""Predicates on region codes, as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def is_ancestor(b1: Column, e1: Column, b2: Column, e2: Column) -> Column:
    return (b1 < b2) & (e2 < e1)


def is_parent(b1: Column, e1: Column, l1: Column, b2: Column, e2: Column, l2: Column) -> Column:
    return is_ancestor(b1, e1, b2, e2) & (l2 == l1 + 1)


def is_disjoint(b1: Column, e1: Column, b2: Column, e2: Column) -> Column:
    """Neither above the other, and not the same node."""
    return (e1 < b2) | (e2 < b1)


def same_path(b1: Column, e1: Column, b2: Column, e2: Column) -> Column:
    return ~is_disjoint(b1, e1, b2, e2)


def subtree_size(begin: Column, end: Column) -> Column:
    return F.floor((end - begin + 1) / 2)


def rank_of(begin: Column, level: Column) -> Column:
    """Place in preorder, from 0."""
    return F.floor((begin + level) / 2)
