"""Order of patterns and their canonical form.

Patterns compare by root label, then by their lists of child subtrees; a list
that extends another comes first. The canonical form sorts the children of
every node by this order.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache

from canopy.pattern.codec import show
from canopy.pattern.model import Pattern, Tree, nested

#: Of labels: code points, which is the order of their UTF-8 bytes.
Rank = Callable[[str], object]
END = (1,)


def identity(label: str) -> str:
    return label


def key(t: Tree, rank: Rank = identity) -> tuple:
    """Sorts like the order of patterns: a child (0, ...) is before the end of a list (1,)."""
    return (rank(t.label), *((0, key(c, rank)) for c in t.children), END)


def compare(p: Pattern, q: Pattern, rank: Rank = identity) -> int:
    a, b = key(nested(p), rank), key(nested(q), rank)
    return (a > b) - (a < b)


def ordered(t: Tree, rank: Rank) -> Tree:
    return Tree(t.label, tuple(sorted((ordered(c, rank) for c in t.children), key=lambda c: key(c, rank))))


def canonical_form(p: Pattern, rank: Rank = identity) -> Pattern:
    """Without a cache: Python workers get functions by value, which a cache cannot be."""
    return ordered(nested(p), rank).pattern()


canonicalise = lru_cache(1 << 16)(canonical_form)


def is_canonical(p: Pattern, rank: Rank = identity) -> bool:
    return canonical_form(p, rank) == p


def code(p: Pattern) -> str:
    """Canonical text in label order; equal for equal unordered patterns."""
    return show(canonical_form(p))
