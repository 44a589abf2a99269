"""Joins of the members of a prefix class, and the order of a class."""

from __future__ import annotations

from canopy.pattern.canonical import Rank, identity
from canopy.pattern.model import Pattern


def child_join(px: Pattern, py: Pattern) -> Pattern | None:
    """The last node of py below the last node of px; needs equal positions."""
    return px.add(px.size - 1, py.labels[-1]) if py.attach_pos == px.attach_pos else None


def cousin_join(px: Pattern, py: Pattern) -> Pattern | None:
    """The last node of py beside the last node of px, at its own position."""
    return px.add(py.attach_pos, py.labels[-1]) if py.attach_pos <= px.attach_pos else None


def class_key(p: Pattern, rank: Rank = identity) -> tuple:
    return -p.attach_pos, rank(p.labels[-1])


def class_order(members: list[Pattern], rank: Rank = identity) -> list[Pattern]:
    """By position, the deepest first, then by label."""
    return sorted(members, key=lambda p: class_key(p, rank))


def expand_class(members: list[Pattern], rank: Rank = identity) -> list[tuple[Pattern, Pattern, str, Pattern]]:
    """(left, right, kind, result) of all joins, for each left parent child results first."""
    members, out = class_order(members, rank), []
    for px in members:
        for kind, join in (("child", child_join), ("cousin", cousin_join)):
            out += [(px, py, kind, q) for py in members if (q := join(px, py))]
    return out
