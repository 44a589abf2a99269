"""Small labelled unordered trees, numbered depth-first from 0."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property


@dataclass(frozen=True)
class Pattern:
    """``labels[n]`` and ``parent[n]`` of each node n; the root's parent is -1."""

    labels: tuple[str, ...]
    parent: tuple[int, ...]

    def __post_init__(self) -> None:
        if len(self.labels) != len(self.parent) or not self.labels or self.parent[0] != -1:
            raise ValueError("a pattern has a root, and a parent for every label")
        path = [0]
        for n in range(1, len(self.parent)):
            while path and path[-1] != self.parent[n]:
                path.pop()
            if not path:
                raise ValueError("nodes are not numbered depth-first")
            path.append(n)

    @property
    def size(self) -> int:
        return len(self.labels)

    @cached_property
    def children(self) -> tuple[tuple[int, ...], ...]:
        out: list[list[int]] = [[] for _ in self.labels]
        for n in range(1, self.size):
            out[self.parent[n]].append(n)
        return tuple(map(tuple, out))

    @cached_property
    def ancestors(self) -> tuple[frozenset[int], ...]:
        out: list[frozenset[int]] = []
        for up in self.parent:
            out.append(out[up] | {up} if up >= 0 else frozenset())
        return tuple(out)

    @property
    def depth(self) -> int:
        return max(map(len, self.ancestors))

    @property
    def fanout(self) -> int:
        return max(map(len, self.children))

    @property
    def leaves(self) -> list[int]:
        return [n for n, c in enumerate(self.children) if not c]

    @property
    def is_path(self) -> bool:
        return self.fanout <= 1

    @property
    def attach_pos(self) -> int:
        """Where the rightmost leaf is attached."""
        return self.parent[-1]

    @property
    def rightmost_path(self) -> list[int]:
        return sorted(self.ancestors[-1]) + [self.size - 1]

    def prefix(self) -> Pattern:
        """Without the rightmost leaf."""
        return Pattern(self.labels[:-1], self.parent[:-1])

    def add(self, position: int, label: str) -> Pattern:
        """With a new rightmost leaf under ``position``, a node of the rightmost path."""
        if position not in self.rightmost_path:
            raise ValueError(f"{position} is not on the rightmost path")
        return Pattern((*self.labels, label), (*self.parent, position))

    def subtree(self, node: int) -> Pattern:
        inside = [n for n in range(self.size) if n == node or node in self.ancestors[n]]
        place = {n: k for k, n in enumerate(inside)}
        return Pattern(tuple(self.labels[n] for n in inside), tuple(place.get(self.parent[n], -1) if n != node else -1 for n in inside))


def single(label: str) -> Pattern:
    return Pattern((label,), (-1,))


@dataclass(frozen=True)
class Tree:
    """A nested tree, before its nodes are numbered."""

    label: str
    children: tuple[Tree, ...] = ()

    def pattern(self) -> Pattern:
        labels, parent = [], []

        def visit(t: Tree, up: int) -> None:
            labels.append(t.label)
            parent.append(up)
            own = len(labels) - 1
            for c in t.children:
                visit(c, own)

        visit(self, -1)
        return Pattern(tuple(labels), tuple(parent))


def nested(p: Pattern, node: int = 0) -> Tree:
    return Tree(p.labels[node], tuple(nested(p, c) for c in p.children[node]))
