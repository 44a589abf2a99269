"""Pattern-in-pattern tests, and neighbours of a pattern in the subpattern order."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

from canopy.pattern.canonical import canonical_form
from canopy.pattern.model import Pattern, Tree, nested


def fits(p: Pattern, q: Pattern, image: list[int], n: int, kind: str) -> bool:
    """Whether the last image agrees with all earlier ones."""
    y = image[n]
    if kind == "hom":
        return n == 0 or image[p.parent[n]] in q.ancestors[y]
    if y in image[:n]:
        return False
    if kind == "iso":
        return all((p.parent[n] == m) == (q.parent[y] == image[m]) and (q.parent[image[m]] != y) for m in range(n))
    return all((m in p.ancestors[n]) == (image[m] in q.ancestors[y]) and y not in q.ancestors[image[m]] for m in range(n))


def maps(p: Pattern, q: Pattern, kind: str = "emb", root: int | None = None) -> Iterator[tuple[int, ...]]:
    """All embeddings (``emb``), isomorphisms onto child edges (``iso``) or homomorphisms (``hom``) of p into q."""
    by_label: dict[str, list[int]] = {}
    for n, x in enumerate(q.labels):
        by_label.setdefault(x, []).append(n)
    image = [-1] * p.size

    def place(n: int) -> Iterator[tuple[int, ...]]:
        if n == p.size:
            yield tuple(image)
            return
        for y in by_label.get(p.labels[n], ()) if n or root is None else (root,):
            image[n] = y
            if p.labels[n] == q.labels[y] and fits(p, q, image[: n + 1], n, kind):
                yield from place(n + 1)

    yield from place(0)


def find_root_images(p: Pattern, q: Pattern, kind: str = "emb") -> frozenset[int]:
    """Nodes of q that the root of p can be mapped to."""
    if p.size > q.size or Counter(p.labels) - Counter(q.labels):
        return frozenset()
    return frozenset(n for n, x in enumerate(q.labels) if x == p.labels[0] and next(maps(p, q, kind, n), None) is not None)


root_images = lru_cache(1 << 18)(find_root_images)


def embeds(p: Pattern, q: Pattern) -> bool:
    return bool(find_root_images(p, q))


def iso_sub(p: Pattern, q: Pattern, root: bool = False) -> bool:
    """Isomorphic subpattern; with ``root``, roots must correspond."""
    return 0 in root_images(p, q, "iso") if root else bool(root_images(p, q, "iso"))


def one_smaller(p: Pattern, keep_root: bool = False) -> set[Pattern]:
    """Embedded subpatterns with one node less: a node is dropped, its children rise to its parent.

    A root is dropped only if it has one child, and not with ``keep_root``.
    """
    out = set()

    def without(t: Tree) -> Iterator[tuple[Tree, ...]]:
        """What can stand in t's place with one node of t gone."""
        yield t.children
        for k, c in enumerate(t.children):
            for instead in without(c):
                yield (Tree(t.label, (*t.children[:k], *instead, *t.children[k + 1 :])),)

    steps = without(nested(p))
    if keep_root:
        next(steps)
    for instead in steps:
        if len(instead) == 1:
            out.add(canonical_form(instead[0].pattern()))
    return out


def one_larger(p: Pattern, labels: list[str]) -> set[Pattern]:
    """Embedded superpatterns with one node more: a new node takes over some children of a node, or stands above the root."""
    out = set()

    def grown(t: Tree, label: str) -> Iterator[Tree]:
        n = len(t.children)
        for size in range(n + 1):
            for below in combinations(range(n), size):
                rest = tuple(c for k, c in enumerate(t.children) if k not in below)
                yield Tree(t.label, (*rest, Tree(label, tuple(t.children[k] for k in below))))
        for k, c in enumerate(t.children):
            for g in grown(c, label):
                yield Tree(t.label, (*t.children[:k], g, *t.children[k + 1 :]))

    top = nested(p)
    for label in labels:
        out.add(canonical_form(Tree(label, (top,)).pattern()))
        out.update(canonical_form(g.pattern()) for g in grown(top, label))
    return out
