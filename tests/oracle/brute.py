"""Definitions by brute force on small forests, independent of the engine."""

from itertools import product

from canopy.pattern.canonical import canonicalise
from canopy.pattern.codec import forest, show
from canopy.pattern.model import Pattern


def above(p):
    out = []
    for up in p.parent:
        out.append(out[up] | {up} if up >= 0 else set())
    return out


def embeddings(p, t):
    """All embeddings, by trying every assignment of nodes."""
    pa, ta = above(p), above(t)
    choices = [[n for n, x in enumerate(t.labels) if x == y] for y in p.labels]
    for image in product(*choices):
        if len(set(image)) == len(image) and all((m in pa[n]) == (image[m] in ta[image[n]]) for n in range(p.size) for m in range(p.size) if m != n):
            yield image


def subpatterns(t, most=None):
    """Codes of all embedded subpatterns of a tree, by choosing nodes with one of them on top."""
    ta, out = above(t), set()
    n = t.size
    for bits in range(1, 1 << n):
        nodes = [k for k in range(n) if bits >> k & 1]
        if most and len(nodes) > most:
            continue
        top = nodes[0]
        if any(top not in ta[k] for k in nodes[1:]):
            continue
        place = {k: i for i, k in enumerate(nodes)}
        parent = [-1] + [place[max(ta[k] & set(nodes))] for k in nodes[1:]]
        out.add(canonicalise(Pattern(tuple(t.labels[k] for k in nodes), tuple(parent))))
    return out


def roots(p, trees):
    return {(t, image[0]) for t, tree in enumerate(trees) for image in embeddings(p, tree)}


def mine(trees, minsup):
    """code -> (support, closed, maximal) of all frequent patterns of two nodes or more."""
    trees = forest(trees) if isinstance(trees, str) else trees
    pool = set().union(*(subpatterns(t) for t in trees))
    images = {p: roots(p, trees) for p in pool if p.size >= 2}
    frequent = {p: r for p, r in images.items() if len(r) >= minsup}
    out = {}
    for p, r in frequent.items():
        closed = maximal = True
        for q in frequent:
            if q.size > p.size:
                tops = {e[0] for e in embeddings(p, q)}
                if tops:
                    maximal = False
                    cover = {(t, e[k]) for t, tree in enumerate(trees) for e in embeddings(q, tree) for k in tops}
                    closed = closed and not r <= cover
        out[show(p)] = (len(r), closed, maximal)
    return out
