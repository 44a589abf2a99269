"""Closed and maximal flags by containment and root coverage."""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterable

from pyspark.sql import functions as F

from canopy.arrow import arrow_map
from canopy.mine.engine import Mined, Search
from canopy.pattern.model import Pattern
from canopy.pattern.morph import find_root_images, root_images

#: Blocked pairs beyond which containment is tested on the executors.
DRIVER_PAIRS = 50_000


def pair_blocks(smaller: Iterable[Mined], larger: Iterable[Mined]) -> list[tuple[Mined, Mined]]:
    """Pairs (P, Q) with Q larger and P's labels, counted, among Q's."""
    by_label: dict[str, list[tuple[Mined, Counter]]] = defaultdict(list)
    for q in larger:
        c = Counter(q.pattern.labels)
        for x in c:
            by_label[x].append((q, c))
    out = []
    for p in smaller:
        need = Counter(p.pattern.labels)
        rarest = min(need, key=lambda x: len(by_label[x]))
        out += [(p, q) for q, c in by_label[rarest] if q.size > p.size and all(c[x] >= n for x, n in need.items())]
    return out


def contained(search: Search, pairs: list[tuple[Mined, Mined]]) -> list[tuple[Mined, Mined, frozenset[int]]]:
    """Pairs with P an embedded subpattern of Q, and the root images of P in Q."""
    if len(pairs) <= DRIVER_PAIRS:
        found = ((p, q, root_images(p.pattern, q.pattern)) for p, q in pairs)
        return [x for x in found if x[2]]

    def make():
        def step(p: list, q: list, pl: list, pp: list, ql: list, qp: list):
            for a, b, *shape in zip(p, q, pl, pp, ql, qp):
                got = find_root_images(Pattern(tuple(shape[0]), tuple(shape[1])), Pattern(tuple(shape[2]), tuple(shape[3])))
                if got:
                    yield a, b, sorted(got)

        return step

    rows = [(p.id, q.id, list(p.pattern.labels), list(p.pattern.parent), list(q.pattern.labels), list(q.pattern.parent)) for p, q in pairs]
    df = search.spark.createDataFrame(rows, "p long, q long, pl array<string>, pp array<int>, ql array<string>, qp array<int>").repartition(64)
    got = arrow_map(df, make, "p long, q long, images array<int>").collect()
    return [(search.mined[r["p"]], search.mined[r["q"]], frozenset(r["images"])) for r in got]


def covering(search: Search, pairs: list[tuple[Mined, Mined, frozenset[int]]]) -> set[tuple[int, int]]:
    """(P, Q) with all of P's root images among those that Q has where P's root can be mapped.

    If the root maps to the root only, counts decide. The rest is one job over
    the occurrence tables: distinct images at the given positions.
    """
    out, inner = set(), defaultdict(list)
    for p, q, images in pairs:
        if 0 in images and p.support == q.support:
            out.add((p.id, q.id))
        elif images != {0}:
            inner[q.size] += [(p.id, q.id, n + 1) for n in images]
    tables = []
    for size, rows in inner.items():
        tables.append(search.images(size, rows))
    if tables:
        every = tables[0]
        for t in tables[1:]:
            every = every.union(t)
        key = ["tree_id"] if search.options.support == "document" else ["tree_id", "root"]
        counts = every.groupBy("p", "q", *key).agg(F.max("w").alias("w")).groupBy("p", "q").agg(F.sum("w").alias("n")).collect()
        out |= {(r["p"], r["q"]) for r in counts if r["n"] == search.mined[r["p"]].support}
    return out


def check_frequent(search: Search, some: list[Mined], witnesses: list[Mined]) -> None:
    """Flags of ``some`` by the definition, against all ``witnesses``."""
    pairs = contained(search, pair_blocks(some, witnesses))
    for p, _, _ in pairs:
        p.maximal = False
    covered = {p for p, _ in covering(search, pairs)}
    for p in some:
        p.closed = p.closed and p.id not in covered


def check_retained(search: Search, some: list[Mined]) -> None:
    """Flags as a serial comparison with the set of patterns retained so far gives them.

    All containments and coverages come from one job; only the order of
    insertions and evictions is replayed here, in the depth-first order of the
    search.
    """
    pairs = contained(search, pair_blocks(some, some))
    covered = covering(search, pairs)
    above: dict[int, set[int]] = defaultdict(set)
    below: dict[int, set[int]] = defaultdict(set)
    for p, q, _ in pairs:
        above[p.id].add(q.id)
        below[q.id].add(p.id)
    kept: set[int] = set()
    for m in depth_first(search, some):
        for other in sorted(kept):
            if other in below[m.id]:
                search.mined[other].maximal = False
                if (other, m.id) in covered:
                    kept.discard(other)
            elif other in above[m.id]:
                m.maximal = False
                if (m.id, other) in covered:
                    m.closed = False
        if m.closed:
            kept.add(m.id)
    for m in some:
        m.closed = m.id in kept


def depth_first(search: Search, some: list[Mined]) -> list[Mined]:
    children: dict[int, list[Mined]] = defaultdict(list)
    for m in search.mined.values():
        children[m.prefix].append(m)
    wanted, out = {m.id for m in some}, []
    stack = [m for root in sorted(search.labels, reverse=True) for m in children[root]][::-1]
    while stack:
        m = stack.pop()
        if m.id in wanted:
            out.append(m)
        stack += children[m.id][::-1]
    return out


def by_support(patterns: list[Mined]) -> set[int]:
    """Ids closed under the naive rule (no frequent superpattern of equal support), for contrast."""
    defeated = {p.id for p, q in pair_blocks(patterns, patterns) if p.support == q.support and root_images(p.pattern, q.pattern)}
    return {p.id for p in patterns} - defeated
