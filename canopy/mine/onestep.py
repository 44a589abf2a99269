"""One-step superpattern check: the costly alternative to local closedness."""

from __future__ import annotations

from dataclasses import dataclass

from canopy.mine.closed import covering
from canopy.mine.miners import mine_frequent
from canopy.mine.result import MiningResult
from canopy.pattern.canonical import canonicalise
from canopy.pattern.morph import one_larger, root_images


@dataclass
class OneStep:
    """``generated`` superpatterns in all, ``distinct`` ones among them; closed and maximal codes."""

    result: MiningResult
    generated: int
    distinct: int
    closed: set[str]
    maximal: set[str]


def mine_onestep(nodes, minsup: float, **kw) -> OneStep:
    """For every frequent pattern, all superpatterns with one node more.

    A superpattern is frequent exactly if the miner found it. Maximal: none is
    frequent. Closed: none that is frequent covers the pattern's root images.
    Coverage is not transitive, so this may keep patterns that a larger
    superpattern defeats.
    """
    result = mine_frequent(nodes, minsup, **kw)
    search, found = result.search, result.search.reported()
    by_shape = {canonicalise(m.pattern): m for m in found}
    labels = sorted({x for m in found for x in m.pattern.labels})
    generated, distinct, pairs = 0, set(), []
    for m in found:
        bigger = one_larger(m.pattern, labels)
        generated += len(bigger)
        distinct |= bigger
        pairs += [(m, q, images) for b in bigger if (q := by_shape.get(b)) and (images := root_images(m.pattern, q.pattern))]
    covered = {p for p, _ in covering(search, pairs)}
    larger = {p.id for p, _, _ in pairs}
    return OneStep(result, generated, len(distinct), {search.code(m) for m in found if m.id not in covered}, {search.code(m) for m in found if m.id not in larger})
