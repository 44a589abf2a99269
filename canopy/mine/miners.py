"""The miners: frequent, post-filter, eager, pruned, and what is built on them."""

from __future__ import annotations

import time
from dataclasses import asdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.match.occlist import union_all
from canopy.mine import closed, surrogate
from canopy.mine.engine import Counters, Mined, Options, Search
from canopy.mine.liststore import ListSearch
from canopy.mine.result import MiningResult
from canopy.storage import stage


def threshold(nodes: DataFrame, minsup: float, label: str | None = None) -> int:
    """An absolute minsup; a fraction below 1 is taken of all nodes, or of those of one label."""
    if minsup >= 1:
        return int(minsup)
    return max(1, int(-(-minsup * nodes.where(F.col("label") == label if label else F.lit(True)).count() // 1)))


def options(nodes: DataFrame, minsup: float, kw: dict) -> Options:
    return Options(threshold(nodes, minsup), **kw)


def open_search(nodes: DataFrame, minsup: float, kw: dict) -> Search:
    """``strategy='tuples'`` stores occurrences, ``'lists'`` a list of images for each pattern node."""
    chosen = options(nodes, minsup, kw)
    if chosen.strategy not in ("tuples", "lists") or chosen.lists not in ("rows", "bitmap"):
        raise ValueError("strategy is tuples or lists, lists is rows or bitmap")
    return ListSearch(nodes, chosen) if chosen.strategy == "lists" else Search(nodes, chosen)


def grow(search: Search, rule: str = "none", pruning: bool = False) -> None:
    """The level loop. With ``pruning``, members with a surrogate lose their subtree."""
    frequent, size = search.seed(), 2
    most = search.options.max_size
    while frequent and (most is None or size < most):
        size += 1
        waves = split_waves(search, frequent) if pruning and rule != "none" else [[(m, list(m)) for m in search.classes(frequent).values()]]
        tables, results, marked, asked = [], [], {}, set()
        for wave in waves:
            new = [q for members, lefts in wave for q in search.candidates(members, [x for x in lefts if x.canonical and x.id not in marked])]
            held = held_back(search, new) if pruning and rule == "uniform" and size != most else set()
            late = [q for q in new if q.kind == "child" and q.left in held]
            new = [q for q in new if not (q.kind == "child" and q.left in held)]
            for last in (False, True):
                step = [q for q in late if q.left not in marked] if last else new
                if not step:
                    continue
                occ = search.join(size, step)
                found = search.evaluated(size, step, occ, part=pruning)
                search.local_flags(found)
                tables.append(occ)
                results += step
                if late and not last:
                    search.occ[size] = union_all(tables)
                    pairs = surrogate.find_candidates(search, results)
                    marked = surrogate.decide(search, size, results, pairs, rule) | marked
                    asked |= set(pairs)
            if pruning and rule != "none" and wave is not waves[-1]:
                pairs = [p for p in surrogate.find_candidates(search, results) if surrogate.shortcut(search, p)]
                marked |= {p.y: (p.x, p.kind) for p in pairs}
        if not results:
            break
        search.occ[size] = union_all(tables)
        search.counters.levels[size] = (len(results), sum(q.support >= search.options.minsup for q in results))
        found = [q for q in results if q.support >= search.options.minsup]
        if pruning:
            # all cousin joins of a pair's y were there when it was asked about, so its answer stands
            pairs = [p for p in surrogate.find_candidates(search, results) if p not in asked and p.y not in marked]
            marked = surrogate.decide(search, size, results, pairs, rule) | marked
            for y, why in marked.items():
                search.mined[y].pruned_by = why
        frequent = [q for q in found if q.left not in marked]


def held_back(search: Search, new: list[Mined]) -> set[int]:
    """Left parents that the first of their class may stand above: their child joins wait for that answer.

    A node below y is below or beside any surrogate with y, so only the cousin joins of y can refute one.
    """
    first: dict[int, int] = {}
    for q in new:
        first.setdefault(search.mined[q.left].prefix, q.left)
    return {q.right for q in new if q.kind == "child" and first[search.mined[q.left].prefix] == q.left != q.right}


def split_waves(search: Search, frequent: list[Mined]) -> list[list[tuple[list[Mined], list[Mined]]]]:
    """Left parents at a class's deepest position first: they may spare the others their expansion."""
    first, rest = [], []
    for members in search.classes(frequent).values():
        deepest = members[0].pattern.attach_pos
        deep = [m for m in members if m.pattern.attach_pos == deepest]
        high = [m for m in members if m.pattern.attach_pos != deepest]
        first.append((members, deep))
        if high:
            rest.append((members, high))
    return [first, rest] if rest else [first]


def finished(search: Search, miner: str) -> MiningResult:
    c, found = search.counters, search.reported()
    c.lclosed = sum(m.locally_closed for m in found)
    c.lmax = sum(m.locally_maximal for m in found)
    c.closed = sum(m.closed for m in found)
    c.maximal = sum(m.maximal for m in found)
    c.seconds = time.perf_counter() - search.started
    return MiningResult(miner, search)


def mine_frequent(nodes: DataFrame, minsup: float, **kw) -> MiningResult:
    """All frequent patterns; flags are not computed."""
    search = open_search(nodes, minsup, kw)
    grow(search)
    return finished(search, "frequent")


def mine_postfilter(nodes: DataFrame, minsup: float, **kw) -> MiningResult:
    """All frequent patterns, then every one against every larger one: the definition."""
    search = open_search(nodes, minsup, kw)
    grow(search)
    at = time.perf_counter()
    found = search.reported()
    closed.check_frequent(search, found, found)
    search.counters.closed_seconds = time.perf_counter() - at
    return finished(search, "postfilter")


def flag_local(search: Search, some: list[Mined], witness: str) -> None:
    """Only locally closed patterns are compared; the others are neither closed nor maximal."""
    at = time.perf_counter()
    checked = [m for m in some if m.locally_closed]
    for m in some:
        if not m.locally_closed:
            m.closed = m.maximal = False
    if witness == "retained":
        closed.check_retained(search, checked)
    else:
        closed.check_frequent(search, checked, search.reported())
    search.counters.closed_seconds = time.perf_counter() - at


def mine_eager(nodes: DataFrame, minsup: float, witness: str = "frequent", **kw) -> MiningResult:
    """Closedness checked for locally closed patterns only.

    ``witness``: ``frequent`` compares with all frequent patterns (the
    definition), ``retained`` with the closed patterns retained so far.
    """
    search = open_search(nodes, minsup, kw)
    grow(search)
    flag_local(search, search.reported(), witness)
    return finished(search, "eager")


def mine_pruned(nodes: DataFrame, minsup: float, rule: str = "uniform", allow_boundary: bool = False, **kw) -> MiningResult:
    """The search space pruned by surrogates.

    A pruned pattern has an equivalent one of one node more, which ``max_size``
    may cut off, so both together raise an error. ``allow_boundary`` accepts
    that patterns of ``max_size`` nodes can be missing.
    """
    if kw.get("max_size") and rule != "none" and not allow_boundary:
        raise ValueError("pruning loses patterns of max_size nodes: leave out max_size, or pass allow_boundary=True")
    if kw.get("few_copies"):
        raise ValueError("surrogates need all occurrences counted: leave out few_copies")
    search = open_search(nodes, minsup, kw)
    grow(search, rule, pruning=True)
    found = search.reported()
    for m in found:
        if m.pruned_by:
            m.locally_closed = False
    flag_local(search, found, "frequent")
    return finished(search, f"pruned-{rule}")


def mine_maximal(nodes: DataFrame, minsup: float, **kw) -> DataFrame:
    return mine_pruned(nodes, minsup, **kw).patterns().where("is_maximal")


def mine_constrained(nodes: DataFrame, minsup: float, forbidden: set[str] = frozenset(), required: set[str] = frozenset(), max_depth: int | None = None, root: str | None = None, **kw) -> DataFrame:
    """Patterns under user constraints. Those that subpatterns inherit cut the search; required labels filter its result.

    A pattern with the required labels, and any that contains it, has all its images in trees that hold them, so only
    these trees are searched: what is left of the result has the same supports and flags.
    """

    def where(p) -> bool:
        return not set(p.labels) & set(forbidden) and (max_depth is None or p.depth <= max_depth)

    minsup = threshold(nodes, minsup)
    if required:
        holds = nodes.where(F.col("label").isin(sorted(required))).groupBy("tree_id").agg(F.count_distinct("label").alias("n")).where(F.col("n") == len(required))
        nodes = stage(nodes.join(holds, "tree_id", "left_semi"), "held")
    got = mine_eager(nodes, minsup, where=where, roots={root} if root else None, few_copies=root is not None, **kw).patterns()
    for x in sorted(required):
        got = got.where(F.array_contains("labels", x))
    return got


def counters_frame(spark, results: list[tuple[str, MiningResult]]) -> DataFrame:
    """One row of counters for each run."""
    rows = [(w, r.miner, r.search.options.minsup, *(int(asdict(r.counters)[k]) for k in ("computed", "freq", "lclosed", "lmax", "closed", "maximal", "occ_rows", "stored_bytes")), r.counters.seconds, r.counters.closed_seconds) for w, r in results]
    return spark.createDataFrame(rows, "workload string, miner string, minsup long, computed long, freq long, lclosed long, lmax long, closed long, maximal long, occ_rows long, stored_bytes long, seconds double, closed_seconds double")


__all__ = ["Counters", "mine_constrained", "mine_eager", "mine_frequent", "mine_maximal", "mine_postfilter", "mine_pruned", "threshold"]
