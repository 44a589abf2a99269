"""The level loop: candidates of a level are evaluated in one Spark job.

The search space is metadata on the driver: patterns, their parents and their
counts. What grows with the data never leaves the executors: the occurrence
table of a level, ``occ(pattern_id, tree_id, img, x_end, y_end, w)``, where
``img`` holds the begins of all images in preorder of the pattern and ``w``
the number of equal trees that this one stands for.

An occurrence of a join result is a pair of its parents' occurrences that
agree on the common prefix and whose last images are one above the other
(child join) or disjoint (cousin join). So a level is one equi-join of the
level before with itself, keyed by the pattern and the prefix's images, which
live under one root and spread over all tasks.
"""

from __future__ import annotations

import time
from collections import defaultdict
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.forest.compress import root_pairs, weighted
from canopy.pattern.canonical import Rank, canonicalise, code, identity, is_canonical
from canopy.pattern.expand import child_join, class_key, cousin_join
from canopy.pattern.model import Pattern, single
from canopy.pattern.morph import one_smaller
from canopy.storage import stage, stored_bytes


@dataclass
class Mined:
    """A pattern whose support was computed."""

    id: int
    pattern: Pattern
    prefix: int
    left: int
    right: int
    kind: str
    support: int = 0
    n_occ: int = 0
    n_part: int = 0  # distinct images of the prefix and the right parent's last node
    sizes: tuple[int, ...] = ()  # entries of each node's list, where lists are stored
    locally_closed: bool = True
    locally_maximal: bool = True
    closed: bool = True
    maximal: bool = True
    pruned_by: tuple[int, str] | None = None
    canonical: bool = True

    @property
    def size(self) -> int:
        return self.pattern.size


@dataclass
class Counters:
    computed: int = 0
    freq: int = 0
    lclosed: int = 0
    lmax: int = 0
    closed: int = 0
    maximal: int = 0
    seconds: float = 0.0
    closed_seconds: float = 0.0
    occ_rows: int = 0
    stored_bytes: int = 0
    complete: bool = True
    levels: dict[int, tuple[int, int]] = field(default_factory=dict)


class TooMany(RuntimeError):
    """A level has more candidates than the budget; ``counters`` says how far the run came."""

    def __init__(self, level: int, n: int, counters: Counters):
        super().__init__(f"level {level} has {n} candidates")
        self.counters = counters


@dataclass
class Options:
    minsup: int
    max_size: int | None = None
    support: str = "root"
    where: Callable[[Pattern], bool] | None = None
    label_order: str = "bytes"
    max_candidates: int = 200_000
    roots: set[str] | None = None
    compress: bool = True
    apriori: bool = False
    max_occurrences: int = 400_000_000
    strategy: str = "tuples"
    lists: str = "rows"
    few_copies: bool = False  # of equal subtrees side by side, as many as a pattern can use; supports and flags stay exact, occurrences are not all counted


def label_rank(nodes: DataFrame, how: str) -> Rank:
    """``bytes``; ``depth``: labels that stand higher on average first; ``frequency``: frequent first."""
    if how == "bytes":
        return identity
    value = F.sum(F.col("level") * F.col("w")) / F.sum("w") if how == "depth" else -F.sum("w").cast("double")
    place = {r["label"]: (round(r["v"], 9), r["label"]) for r in weighted(nodes).groupBy("label").agg(value.alias("v")).collect()}
    return place.__getitem__


class Search:
    """All evaluated patterns of one run and the occurrences of each level."""

    def __init__(self, nodes: DataFrame, options: Options):
        if "w" in nodes.columns and options.support != "root":
            raise ValueError("only root support is defined over trees with weights")
        self.nodes, self.options, self.spark = weighted(nodes), options, nodes.sparkSession
        self.rows_held = 0
        self.rank = label_rank(nodes, options.label_order)
        self.mined: dict[int, Mined] = {}
        self.occ: dict[int, DataFrame] = {}
        self.counters = Counters()
        self.started = time.perf_counter()
        self.labels: dict[int, str] = {}
        self.known: tuple[int, set[Pattern]] = (-1, set())
        self.weights: DataFrame | None = None  # of the nodes, where those of a tree differ

    # seeds

    def counted(self, occ: DataFrame, id_col: str = "pattern_id", part: bool = False) -> dict[int, tuple[int, int, int]]:
        """Support, occurrences and (with ``part``) distinct right-parent parts of every pattern."""
        per_root = occ.groupBy(id_col, "tree_id", F.col("img")[0].alias("root")).agg(F.sum("w").alias("n"), F.max("w").alias("w"))
        if self.options.support == "document":
            per_root = per_root.groupBy(id_col, "tree_id").agg(F.sum("n").alias("n"), F.max("w").alias("w"))
        support = F.sum("n") if self.options.support == "occurrence" else F.sum("w")
        got = per_root.groupBy(id_col).agg(support.alias("support"), F.sum("n").alias("n"))
        if part:
            size = F.size("img")
            key = F.concat(F.slice("img", 1, size - 2), F.slice("img", size, 1))
            parts = occ.groupBy(id_col, "tree_id", key.alias("key")).agg(F.max("w").alias("w")).groupBy(id_col).agg(F.sum("w").alias("part"))
            got = got.join(parts, id_col)
        return {r[id_col]: (r["support"], r["n"], r["part"] if part else 0) for r in got.collect()}

    def allowed(self, p: Pattern) -> bool:
        return self.options.where is None or self.options.where(p)

    def seed(self) -> list[Mined]:
        """Frequent root labels, and all frequent 2-patterns under them."""
        n = self.options.minsup
        roots = self.nodes.groupBy("label").agg((F.count_distinct("tree_id") if self.options.support == "document" else F.sum("w")).alias("n")).where(F.col("n") >= n)
        if self.options.support == "occurrence":  # the root may be rarer than the pattern
            roots = self.nodes.select("label").distinct()
        if self.options.roots is not None:
            roots = roots.where(F.col("label").isin(sorted(self.options.roots)))
        self.roots = sorted((r["label"] for r in roots.select("label").collect()), key=self.rank)
        for k, x in enumerate(self.roots):
            self.labels[-1 - k] = x
        upper = self.nodes.where(F.col("label").isin(self.roots)).select("tree_id", F.col("begin").alias("a"), F.col("label").alias("a_label"), F.col("end").alias("x_end"))
        lower = self.nodes.select("tree_id", F.explode("anc").alias("a"), F.col("begin").alias("d"), F.col("end").alias("y_end"), F.col("label").alias("d_label"), "w")
        pairs = stage(lower.join(upper, ["tree_id", "a"]), "pairs")
        kinds = sorted(((r["a_label"], r["d_label"]) for r in pairs.select("a_label", "d_label").distinct().collect()), key=lambda k: (self.rank(k[0]), self.rank(k[1])))
        prefix_of = {x: k for k, x in self.labels.items()}
        new, rows = [], []
        for a, d in kinds:
            p = single(a).add(0, d)
            if self.allowed(p):
                m = Mined(len(self.mined), p, prefix_of[a], prefix_of[a], -1, "seed")
                self.mined[m.id] = m
                new.append(m)
                rows.append((m.id, a, d))
        if not rows:
            return []
        if self.options.compress and self.options.support == "root":
            per_root = pairs.groupBy("a_label", "d_label", "tree_id", "a").agg(F.max("w").alias("w")).groupBy("a_label", "d_label").agg(F.sum("w").alias("n"))
            often = [(r["a_label"], r["d_label"]) for r in per_root.where(F.col("n") >= n).collect()]
            most = self.options.max_size
            copies = most - 1 if self.options.few_copies and most else None
            pairs, trees = root_pairs(self.nodes, pairs, self.roots, sorted({x for k in often for x in k}), copies)
            if copies:
                self.weights = stage(trees.select("tree_id", F.col("begin").alias("root"), "w"), "weights")
        else:
            trees = self.nodes.select("tree_id", "begin", "end", "label", "anc", "w")
        table = self.spark.createDataFrame(rows, "pattern_id long, a_label string, d_label string")
        return self.evaluated(2, new, self.seeded(pairs.join(F.broadcast(table), ["a_label", "d_label"]), trees))

    def seeded(self, pairs: DataFrame, trees: DataFrame) -> DataFrame:
        """What is stored of the 2-patterns; ``trees`` holds the weighted nodes."""
        return stage(pairs.select("pattern_id", "tree_id", F.array("a", "d").alias("img"), "x_end", "y_end", "w"), "occ2")

    def evaluated(self, size: int, new: list[Mined], occ: DataFrame, part: bool = False) -> list[Mined]:
        """Fill in counts; keeps the frequent ones' occurrences for the next level."""
        counts = self.counted(occ, part=part)
        for m in new:
            m.support, m.n_occ, m.n_part = counts.get(m.id, (0, 0, 0))
            m.canonical = is_canonical(m.pattern, self.rank)
        return self.tallied(size, new, occ, sum(m.n_occ for m in new if m.support >= self.options.minsup))

    def tallied(self, size: int, new: list[Mined], occ: DataFrame, entries: int) -> list[Mined]:
        """The frequent ones of ``new``, with counters and budgets brought up to date."""
        frequent = [m for m in new if m.support >= self.options.minsup]
        c = self.counters
        c.computed += len(new)
        c.freq += sum(m.canonical for m in frequent)
        c.occ_rows += entries
        self.rows_held += occ.count()
        c.stored_bytes += stored_bytes(occ)
        c.levels[size] = (len(new), len(frequent))
        self.occ[size] = occ
        if self.rows_held > self.options.max_occurrences:  # rows that are stored, however many equal trees each stands for
            c.complete = False
            raise TooMany(size, len(new), c)
        return frequent

    # expansion

    def classes(self, frequent: Iterable[Mined]) -> dict[int, list[Mined]]:
        out: dict[int, list[Mined]] = defaultdict(list)
        for m in frequent:
            out[m.prefix].append(m)
        return {k: sorted(v, key=lambda m: class_key(m.pattern, self.rank)) for k, v in out.items()}

    def candidates(self, members: list[Mined], lefts: Iterable[Mined]) -> list[Mined]:
        """Join results of the given left parents with all members, child joins first."""
        out = []
        for x in lefts:
            for kind, join in (("child", child_join), ("cousin", cousin_join)):
                for y in members:
                    q = join(x.pattern, y.pattern)
                    if q is not None and self.allowed(q) and (not self.options.apriori or self.may_be_frequent(q)):
                        out.append(Mined(-1, q, x.id, x.id, y.id, kind))
        return out

    def may_be_frequent(self, q: Pattern) -> bool:
        """Whether all subpatterns with one node less and the same root are frequent; they have at least q's support."""
        if self.known[0] != len(self.mined):
            self.known = (len(self.mined), {canonicalise(m.pattern) for m in self.mined.values() if m.support >= self.options.minsup})
        return all(p in self.known[1] for p in one_smaller(q, keep_root=True))

    def admit(self, size: int, new: list[Mined]) -> None:
        """Number the candidates of a level, within the budget."""
        if len(new) > self.options.max_candidates:
            self.counters.complete = False
            raise TooMany(size, len(new), self.counters)
        for m in new:
            m.id = len(self.mined)
            self.mined[m.id] = m

    def join(self, size: int, new: list[Mined]) -> DataFrame:
        """Occurrences of the candidates of one level (patterns of ``size`` nodes)."""
        self.admit(size, new)
        table = F.broadcast(self.spark.createDataFrame([(m.id, m.left, m.right, m.kind == "child") for m in new], "q long, left long, right long, child boolean"))
        wanted = self.spark.createDataFrame([(k,) for k in sorted({i for m in new for i in (m.left, m.right)})], "pattern_id long")
        before = self.occ[size - 1].join(F.broadcast(wanted), "pattern_id", "left_semi")
        prefix, last = F.slice("img", 1, size - 2), F.col("img")[size - 2]
        x = before.join(table, F.col("pattern_id") == F.col("left")).select("q", "right", "child", "tree_id", prefix.alias("pre"), last.alias("x"), F.col("y_end").alias("x_end"), "w")
        y = before.select(F.col("pattern_id").alias("right"), "tree_id", prefix.alias("pre"), last.alias("y"), "y_end")
        inside = (F.col("y") > F.col("x")) & (F.col("y_end") < F.col("x_end"))
        beside = (F.col("y") > F.col("x_end")) | (F.col("y_end") < F.col("x"))
        both = x.join(y, ["right", "tree_id", "pre"]).where((F.col("child") & inside) | (~F.col("child") & beside))
        return stage(both.select(F.col("q").alias("pattern_id"), "tree_id", F.concat("pre", F.array("x", "y")).alias("img"), "x_end", "y_end", "w"), f"occ{size}")

    def local_flags(self, frequent: Iterable[Mined]) -> None:
        """Frequent join results against both parents: counts decide, since lists are nested."""
        for q in frequent:
            for parent in {q.left, q.right}:
                if parent in self.mined and self.mined[parent].support == q.support:
                    self.mined[parent].locally_closed = False
            if q.canonical and q.left in self.mined:
                self.mined[q.left].locally_maximal = False

    # reading what is stored

    def count_parts(self, size: int, possible: list[tuple[Mined, Mined]]) -> None:
        """``n_part`` of joins and ``n_occ`` of their right parents; tuples have been counted with their support."""

    def occurrences(self, size: int, ids: list[int]) -> DataFrame:
        """``(pattern_id, tree_id, img, x_end, y_end, w)`` of some patterns of a level."""
        some = self.spark.createDataFrame([(k,) for k in ids], "pattern_id long")
        return self.occ[size].join(F.broadcast(some), "pattern_id", "left_semi")

    def images(self, size: int, where: list[tuple[int, int, int]]) -> DataFrame:
        """``(p, q, tree_id, root, w)``: images of the node at a place (from 1) of q, for each ``(p, q, place)``."""
        at = self.spark.createDataFrame(where, "p long, pattern_id long, place int")
        found = self.occ[size].join(F.broadcast(at), "pattern_id").select("p", F.col("pattern_id").alias("q"), "tree_id", F.element_at("img", F.col("place")).alias("root"), "w")
        return found if self.weights is None else found.drop("w").distinct().join(self.weights, ["tree_id", "root"])

    def lists(self, size: int) -> DataFrame:
        """``(pattern_id, pos, tree_id, begin)`` of a level's patterns."""
        return self.occ[size].select("pattern_id", "tree_id", F.posexplode("img").alias("pos", "begin")).select("pattern_id", "pos", "tree_id", "begin").distinct()

    # results

    def reported(self) -> list[Mined]:
        """Frequent canonical patterns of two nodes or more."""
        return [m for m in self.mined.values() if m.canonical and m.support >= self.options.minsup and m.size >= 2]

    def code(self, m: Mined) -> str:
        return code(canonicalise(m.pattern))

    def class_names(self) -> dict[int, Pattern]:
        return {k: single(x) for k, x in self.labels.items()} | {m.id: m.pattern for m in self.mined.values()}
