"""Results of a run as tables, and what is read off them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from canopy.mine.engine import Counters, Search
from canopy.pattern.canonical import canonicalise
from canopy.pattern.codec import dot, parse
from canopy.pattern.morph import embeds, one_smaller

PATTERNS = "pattern_id long, prefix_id long, right_id long, k int, labels array<string>, parent array<int>, attach_pos int, join_kind string, code string, is_canonical boolean, support long, n_occ long, is_locally_closed boolean, is_locally_maximal boolean, is_closed boolean, is_maximal boolean, pruned_by struct<by:long,kind:string>"
RESULT = "code string, k int, support long, is_closed boolean, is_maximal boolean"


@dataclass
class MiningResult:
    miner: str
    search: Search

    @property
    def counters(self) -> Counters:
        return self.search.counters

    def patterns(self) -> DataFrame:
        """All frequent patterns with a canonical form, two nodes or more."""
        rows = []
        for m in self.search.reported():
            p = canonicalise(m.pattern)
            rows.append((m.id, m.prefix, m.right, m.size, list(p.labels), list(p.parent), m.pattern.attach_pos, m.kind, self.search.code(m), m.canonical, m.support, m.n_occ, m.locally_closed, m.locally_maximal, m.closed, m.maximal, m.pruned_by))
        return self.search.spark.createDataFrame(rows, PATTERNS)

    def result(self) -> DataFrame:
        return self.search.spark.createDataFrame([(self.search.code(m), m.size, m.support, m.closed, m.maximal) for m in self.search.reported()], RESULT)

    def codes(self, which: str = "frequent") -> set[str]:
        keep = {"frequent": lambda m: True, "closed": lambda m: m.closed, "maximal": lambda m: m.maximal}[which]
        return {self.search.code(m) for m in self.search.reported() if keep(m)}

    def occurrence_lists(self) -> DataFrame:
        """``(pattern_id, pos, tree_id, begin)`` of the frequent patterns; needs a run with ``compress=False``."""
        if self.search.options.compress:
            raise ValueError("equal trees were merged: run with compress=False")
        keep = self.search.spark.createDataFrame([(m.id,) for m in self.search.reported()], "pattern_id long")
        out = None
        for size in self.search.occ:
            part = self.search.lists(size).join(F.broadcast(keep), "pattern_id", "left_semi")
            out = part if out is None else out.union(part)
        return out


def search_tree(patterns: DataFrame) -> DataFrame:
    """``(parent, root, code, k)``: every pattern with the prefix it grew from; none above two nodes."""
    upper = patterns.select(F.col("pattern_id").alias("prefix_id"), F.col("code").alias("above"))
    return patterns.join(upper, "prefix_id", "left").select(F.col("above").alias("parent"), F.col("labels")[0].alias("root"), "code", "k")


def targets(patterns: DataFrame) -> DataFrame:
    """A row for each pattern and set (frequent, closed, maximal) it is in."""
    sets = F.array_compact(F.array(F.lit("frequent"), F.when(F.col("is_closed"), F.lit("closed")), F.when(F.col("is_maximal"), F.lit("maximal"))))
    return patterns.select("code", "k", "support", F.explode(sets).alias("target"))


def distribution(patterns: DataFrame, how: str = "rollup") -> DataFrame:
    """Patterns by size and target, with subtotals (``rollup`` or ``cube``)."""
    t = targets(patterns)
    return getattr(t, how)("target", "k").agg(F.count(F.lit(1)).alias("n"), F.max("support").alias("best"))


def compression(patterns: DataFrame) -> DataFrame:
    n = lambda c: F.sum(F.col(c).cast("long"))
    return patterns.agg(F.count(F.lit(1)).alias("n_frequent"), n("is_closed").alias("n_closed"), n("is_maximal").alias("n_maximal"))


def top(patterns: DataFrame, n: int, by: str = "support") -> DataFrame:
    """The n best of each size."""
    place = F.row_number().over(Window.partitionBy("k").orderBy(F.desc(by), "code"))
    return patterns.withColumn("place", place).where(F.col("place") <= n)


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Codes in both, only in the first, only in the second."""
    x, y = a.select("code"), b.select("code")
    return x.intersect(y).withColumn("side", F.lit("both")).unionByName(x.exceptAll(y).withColumn("side", F.lit("first"))).unionByName(y.exceptAll(x).withColumn("side", F.lit("second")))


def implied(closed_codes: set[str]) -> set[str]:
    """All patterns of two nodes or more that the given ones contain."""
    todo, seen = [parse(c) for c in closed_codes], set()
    while todo:
        p = canonicalise(todo.pop())
        if p not in seen and p.size >= 2:
            seen.add(p)
            todo += one_smaller(p)
    from canopy.pattern.canonical import code

    return {code(p) for p in seen}


def hierarchy(codes: set[str]) -> list[tuple[str, str]]:
    """(smaller, larger) pairs of the subpattern order without the implied ones."""
    ps = {c: parse(c) for c in codes}
    up = {c: {d for d in ps if ps[d].size > ps[c].size and embeds(ps[c], ps[d])} for c in ps}
    return sorted((c, d) for c in ps for d in up[c] if not any(d in up[e] for e in up[c]))


def to_dot(codes: list[str]) -> str:
    return "\n".join(dot(parse(c), f"p{n}") for n, c in enumerate(codes))


def write(result: MiningResult, folder: str) -> None:
    """``patterns``, ``olist`` and ``result`` as Parquet, partitioned by size; counters as CSV."""
    result.patterns().write.mode("overwrite").partitionBy("k").parquet(f"{folder}/patterns")
    if not result.search.options.compress:
        result.occurrence_lists().write.mode("overwrite").parquet(f"{folder}/olist")
    result.result().write.mode("overwrite").json(f"{folder}/result")
    from canopy.mine.miners import counters_frame

    counters_frame(result.search.spark, [("run", result)]).write.mode("overwrite").option("header", True).csv(f"{folder}/counters")
