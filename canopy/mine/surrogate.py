"""Surrogate patterns: when the subtree of a pattern need not be searched.

P_x is a surrogate of a later member P_y of its class if every occurrence of
P_y, and of whatever grows out of it, extends by x. All tests read the
occurrence tables of the level that was just evaluated: an occurrence of the
join of P_x and P_y is (prefix, x, y), one of the cousin join of P_y and P_z
is (prefix, y, z), so they meet on (prefix, y).

Rules:

``uniform``
    x is chosen by a function of P_y's occurrence alone, so it suits all later
    siblings together. Sound; the default.
``definition``
    Followers are tested one at a time, as printed; may lose patterns.
``filters``
    The definition and two necessary conditions that refute earlier; may lose
    patterns as well.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.mine.engine import Mined, Search
from canopy.storage import stage

RULES = ("uniform", "definition", "filters", "none")


@dataclass(frozen=True)
class Pair:
    """A member x that may stand for y; ``q`` is their join."""

    x: int
    y: int
    q: int
    kind: str


def find_candidates(search: Search, results: list[Mined]) -> list[Pair]:
    """Joins whose (prefix, y) parts are all of P_y's occurrences, with P_x before P_y."""
    place = {m.id: k for members in search.classes([search.mined[i] for i in {r.left for r in results} | {r.right for r in results}]).values() for k, m in enumerate(members)}
    possible = [(q, search.mined[q.right]) for q in results if place[q.left] < place[q.right]]
    if possible:
        search.count_parts(possible[0][0].size, possible)
    return [Pair(q.left, y.id, q.id, q.kind) for q, y in possible if q.n_part == y.n_occ and y.n_occ > 0]


def shortcut(search: Search, pair: Pair) -> bool:
    """Cousins at different positions: followers of y hang too high to meet x."""
    return pair.kind == "cousin" and search.mined[pair.x].pattern.attach_pos > search.mined[pair.y].pattern.attach_pos


def decide(search: Search, size: int, results: list[Mined], pairs: list[Pair], rule: str) -> dict[int, tuple[int, str]]:
    """y -> (x, kind) for the members of a level that have a surrogate.

    ``results`` are the evaluated joins of this level (patterns of ``size``
    nodes), whose occurrences are at hand.
    """
    if rule not in RULES:
        raise ValueError(f"rule is one of {RULES}")
    if rule == "none":
        return {}
    taken = {p for p in pairs if shortcut(search, p)}
    open_ = [p for p in pairs if p not in taken and p.y not in {t.y for t in taken}]
    if open_:
        cousins: dict[int, list[Mined]] = defaultdict(list)  # y -> frequent cousin joins with followers at y's position
        for r in results:
            if r.kind == "cousin" and r.support >= search.options.minsup and search.mined[r.right].pattern.attach_pos == search.mined[r.left].pattern.attach_pos:
                cousins[r.left].append(r)
        order = {m.id: k for members in search.classes([search.mined[i] for i in {r.left for r in results} | {r.right for r in results}]).values() for k, m in enumerate(members)}
        followers = {p: [r for r in cousins[p.y] if order[r.right] >= order[p.y]] for p in open_}
        if rule == "filters":
            refuted = filters(search, size, results, open_, order)
            open_ = [p for p in open_ if p not in refuted]
        test = uniform if rule == "uniform" else definition
        taken |= test(search, size, open_, followers) if open_ else set()
    out: dict[int, tuple[int, str]] = {}
    for p in sorted(taken, key=lambda p: (p.y, p.kind, p.x)):
        out.setdefault(p.y, (p.x, p.kind))
    return out


def occurrences_of(search: Search, size: int, ids: DataFrame, names: tuple[str, str], id_name: str) -> DataFrame:
    """(number, tree, prefix, two last images with their ends) of joins; ``ids(number, pattern_id)``."""
    a, b = names
    wanted = sorted({r["pattern_id"] for r in ids.select("pattern_id").collect()})  # as many as there are pairs
    occ = search.occurrences(size, wanted).join(F.broadcast(ids), "pattern_id")
    return occ.select(
        *(c for c in ids.columns if c != "pattern_id"),
        "tree_id",
        F.slice("img", 1, size - 2).alias("pre"),
        F.col("img")[size - 2].alias(a),
        F.col("x_end").alias(f"{a}_end"),
        F.col("img")[size - 1].alias(b),
        F.col("y_end").alias(f"{b}_end"),
        "w",
    )


def tables(search: Search, size: int, pairs: list[Pair], followers: dict[Pair, list[Mined]]) -> tuple[DataFrame, DataFrame | None]:
    """(prefix, x, y) of the pairs and (prefix, y, z) of their followers, numbered by pair."""
    spark = search.spark
    xy = occurrences_of(search, size, spark.createDataFrame([(n, p.kind == "child", p.q) for n, p in enumerate(pairs)], "n int, child boolean, pattern_id long"), ("x", "y"), "n")
    rows = [(n, r.id, r.id) for n, p in enumerate(pairs) for r in followers[p]]
    if not rows:
        return xy, None
    yz = occurrences_of(search, size, spark.createDataFrame(rows, "n int, r long, pattern_id long"), ("y", "z"), "n")
    return xy, yz


KEY = ["n", "tree_id", "pre", "y"]


def below(node: str, top: str) -> F.Column:
    return (F.col(node) > F.col(top)) & (F.col(f"{node}_end") < F.col(f"{top}_end"))


def beside(a: str, b: str) -> F.Column:
    return (F.col(a) > F.col(f"{b}_end")) | (F.col(f"{a}_end") < F.col(b))


def uniform(search: Search, size: int, pairs: list[Pair], followers: dict[Pair, list[Mined]]) -> set[Pair]:
    xy, yz = tables(search, size, pairs, followers)
    if yz is None:
        return set(pairs)
    good = set()
    # child: the topmost or the lowest valid x; each follower is below it always or never
    chosen = xy.where("child").groupBy(KEY).agg(F.min(F.struct("x", "x_end")).alias("top"), F.max(F.struct("x", "x_end")).alias("low"))
    seen = yz.join(chosen, KEY)
    inside = lambda c: ((F.col("z") > F.col(f"{c}.x")) & (F.col("z_end") < F.col(f"{c}.x_end"))).cast("long")
    counts = seen.groupBy("n", "r").agg(F.count(F.lit(1)).alias("total"), F.sum(inside("top")).alias("top"), F.sum(inside("low")).alias("low")).collect()
    fails = {c: {r["n"] for r in counts if r[c] not in (0, r["total"])} for c in ("top", "low")}
    for n, p in enumerate(pairs):
        if p.kind == "child" and (n not in fails["top"] or n not in fails["low"]):
            good.add(p)
    # cousin: one x that is beside every follower
    cousin = xy.where("NOT child")
    clash = cousin.join(yz.select(*KEY, "z", "z_end"), KEY).where(~beside("x", "z")).select(*KEY, "x").distinct()
    left = cousin.join(clash, [*KEY, "x"], "left_anti").select(*KEY, "w").distinct().groupBy("n").agg(F.sum("w").alias("k")).collect()
    have = {r["n"]: r["k"] for r in left}
    good |= {p for n, p in enumerate(pairs) if p.kind == "cousin" and have.get(n, 0) == search.mined[p.y].n_occ}
    return good


def definition(search: Search, size: int, pairs: list[Pair], followers: dict[Pair, list[Mined]]) -> set[Pair]:
    xy, yz = tables(search, size, pairs, followers)
    if yz is None:
        return set(pairs)
    seen = yz.join(xy.select(*KEY, "x", "x_end"), KEY, "left")
    each = seen.groupBy(*KEY, "r", "z").agg(F.max(below("z", "x")).alias("above"), F.max(beside("z", "x")).alias("aside"))
    counts = each.groupBy("n", "r").agg(F.count(F.lit(1)).alias("total"), F.sum(F.coalesce("above", F.lit(False)).cast("long")).alias("above"), F.sum(F.coalesce("aside", F.lit(False)).cast("long")).alias("aside")).collect()
    bad = {r["n"] for r in counts if r["aside"] != r["total"] and (pairs[r["n"]].kind == "cousin" or r["above"] != r["total"])}
    return {p for n, p in enumerate(pairs) if n not in bad}


def filters(search: Search, size: int, results: list[Mined], pairs: list[Pair], order: dict[int, int]) -> set[Pair]:
    """Pairs refuted by the two necessary conditions.

    child: for a follower z with the same prefix images, the (prefix, x) images
    with y below must all have z below, or all have z beside.
    cousin: none of the (prefix, x) images with y beside may be on one path with z.
    """
    spark, by_join = search.spark, {(r.left, r.right, r.kind): r for r in results}
    asks, prefix_asks = [], []
    for n, p in enumerate(pairs):
        x, y = search.mined[p.x], search.mined[p.y]
        for z in search.mined.values():
            if z.prefix != y.prefix or z.id not in order or z.pattern.attach_pos != y.pattern.attach_pos:
                continue
            if order[z.id] < order[y.id] or (p.kind == "child" and z.id == y.id):
                continue
            for kind, left, right, side in (("child", x.id, z.id, 0), ("cousin", x.id, z.id, 0), ("child", z.id, x.id, 1)):
                r = by_join.get((left, right, kind))
                if p.kind == "child" and side == 0 or p.kind == "cousin" and kind == "child":
                    asks.append((n, z.id, p.q, r.id if r and r.n_occ else -1, kind, side))
            prefix_asks.append((n, z.id, y.id, z.id))
    if not asks:
        return set()
    found = search.occurrences(size, sorted({i for a in asks for i in a[2:4] if i >= 0}))
    px = found.select("pattern_id", "tree_id", F.slice("img", 1, size - 1).alias("px")).distinct()
    swapped = found.select("pattern_id", "tree_id", F.concat(F.slice("img", 1, size - 2), F.slice("img", size, 1)).alias("px")).distinct()
    table = F.broadcast(spark.createDataFrame(asks, "n int, z long, pattern_id long, other long, kind string, side int"))
    base = px.join(table, "pattern_id").drop("pattern_id")
    others = px.withColumn("side", F.lit(0)).union(swapped.withColumn("side", F.lit(1))).withColumnRenamed("pattern_id", "other")
    hit = base.join(others.withColumn("hit", F.lit(1)), ["other", "side", "tree_id", "px"], "left")
    counts = hit.groupBy("n", "z", "kind", "side").agg(F.count(F.lit(1)).alias("total"), F.sum(F.coalesce("hit", F.lit(0))).alias("hits")).collect()
    got = {(r["n"], r["z"], r["kind"], r["side"]): (r["total"], r["hits"]) for r in counts}
    same = same_prefix(search, size, [a for a in prefix_asks if pairs[a[0]].kind == "child"])
    out = set()
    for n, z, _, _, _, _ in asks:
        if pairs[n].kind == "child":
            if (n, z) in same and all(got.get((n, z, kind, 0), (1, 0))[0] != got.get((n, z, kind, 0), (1, 0))[1] for kind in ("child", "cousin")):
                out.add(pairs[n])
        elif any(got.get((n, z, "child", side), (0, 0))[1] for side in (0, 1)):
            out.add(pairs[n])
    return out


def same_prefix(search: Search, size: int, asks: list[tuple[int, int, int, int]]) -> set[tuple[int, int]]:
    """(n, z) for which P_y and P_z have the same images of their prefix."""
    if not asks:
        return set()
    ids = sorted({i for a in asks for i in a[2:]})
    own = search.occurrences(size - 1, ids).select("pattern_id", "tree_id", F.slice("img", 1, size - 2).alias("pre")).distinct()
    own = stage(own, "prefixes")
    counts = {r["pattern_id"]: r["n"] for r in own.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    table = F.broadcast(search.spark.createDataFrame(asks, "n int, z long, y_id long, z_id long"))
    both = own.join(table, F.col("pattern_id") == F.col("y_id")).select("n", "z", "y_id", "z_id", "tree_id", "pre").join(own.withColumnRenamed("pattern_id", "z_id"), ["z_id", "tree_id", "pre"])
    got = both.groupBy("n", "z", "y_id", "z_id").agg(F.count(F.lit(1)).alias("k")).collect()
    return {(r["n"], r["z"]) for r in got if r["k"] == counts[r["y_id"]] == counts[r["z_id"]]}
