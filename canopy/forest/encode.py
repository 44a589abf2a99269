"""Region encoding: parent links to ``nodes`` with (begin, end, level).

One counter numbers both visits of a node, so with preorder rank r (from 0 in
its tree) and level l, ``begin = 2 r - l`` and ``end = begin + 2 size - 1``.
``anc`` holds the begins of all proper ancestors, root first: an
ancestor-descendant join is then an explode and an equi-join.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from canopy.storage import stage

NODES = ["tree_id", "begin", "end", "level", "parent", "label", "anc"]


def encode_edges(edges: DataFrame, id: str = "id", parent: str = "parent", label: str = "label", order: str | None = None, tree: str | None = None, most_levels: int = 10_000) -> DataFrame:
    """Region codes of a forest given by parent links.

    ``edges(id, parent, label[, order][, tree])``: a null parent marks a root.
    ids are unique in the whole forest, or within ``tree`` if that is named;
    without it, a root's id is its tree_id. Siblings are numbered by
    ``(order, id)``. Rows that no root reaches (cycles, lost parents) are left
    out. One join per level; each level is written, so lineage stays short.
    """
    rows = edges.select(
        (F.col(tree) if tree else F.lit(None).cast("long")).cast("long").alias("t"),
        F.col(id).cast("long").alias("id"),
        F.col(parent).cast("long").alias("parent"),
        F.col(label).alias("label"),
        (F.col(order) if order else F.col(id)).cast("long").alias("o"),
    )
    step = F.struct(F.col("o"), F.col("id"))
    roots = rows.where("parent IS NULL").select((F.col("t") if tree else F.col("id")).alias("tree_id"), "t", "id", "parent", "label", F.array(step).alias("path"))
    levels = [stage(roots, "level")]
    below = stage(rows.where("parent IS NOT NULL"), "edges")
    while len(levels) <= most_levels:
        up = levels[-1].select("tree_id", F.col("t").alias("ut"), F.col("id").alias("up"), F.col("path").alias("above"))
        on = below["parent"] == up["up"]
        on = on & (below["t"] == up["ut"]) if tree else on
        level = stage(below.join(up, on).select("tree_id", "t", "id", "parent", "label", F.concat("above", F.array(step)).alias("path")), "level")
        if level.isEmpty():
            break
        levels.append(level)
    everything = levels[0]
    for level in levels[1:]:
        everything = everything.union(level)
    return number(everything.select("tree_id", "label", "path"))


def preorder(rows: DataFrame, keys: list[str], group: str = "tree_id") -> DataFrame:
    """Adds ``rank``: the row's place in its group (a tree), in the order of ``keys``, from 0.

    A distributed rank: rows are range-partitioned by the keys, sorted and
    numbered where they lie; the number of rows in the partitions before is
    added. One shuffle, and no window, however large a group.
    """
    spark = rows.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartitionByRange(parts, group, *keys).sortWithinPartitions(group, *keys)
    # the number holds the partition above bit 33 and the place in it below
    local = stage(dealt.withColumn("at", F.monotonically_increasing_id()), "ranked")
    part = F.shiftright("at", 33).cast("int")
    counts = {r["part"]: r["n"] for r in local.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n")).collect()}  # one number for each partition
    total, offsets = 0, []
    for k in range(max(counts, default=-1) + 1):
        offsets.append(total)
        total += counts.get(k, 0)
    base = F.element_at(F.array(*map(F.lit, offsets)), part + 1) if offsets else F.lit(0)
    numbered = local.withColumn("place", (F.col("at").bitwiseAND(F.lit((1 << 33) - 1)) + base).cast("long"))
    first = numbered.groupBy(group).agg(F.min("place").alias("first"))
    return numbered.join(first, group).withColumn("rank", F.col("place") - F.col("first")).drop("at", "place", "first")


def number(paths: DataFrame) -> DataFrame:
    """``nodes`` from ``(tree_id, label, path)``; a path is the array of (order, id) from its root."""
    ranked = preorder(paths.withColumn("level", F.size("path") - 1), ["path"])
    coded = stage(ranked.select("tree_id", "label", F.col("path.id").alias("ids"), "level", (2 * F.col("rank") - F.col("level")).alias("begin")), "coded")
    above = coded.where("level > 0").select("tree_id", "begin", F.explode(F.slice("ids", 1, F.col("level"))).alias("id"))
    holders = coded.select("tree_id", F.element_at("ids", -1).alias("id"), F.col("begin").alias("a"))
    pairs = stage(above.join(holders, ["tree_id", "id"]).select("tree_id", "begin", "a"), "pairs")
    sizes = pairs.groupBy("tree_id", F.col("a").alias("begin")).agg(F.count(F.lit(1)).alias("below"))
    ancestors = pairs.groupBy("tree_id", "begin").agg(F.array_sort(F.collect_list("a")).alias("anc"))
    return finish(coded.join(sizes, ["tree_id", "begin"], "left").join(ancestors, ["tree_id", "begin"], "left").withColumn("anc", F.coalesce("anc", F.array().cast("array<bigint>"))))


def finish(coded: DataFrame) -> DataFrame:
    """Columns of ``nodes`` from ``begin``, ``level``, ``below`` (nodes below) and ``anc``."""
    return coded.select(
        "tree_id",
        "begin",
        (F.col("begin") + 2 * F.coalesce("below", F.lit(0)) + 1).alias("end"),
        F.col("level").cast("int").alias("level"),
        F.try_element_at("anc", F.lit(-1)).alias("parent"),
        "label",
        "anc",
    )


def encode_levels(levels: list[tuple[DataFrame, list[str], Column]], keys: list[str], tree: str) -> DataFrame:
    """Region codes of nests whose depth is fixed by key columns, without iteration over the data.

    ``levels`` lists (rows, key columns that identify them, label). A row lies
    below the row of an earlier entry whose keys are a proper prefix of its own
    (in the order of ``keys``); the longest such entry is its parent. Keys are
    integers from 0; the sibling order is that of the keys. ``tree`` is the key
    that names the tree; it must be the first.
    """
    rows = None
    for df, own, label in levels:
        part = df.select(*(F.col(k).cast("long").alias(k) if k in own else F.lit(-1).cast("long").alias(k) for k in keys), label.alias("label"))
        part = part.withColumn("tree_id", F.col(tree))
        rows = part if rows is None else rows.unionByName(part)
    kinds = [own for _, own, _ in levels]
    above = [max((k for k in kinds if len(k) < len(own) and set(k) < set(own)), key=len, default=None) for own in kinds]
    depth = [0] * len(kinds)
    for n, up in enumerate(above):
        depth[n] = depth[kinds.index(up)] + 1 if up is not None else 0

    def is_kind(own: list[str]) -> Column:
        out = F.lit(True)
        for k in keys:
            out = out & ((F.col(k) >= 0) if k in own else (F.col(k) == -1))
        return out

    level = F.coalesce(*(F.when(is_kind(own), F.lit(d)) for own, d in zip(kinds, depth)))
    coded = preorder(rows.withColumn("level", level), keys)
    coded = stage(coded.withColumn("begin", 2 * F.col("rank") - F.col("level")), "coded")
    # top down: each kind takes its parent's ancestors, by an equi-join on the parent's keys
    done: dict[int, DataFrame] = {}
    for n in sorted(range(len(kinds)), key=lambda n: depth[n]):
        own, up = kinds[n], above[n]
        part = coded.where(is_kind(own))
        if up is None:
            done[n] = part.withColumn("anc", F.array().cast("array<bigint>"))
            continue
        holder = done[kinds.index(up)].select(*(F.col(k).alias(f"up_{k}") for k in up), F.concat("anc", F.array("begin")).alias("anc"))
        on = [part[k] == holder[f"up_{k}"] for k in up]
        done[n] = part.join(holder, on).select(*keys, "label", "tree_id", "level", "begin", "anc")
        if any(a == own for a in above):
            done[n] = stage(done[n], "kind")
    out = None
    for n in done:
        part = done[n].select("tree_id", "begin", "level", "label", "anc")
        out = part if out is None else out.unionByName(part)
    out = stage(out, "nested")
    below = out.select("tree_id", F.explode("anc").alias("begin")).groupBy("tree_id", "begin").agg(F.count(F.lit(1)).alias("below"))
    return finish(out.join(below, ["tree_id", "begin"], "left"))


def glue(nodes: DataFrame) -> DataFrame:
    """The forest as one tree, tree_id 0, under a virtual root that is not stored.

    Trees follow each other in the order of tree_id; levels grow by one. If trees have weights, their nodes keep them:
    a node stands for so many, and all nodes below it do.
    """
    sizes = stage(nodes.groupBy("tree_id").agg(F.count(F.lit(1)).alias("n")), "sizes")
    parts = preorder(sizes.select(F.lit(0).alias("tree_id"), F.col("tree_id").alias("t"), "n"), ["t"]).select("t", "n", "rank")
    # the offset is a running sum; partial sums of blocks of ranks keep its window short
    block = F.floor(F.col("rank") / 4096)
    blocks = parts.groupBy(block.alias("b")).agg(F.sum("n").alias("bn"))
    before = blocks.select("b", (F.sum("bn").over(Window.orderBy("b")) - F.col("bn")).alias("base"))
    own = F.sum("n").over(Window.partitionBy("b").orderBy("rank")) - F.col("n")
    offset = parts.withColumn("b", block).withColumn("own", own).join(before, "b").select("t", (2 * (F.col("base") + F.col("own")) + 1).cast("long").alias("shift"))
    moved = nodes.join(offset, nodes["tree_id"] == offset["t"])
    return moved.select(
        F.lit(0).cast("long").alias("tree_id"),
        (F.col("begin") + F.col("shift")).alias("begin"),
        (F.col("end") + F.col("shift")).alias("end"),
        (F.col("level") + 1).cast("int").alias("level"),
        (F.col("parent") + F.col("shift")).alias("parent"),
        "label",
        F.transform("anc", lambda a: a + F.col("shift")).alias("anc"),
        *(["w"] if "w" in nodes.columns else []),
    )


def split(nodes: DataFrame, level: int = 1) -> DataFrame:
    """The subtrees rooted at ``level`` as trees of their own; nodes above are dropped.

    A new tree_id is the begin of the old root. Input is one tree.
    """
    deep = nodes.where(F.col("level") >= level)
    root = F.when(F.col("level") == level, F.col("begin")).otherwise(F.element_at("anc", F.lit(1) + F.size("anc") - (F.col("level") - level)))
    cut = deep.withColumn("root", root)
    return cut.select(
        F.col("root").alias("tree_id"),
        (F.col("begin") - F.col("root")).alias("begin"),
        (F.col("end") - F.col("root")).alias("end"),
        (F.col("level") - level).cast("int").alias("level"),
        F.when(F.col("level") > level, F.col("parent") - F.col("root")).alias("parent"),
        "label",
        F.transform(F.slice("anc", F.size("anc") - (F.col("level") - level) + 1, F.col("level") - level), lambda a: a - F.col("root")).alias("anc"),
    )


def from_patterns(spark, trees: list, first_id: int = 0) -> DataFrame:
    """``nodes`` of small trees held as patterns, for worked examples."""
    rows = []
    for t, p in enumerate(trees, first_id):
        size = [1 + sum(n in a for a in p.ancestors) for n in range(p.size)]
        begin = [2 * n - len(p.ancestors[n]) for n in range(p.size)]
        for n in range(p.size):
            anc = [begin[a] for a in sorted(p.ancestors[n])]
            rows.append((t, begin[n], begin[n] + 2 * size[n] - 1, len(anc), anc[-1] if anc else None, p.labels[n], anc))
    return spark.createDataFrame(rows, "tree_id long, begin long, end long, level int, parent long, label string, anc array<long>")
