"""Trees out of the given tables: nests, event logs, dialogues, pages and texts."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from canopy.arrow import arrow_map
from canopy.forest.encode import encode_edges, encode_levels
from canopy.functions.labels import cat_label, json_label, text_len_label, width_label
from canopy.storage import stage

STAGES = ["view", "click", "signup", "purchase", "error"]
WEEK = 7 * 24 * 3600
#: Monday; windows of whole weeks start here.
EPOCH = 4 * 24 * 3600
# fixed values: elements without content
VOID = "area base br col embed hr img input link meta param source track wbr".split()
TAG = re.compile(r"<(/?)([a-zA-Z][a-zA-Z0-9]*)([^>]*)>")
#: Kinds of lines that ``order_trees`` counts in columns; with more, it gathers them.
MOST_KINDS, LINES = 64, "array<struct<flag:string,ls:string>>"
CLASS = re.compile(r"""\bclass\s*=\s*["']?([^"'\s>]+)""")


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def star(spark: SparkSession, folder: str, tenths: int = 10) -> DataFrame:
    """region > nation > customer > order > line, with attribute leaves; a tree is a region.

    ``tenths`` keeps so many tenths of the customers, for a forest that grows.
    """
    region = table(spark, folder, "region").select(F.col("r_regionkey").alias("r"))
    nation = table(spark, folder, "nation").select(F.col("n_regionkey").alias("r"), F.col("n_nationkey").alias("n"))
    customer = table(spark, folder, "customer").where(F.lit(tenths == 10) | (F.col("c_custkey") % 10 < tenths)).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n")).select("r", "n", F.col("c_custkey").alias("c"), "c_mktsegment")
    orders = table(spark, folder, "orders").join(customer, F.col("o_custkey") == F.col("c")).select("r", "n", "c", F.col("o_orderkey").alias("o"), "o_orderstatus", "o_orderpriority")
    place = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice"))
    line = table(spark, folder, "lineitem").withColumn("l", place).join(orders.select("r", "n", "c", "o"), F.col("l_orderkey") == F.col("o"))
    line = line.select("r", "n", "c", "o", "l", "l_returnflag", "l_linestatus")
    leaf = lambda df, k, label: (df.withColumn("a", F.lit(k)), label)
    c, o, ln = ["r", "n", "c"], ["r", "n", "c", "o"], ["r", "n", "c", "o", "l"]
    levels = [
        (region, ["r"], F.lit("region")),
        (nation, ["r", "n"], F.lit("nation")),
        (customer, c, F.lit("customer")),
        (orders, o, F.lit("order")),
        (line, ln, F.lit("line")),
    ]
    leaves = [(c, customer, [cat_label("c_mktsegment", "seg")]), (o, orders, [cat_label("o_orderstatus", "status"), cat_label("o_orderpriority", "prio")]), (ln, line, [cat_label("l_returnflag", "flag"), cat_label("l_linestatus", "ls")])]
    for own, df, labels in leaves:
        both = None
        for k, label in enumerate(labels):
            part = df.select(*own, F.lit(k).alias("a"), label.alias("label"))
            both = part if both is None else both.union(part)
        levels.append((both, [*own, "a"], F.col("label")))
    return encode_levels(levels, ["r", "n", "c", "o", "l", "a"], "r")


def order_shapes(spark: SparkSession, folder: str, *more: Column) -> DataFrame:
    """``(status, prio, every, *more, w)``: the distinct orders, the kinds of their lines, and how many orders are so.

    Orders are compared by how many lines of each kind they have, before any node is made, so what is
    shuffled are orders with counts, not nodes. ``more`` are columns of the orders that keep them apart.
    """
    customer = table(spark, folder, "customer").join(F.broadcast(table(spark, folder, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey")
    orders = table(spark, folder, "orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").alias("l_orderkey"), cat_label("o_orderstatus", "status").alias("status"), cat_label("o_orderpriority", "prio").alias("prio"), *more)
    own = [c for c in orders.columns if c != "l_orderkey"]
    item = table(spark, folder, "lineitem")
    kinds = sorted(item.select("l_returnflag", "l_linestatus").distinct().limit(MOST_KINDS + 1).collect(), key=lambda r: tuple((v is not None, v or "") for v in r))
    named = F.struct(cat_label("l_returnflag", "flag").alias("flag"), cat_label("l_linestatus", "ls").alias("ls"))
    if len(kinds) <= MOST_KINDS:  # a count for each kind of line
        same = [F.col("l_returnflag").eqNullSafe(F.lit(x)) & F.col("l_linestatus").eqNullSafe(F.lit(y)) for x, y in kinds]
        lines = item.groupBy("l_orderkey").agg(*(F.count_if(c).alias(f"n{k}") for k, c in enumerate(same)))
        counts = [f"n{k}" for k in range(len(kinds))]
        shapes = orders.join(lines, "l_orderkey", "left").groupBy(*own, *counts).agg(F.count(F.lit(1)).alias("w"))
        label = lambda name, v: F.lit(None if v is None else f"{name}={v}").cast("string")
        one = [F.array_repeat(F.struct(label("flag", x).alias("flag"), label("ls", y).alias("ls")), F.coalesce(n, F.lit(0)).cast("int")) for n, (x, y) in zip(counts, kinds)]
        return shapes.select(*own, F.concat(*one).alias("every") if one else F.array().cast(LINES).alias("every"), "w")
    lines = item.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(named)).alias("every"))
    return orders.join(lines, "l_orderkey", "left").groupBy(*own, F.coalesce("every", F.array().cast(LINES)).alias("every")).agg(F.count(F.lit(1)).alias("w"))


def order_trees(spark: SparkSession, folder: str) -> DataFrame:
    """The subtrees of ``star`` below its orders, equal ones once; ``w`` is how many orders a tree stands for."""
    return shape_trees(order_shapes(spark, folder))


def shape_trees(shapes: DataFrame) -> DataFrame:
    """Weighted trees of ``(status, prio, every, w)``; further columns, like weights of other forests, stay."""
    weights = [c for c in shapes.columns if c not in ("status", "prio", "every")]
    shapes = stage(shapes.select(F.monotonically_increasing_id().alias("tree_id"), "*"), "shapes")

    def node(begin: Column, size: Column | int, level: int, parent: Column, label: Column, anc: list) -> Column:
        made = [c.cast("bigint") for c in anc]
        return F.struct(begin.cast("bigint").alias("begin"), (begin + 2 * size - 1).cast("bigint").alias("end"), F.lit(level).alias("level"), parent.cast("bigint").alias("parent"), label.alias("label"), F.array(*made).cast("array<bigint>").alias("anc"))

    top = F.lit(0)

    def line(x: Column, k: Column) -> Column:
        at = 5 + 6 * k
        return F.array(node(at, 3, 1, top, F.lit("line"), [top]), node(at + 1, 1, 2, at, x["flag"], [top, at]), node(at + 3, 1, 2, at, x["ls"], [top, at]))

    own = F.array(node(top, 3 + 3 * F.size("every"), 0, F.lit(None), F.lit("order"), []), node(F.lit(1), 1, 1, top, F.col("status"), [top]), node(F.lit(3), 1, 1, top, F.col("prio"), [top]))
    rows = shapes.select("tree_id", *weights, F.inline(F.concat(own, F.flatten(F.transform("every", line)))))
    return rows.select("tree_id", "begin", "end", "level", "parent", "label", "anc", *weights)


def above_orders(spark: SparkSession, folder: str, steps: Iterable[int] = (10,)) -> dict[int, int]:
    """How many nodes of ``star`` stand above its orders or beside them, for each ``tenths``: regions, nations, customers and their leaves."""
    nation = table(spark, folder, "nation").select("n_nationkey")
    customer = table(spark, folder, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    counts = customer.agg(*(F.count_if(F.lit(t == 10) | (F.col("c_custkey") % 10 < t)).alias(str(t)) for t in steps)).first()
    top = table(spark, folder, "region").count() + nation.count()
    return {t: top + 2 * counts[str(t)] for t in steps}


def line_paths(spark: SparkSession, folder: str) -> DataFrame:
    """order(line(flag, ls), prio, status) of every line; the shape is fixed, so the codes are.

    Equal paths are one tree; ``w`` is how many lines it stands for.
    """
    orders = table(spark, folder, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderstatus", "o_orderpriority")
    rows = table(spark, folder, "lineitem").join(orders, "l_orderkey").groupBy("l_returnflag", "l_linestatus", "o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("w"))
    rows = stage(rows.select(F.monotonically_increasing_id().alias("tree_id"), "*"), "shapes")
    shape = [
        (0, 11, 0, None, F.lit("order"), []),
        (1, 6, 1, 0, F.lit("line"), [0]),
        (2, 3, 2, 1, cat_label("l_returnflag", "flag"), [0, 1]),
        (4, 5, 2, 1, cat_label("l_linestatus", "ls"), [0, 1]),
        (7, 8, 1, 0, cat_label("o_orderpriority", "prio"), [0]),
        (9, 10, 1, 0, cat_label("o_orderstatus", "status"), [0]),
    ]
    nodes = [
        F.struct(
            F.lit(b).cast("long").alias("begin"), F.lit(e).cast("long").alias("end"), F.lit(lv).alias("level"), F.lit(up).cast("long").alias("parent"), label.alias("label"),
            F.array(*(F.lit(a) for a in anc)).cast("array<bigint>").alias("anc"),
        )
        for b, e, lv, up, label, anc in shape
    ]
    return rows.select("tree_id", F.inline(F.array(*nodes)), "w")


def supply(spark: SparkSession, folder: str) -> DataFrame:
    """nation > supplier > part (of its lines), with brand, type and size leaves; a tree is a nation."""
    supplier = table(spark, folder, "supplier").select(F.col("s_nationkey").alias("n"), F.col("s_suppkey").alias("s"))
    nation = table(spark, folder, "nation").select(F.col("n_nationkey").alias("n"))
    sold = table(spark, folder, "lineitem").select(F.col("l_suppkey").alias("s"), F.col("l_partkey").alias("p")).distinct()
    part = sold.join(supplier, "s").join(table(spark, folder, "part"), F.col("p") == F.col("p_partkey")).select("n", "s", "p", "p_brand", "p_type", "p_size")
    labels = [cat_label("p_brand", "brand"), cat_label("p_type", "type"), width_label("p_size", 1, 51, 5, "size")]
    leaves = None
    for k, label in enumerate(labels):
        rows = part.select("n", "s", "p", F.lit(k).alias("a"), label.alias("label"))
        leaves = rows if leaves is None else leaves.union(rows)
    levels = [(nation, ["n"], F.lit("nation")), (supplier, ["n", "s"], F.lit("supplier")), (part, ["n", "s", "p"], F.lit("part")), (leaves, ["n", "s", "p", "a"], F.col("label"))]
    return encode_levels(levels, ["n", "s", "p", "a"], "n")


def micros(column: str) -> Column:
    """Microseconds since 1970 of a timestamp's own clock time, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast({column} AS timestamp_ntz))")


def stage_rank(event_type: Column) -> Column:
    return F.coalesce(*(F.when(event_type == s, F.lit(k)) for k, s in enumerate(STAGES)), F.lit(len(STAGES)))


def navigation_edges(spark: SparkSession, folder: str, label: str = "type", sessions: str = "week", gap: str = "12 hours") -> DataFrame:
    """``(tree, id, parent, label, o)`` of visits: a user's events of one week (or gap session).

    An event's parent is the latest earlier event of the visit whose type has
    a smaller stage rank, else the visit's root. A visit is small, so its
    windows are.
    """
    e = table(spark, folder, "events").where("event_type IS NOT NULL AND ts IS NOT NULL AND user_id IS NOT NULL")
    name = F.col("event_type") if label == "type" else F.concat_ws(":", "event_type", json_label("props", "$.k"))
    e = e.select("user_id", "event_id", micros("ts").alias("t"), stage_rank(F.col("event_type")).alias("s"), name.alias("label"))
    if sessions == "week":
        e = e.withColumn("visit", F.floor((F.col("t") / 1_000_000 - EPOCH) / WEEK))
    else:
        by_user = Window.partitionBy("user_id").orderBy("t", "event_id")
        limit = int(gap.split()[0]) * {"hours": 3600, "minutes": 60}[gap.split()[1]] * 1_000_000
        cut = F.when(F.col("t") - F.lag("t").over(by_user) > limit, 1).otherwise(0)
        e = e.withColumn("cut", cut).withColumn("visit", F.sum("cut").over(by_user)).drop("cut")
    e = e.withColumn("tree", F.col("user_id") * 100_000 + F.col("visit"))
    before = Window.partitionBy("tree").orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    latest = [F.last(F.when(F.col("s") < k, F.struct("t", "event_id")), ignorenulls=True).over(before) for k in range(1, len(STAGES) + 1)]
    e = e.withColumn("up", F.element_at(F.array(F.lit(None).cast("struct<t:bigint,event_id:bigint>"), *latest), F.col("s") + 1))
    inner = e.select("tree", F.col("event_id").alias("id"), F.coalesce("up.event_id", F.lit(-1)).alias("parent"), "label", F.col("t").alias("o"))
    roots = e.select("tree").distinct().select("tree", F.lit(-1).cast("long").alias("id"), F.lit(None).cast("long").alias("parent"), F.lit("visit").alias("label"), F.lit(0).cast("long").alias("o"))
    return inner.unionByName(roots)


def navigation(spark: SparkSession, folder: str, label: str = "type", sessions: str = "week", gap: str = "12 hours", keep: int = 100) -> DataFrame:
    """Visits as trees; ``keep`` percent of them, by a hash of the tree."""
    edges = navigation_edges(spark, folder, label, sessions, gap)
    if keep < 100:
        edges = edges.where(F.conv(F.substring(F.md5(F.col("tree").cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % 100 < keep)
    return encode_edges(edges, order="o", tree="tree")


def dialogue(spark: SparkSession, folder: str) -> DataFrame:
    """conversation > turn > next turn ..., each turn with a text-length leaf."""
    t = table(spark, folder, "conversations").where("conv_id IS NOT NULL AND turn IS NOT NULL")
    by_conv = Window.partitionBy("conv_id").orderBy("turn", "role", F.coalesce("text", F.lit("")))
    t = t.select(F.col("conv_id").alias("tree"), F.row_number().over(by_conv).alias("k"), "role", "text")
    turns = t.select("tree", (2 * F.col("k")).alias("id"), F.when(F.col("k") > 1, 2 * F.col("k") - 2).otherwise(F.lit(0)).alias("parent"), F.coalesce("role", F.lit("none")).alias("label"))
    leaves = t.select("tree", (2 * F.col("k") + 1).alias("id"), (2 * F.col("k")).alias("parent"), text_len_label("text").alias("label"))
    roots = t.select("tree").distinct().select("tree", F.lit(0).alias("id"), F.lit(None).cast("int").alias("parent"), F.lit("conv").alias("label"))
    return encode_edges(turns.unionByName(leaves).unionByName(roots), tree="tree")


def text(spark: SparkSession, folder: str) -> DataFrame:
    """doc > line > sentence bucket; leaves lang, quality and toxic of the doc."""
    docs = table(spark, folder, "documents").where("doc_id IS NOT NULL")
    labels = table(spark, folder, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    lines = docs.select(F.col("doc_id").alias("tree"), F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("k", "line"))
    row = F.col("k") * 10_000 + 100
    line_nodes = lines.select("tree", row.alias("id"), F.lit(0).alias("parent"), F.lit("line").alias("label"))
    sentences = lines.select("tree", row.alias("up"), F.posexplode(F.filter(F.split("line", r"(?<=\.)\s+"), lambda s: F.length(s) > 0)).alias("j", "s"))
    sentences = sentences.select("tree", (F.col("up") + F.col("j") + 1).alias("id"), F.col("up").alias("parent"), F.concat(F.lit("s:"), text_len_label("s")).alias("label"))
    tagged = docs.join(labels, "doc_id", "left").select(F.col("doc_id").alias("tree"), F.explode(F.array(cat_label("lang", "lang"), cat_label("quality", "quality"), cat_label("toxic", "toxic"))).alias("label"))
    tags = tagged.where("label IS NOT NULL").select("tree", F.dense_rank().over(Window.partitionBy("tree").orderBy("label")).alias("id"), F.lit(0).alias("parent"), "label")
    roots = docs.select(F.col("doc_id").alias("tree"), F.lit(0).alias("id"), F.lit(None).cast("int").alias("parent"), F.lit("doc").alias("label")).distinct()
    return encode_edges(line_nodes.unionByName(sentences).unionByName(tags).unionByName(roots), tree="tree")


def fold(html: str, classes: bool = False) -> list[tuple[int, str]]:
    """(parent, label) of each element, in order of its start tag; parent -1 above the roots.

    Void elements are leaves. An end tag closes back to its match; one without
    a match is ignored. What stays open ends with the page.
    """
    out: list[tuple[int, str]] = []
    open_: list[int] = []
    names: list[str] = []
    for end, name, rest in TAG.findall(html):
        name = name.lower()
        if end:
            for k in range(len(open_) - 1, -1, -1):
                if names[open_[k]] == name:
                    del open_[k:]
                    break
            continue
        found = CLASS.search(rest) if classes else None
        out.append((open_[-1] if open_ else -1, f"{name}.{found[1]}" if found else name))
        names.append(name)
        if name not in VOID and not rest.endswith("/"):
            open_.append(len(out) - 1)
    return out


def coded(elements: list[tuple[int, str]]) -> list[tuple]:
    """(begin, end, level, parent, label, anc) of a forest in preorder, below a virtual root if it has several roots."""
    level, anc, size = [], [], [1] * len(elements)
    for up, _ in elements:
        level.append(level[up] + 1 if up >= 0 else 0)
    for n in range(len(elements) - 1, -1, -1):
        if elements[n][0] >= 0:
            size[elements[n][0]] += size[n]
    begin = [2 * n - lv for n, lv in enumerate(level)]
    for n, (up, _) in enumerate(elements):
        anc.append([*anc[up], begin[up]] if up >= 0 else [])
    return [(begin[n], begin[n] + 2 * size[n] - 1, level[n], begin[up] if up >= 0 else None, label, anc[n]) for n, (up, label) in enumerate(elements)]


def dom(spark: SparkSession, folder: str, classes: bool = False, labels: list[str] | None = None, dedupe_siblings: bool = False) -> DataFrame:
    """Element trees of pages; a page is folded in one pass over its tags.

    ``labels`` keeps these elements only (others pass their children up);
    ``dedupe_siblings`` keeps one of equal leaves side by side.
    """

    def make():
        def step(ids: list, pages: list) -> Iterator[tuple]:
            for page, html in zip(ids, pages):
                elements = fold(html or "", classes)
                if labels is not None:
                    elements = only(elements, set(labels))
                if dedupe_siblings:
                    elements = without_repeats(elements)
                for row in coded(elements):
                    yield (page, *row)

        return step

    pages = table(spark, folder, "pages").where("page_id IS NOT NULL").select("page_id", "html")
    return arrow_map(pages, make, "tree_id long, begin long, end long, level int, parent long, label string, anc array<long>")


def page_trees(spark: SparkSession, folder: str) -> DataFrame:
    """The trees of ``dom``, equal ones once; ``w`` is how many pages a tree stands for.

    Pages are compared by their elements; regions and ancestors are made for the distinct ones only.
    """

    def make():
        def step(pages: list) -> Iterator[tuple]:
            for elements, n in Counter(tuple(fold(html or "")) for html in pages).items():
                if elements:
                    ups, labels = zip(*elements)
                    yield ups, labels, n

        return step

    def make_nodes():
        def step(ids: list, ups: list, labels: list, counts: list) -> Iterator[tuple]:
            for tree, up, label, w in zip(ids, ups, labels, counts):
                for row in coded(list(zip(up, label))):
                    yield (tree, *row, w)

        return step

    pages = table(spark, folder, "pages").where("page_id IS NOT NULL").select("html")
    found = arrow_map(pages, make, "ups array<int>, labels array<string>, n long").groupBy("ups", "labels").agg(F.sum("n").alias("w"))
    shapes = stage(found.select(F.monotonically_increasing_id().alias("tree_id"), "ups", "labels", "w"), "shapes")
    return arrow_map(shapes, make_nodes, "tree_id long, begin long, end long, level int, parent long, label string, anc array<long>, w long")


def text_trees(spark: SparkSession, folder: str, required: set[str] = frozenset()) -> DataFrame:
    """The trees of ``text`` with lines and sentences in the order of their labels, equal ones once.

    ``w`` is how many documents a tree stands for. Only labels are shuffled, not texts or nodes.
    ``required`` are leaves of the document that a tree must have to be made, for patterns that hold them.
    """
    docs = table(spark, folder, "documents").where("doc_id IS NOT NULL")
    labels = table(spark, folder, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    kept = F.filter(F.array(cat_label("lang", "lang"), cat_label("quality", "quality"), cat_label("toxic", "toxic")), lambda x: x.isNotNull())
    buckets = lambda line: F.array_sort(F.transform(F.filter(F.split(line, r"(?<=\.)\s+"), lambda s: F.length(s) > 0), lambda s: F.concat(F.lit("s:"), text_len_label(s))))
    lines = F.array_sort(F.transform(F.split(F.coalesce("text", F.lit("")), "\n"), buckets))
    found = docs.select("doc_id", "lang", lines.alias("every")).join(labels, "doc_id", "left").groupBy(F.array_sort(kept).alias("tags"), "every").agg(F.count(F.lit(1)).alias("w"))
    for x in sorted(required):
        found = found.where(F.array_contains("tags", x))
    shapes = stage(found.select(F.monotonically_increasing_id().alias("tree_id"), "*"), "shapes")

    def make():
        def step(ids: list, tags: list, every: list, counts: list) -> Iterator[tuple]:
            for tree, own, doc, w in zip(ids, tags, every, counts):
                elements = [(-1, "doc"), *((0, x) for x in own)]
                for line in doc:
                    elements.append((0, "line"))
                    at = len(elements) - 1
                    elements += [(at, x) for x in line]
                for row in coded(elements):
                    yield (tree, *row, w)

        return step

    return arrow_map(shapes.select("tree_id", "tags", "every", "w"), make, "tree_id long, begin long, end long, level int, parent long, label string, anc array<long>, w long")


def only(elements: list[tuple[int, str]], labels: set[str]) -> list[tuple[int, str]]:
    out, place = [], []
    for up, label in elements:
        above = place[up] if up >= 0 else -1
        if label in labels:
            out.append((above, label))
            place.append(len(out) - 1)
        else:
            place.append(above)
    return out


def without_repeats(elements: list[tuple[int, str]]) -> list[tuple[int, str]]:
    has_child = {up for up, _ in elements}
    out, place, seen = [], {}, set()
    for n, (up, label) in enumerate(elements):
        if n not in has_child and (up, label) in seen:
            continue
        if n not in has_child:
            seen.add((up, label))
        place[n] = len(out)
        out.append((place[up] if up >= 0 else -1, label))
    return out
