"""Queries of the miners, measures and operators over the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from canopy import oracles as O
from canopy.forest import encode, lists, navigate, sources, stats
from canopy.forest.sources import STAGES, WEEK
from canopy.functions import patterns as pf
from canopy.functions import region
from canopy.match import occlist, sibling, structural, twig
from canopy.mine import closed, miners, result, surrogate
from canopy.mine.induced import mine_induced
from canopy.mine.lists import mine_lists
from canopy.mine.onestep import mine_onestep
from canopy.mine.scopejoin import mine_occurrence_join
from canopy.pattern.codec import parse, show
from canopy.pattern.expand import expand_class
from canopy.storage import kept, stage
from canopy.stream import sessions

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

STAR_ROOTS = ("order", "line")
CODE = ["tree_id", "begin", "end", "level", "parent", "label"]
NODE_SQL = 'tree_id, "begin", "end", level, parent, label'


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def star(spark: SparkSession, d: str) -> DataFrame:
    """The encoded star hierarchy, a preprocessing step that queries share."""
    tables = [f"{d}/{t}.parquet" for t in ("region", "nation", "customer", "orders", "lineitem")]
    return kept(spark, "star", tables, lambda: sources.star(spark, d))


def order_trees(spark: SparkSession, d: str, minsup: int) -> DataFrame:
    """The star's subtrees below orders, if nothing above an order is frequent; else the star.

    A pattern's support is at most its root label's count, so trees cut at the orders then hold all frequent patterns.
    """
    if max(spark.read.parquet(f"{d}/{t}.parquet").count() for t in ("region", "nation", "customer")) >= minsup:
        return star(spark, d)
    tables = [f"{d}/{t}.parquet" for t in ("nation", "customer", "orders", "lineitem")]
    return kept(spark, "order_trees", tables, lambda: sources.order_trees(spark, d))


def order_minsup(spark: SparkSession, d: str, percent: int) -> int:
    """A share of the orders, rounded up."""
    return -(-spark.read.parquet(f"{d}/orders.parquet").count() * percent // 100)


# encodings and statistics


@query("encode_star", f"WITH {O.star()} SELECT {NODE_SQL} FROM nodes")
def encode_star(spark, d):
    return sources.star(spark, d).select(CODE)


@query("encode_dialogue", f"WITH {O.dialogue()} SELECT {NODE_SQL} FROM nodes")
def encode_dialogue(spark, d):
    return sources.dialogue(spark, d).select(CODE)


NAV = (STAGES, WEEK, sources.EPOCH)
NAV_EDGES = O.navigation_edges(*NAV)


@query("nav_edges", f"WITH {NAV_EDGES} SELECT tree, id, parent, label, o FROM edges")
def nav_edges(spark, d):
    return sources.navigation_edges(spark, d)


@query(
    "session_trees",
    f"""WITH {NAV_EDGES} SELECT tree AS tree_id, count(*) AS n_nodes, count(*) FILTER (label = 'view') AS n_view, count(*) FILTER (parent = -1) AS n_top FROM edges GROUP BY tree""",
)
def session_trees(spark, d):
    nodes = sources.navigation(spark, d)
    return nodes.groupBy("tree_id").agg(F.count(F.lit(1)).alias("n_nodes"), F.count_if(F.col("label") == "view").alias("n_view"), F.count_if(F.col("parent") == 0).alias("n_top"))




def encoded(edges: str) -> str:
    return f"WITH RECURSIVE {edges}, {O.encoded()}"


NAV_SQL, TEXT_SQL, DOM_SQL = map(encoded, (NAV_EDGES, O.text_edges(), O.dom_edges(sources.VOID)))


@query("encode_nav", f"{NAV_SQL} SELECT {NODE_SQL} FROM nodes")
def encode_nav(spark, d):
    return sources.navigation(spark, d).select(CODE)


@query("encode_nav_gap_sessions", f"{encoded(O.navigation_edges(*NAV, gap_s=12 * 3600))} SELECT {NODE_SQL} FROM nodes")
def encode_nav_gap(spark, d):
    return sources.navigation(spark, d, sessions="gap", gap="12 hours").select(CODE)


@query("encode_supply", f"WITH {O.supply()} SELECT {NODE_SQL} FROM nodes")
def encode_supply(spark, d):
    return sources.supply(spark, d).select(CODE)


@query("encode_text", f"{TEXT_SQL} SELECT {NODE_SQL} FROM nodes")
def encode_text(spark, d):
    return sources.text(spark, d).select(CODE)


@query("encode_dom", f"{DOM_SQL} SELECT {NODE_SQL} FROM nodes")
def encode_dom(spark, d):
    return sources.dom(spark, d).select(CODE)


@query("sampled_forest", f"{encoded(O.navigation_edges(*NAV, keep=50))} SELECT {NODE_SQL} FROM nodes")
def sampled_forest(spark, d):
    return sources.navigation(spark, d, keep=50).select(CODE)


STATS_SQL = """, paths AS (SELECT v.tree_id, v."begin", v.label, coalesce(string_agg(u.label, '/' ORDER BY u."begin"), '') || '/' || v.label AS path, coalesce(bool_or(u.label = v.label), false) AS again
    FROM nodes v LEFT JOIN nodes u ON u.tree_id = v.tree_id AND u."begin" < v."begin" AND v."end" < u."end" GROUP BY v.tree_id, v."begin", v.label)
    SELECT count(*) AS n_nodes, count(DISTINCT tree_id) AS n_trees, count(DISTINCT label) AS n_labels, max(level)::BIGINT AS max_depth, sum(level)::BIGINT AS sum_depth,
      (SELECT count(DISTINCT path) FROM paths) AS n_paths, (SELECT sum(again::INT)::BIGINT FROM paths) AS n_recursive FROM nodes"""


@query("tree_stats_dialogue", f"WITH {O.dialogue()}{STATS_SQL}")
def tree_stats_dialogue(spark, d):
    return stats.describe(stage(sources.dialogue(spark, d), "dialogue"))


@query(
    "tree_stats_star",
    f"""WITH {O.star()} SELECT count(*) AS n_nodes, count(DISTINCT tree_id) AS n_trees, count(DISTINCT label) AS n_labels, max(level)::BIGINT AS max_depth, sum(level)::BIGINT AS sum_depth,
    count(DISTINCT label) AS n_paths, 0::BIGINT AS n_recursive FROM nodes""",
)
def tree_stats_star(spark, d):
    return stats.describe(star(spark, d))


@query("tree_stats_dom", DOM_SQL + STATS_SQL)
def tree_stats_dom(spark, d):
    return stats.describe(stage(sources.dom(spark, d), "dom"))


@query("label_freq", f"WITH {O.star()} SELECT label, count(*) AS support, count(DISTINCT tree_id) AS trees FROM nodes GROUP BY label")
def label_freq(spark, d):
    return lists.label_counts(star(spark, d))


@query("inverted_lists", f"""WITH {O.dialogue()} SELECT label, tree_id, row_number() OVER (PARTITION BY label ORDER BY tree_id, "begin") - 1 AS ord, "begin", "end", level FROM nodes""")
def inverted_lists(spark, d):
    return lists.build(sources.dialogue(spark, d))


@query("label_dictionary", f"WITH {O.star()} SELECT DISTINCT label, (dense_rank() OVER (ORDER BY label) - 1)::INT AS label_id FROM nodes")
def label_dictionary(spark, d):
    return lists.label_ids(star(spark, d))


@query("glue_forest", f"""WITH {O.dialogue()}, sizes AS (SELECT tree_id, count(*) n FROM nodes GROUP BY tree_id), shifts AS (SELECT tree_id, (2 * (sum(n) OVER (ORDER BY tree_id) - n) + 1)::BIGINT s FROM sizes)
    SELECT 0 AS tree_id, "begin" + s AS "begin", "end" + s AS "end", level + 1 AS level, parent + s AS parent, label FROM nodes JOIN shifts USING (tree_id)""")
def glue_forest(spark, d):
    return encode.glue(stage(sources.dialogue(spark, d), "dialogue")).select(CODE)


@query("split_forest", f"WITH {O.dialogue()} SELECT count(*) AS n_nodes, count(DISTINCT tree_id) AS n_trees, sum(level)::BIGINT AS sum_depth, sum(\"end\" - \"begin\")::BIGINT AS span FROM nodes")
def split_forest(spark, d):
    glued = encode.glue(stage(sources.dialogue(spark, d), "dialogue"))
    return encode.split(glued).agg(F.count(F.lit(1)).alias("n_nodes"), F.count_distinct("tree_id").alias("n_trees"), F.sum("level").alias("sum_depth"), F.sum(F.col("end") - F.col("begin")).alias("span"))


@query("depth_histogram", f"WITH {O.star()} SELECT level, count(*) AS n FROM nodes GROUP BY level")
def depth_histogram(spark, d):
    return navigate.depth_histogram(star(spark, d))


@query("subtree_sizes", f"""WITH {O.star()} SELECT label, sum(("end" - "begin" + 1) // 2)::BIGINT AS nodes_below, max(("end" - "begin" + 1) // 2) AS largest FROM nodes GROUP BY label""")
def subtree_sizes(spark, d):
    size = region.subtree_size(F.col("begin"), F.col("end"))
    return star(spark, d).groupBy("label").agg(F.sum(size).alias("nodes_below"), F.max(size).alias("largest"))


@query("navigation_relatives", f"""WITH {O.dialogue()}, w AS (SELECT tree_id, "begin" b, "end" e, parent p FROM nodes WHERE label = 'assistant')
    SELECT 'children' AS relation, count(DISTINCT (v.tree_id, v."begin")) AS n FROM nodes v JOIN w ON v.tree_id = w.tree_id AND v.parent = b
    UNION ALL SELECT 'parent', count(DISTINCT (v.tree_id, v."begin")) FROM nodes v JOIN w ON v.tree_id = w.tree_id AND v."begin" = p
    UNION ALL SELECT 'ancestors', count(DISTINCT (v.tree_id, v."begin")) FROM nodes v JOIN w ON v.tree_id = w.tree_id AND v."begin" < b AND v."end" > e
    UNION ALL SELECT 'descendants', count(DISTINCT (v.tree_id, v."begin")) FROM nodes v JOIN w ON v.tree_id = w.tree_id AND v."begin" > b AND v."end" < e
    UNION ALL SELECT 'siblings', count(DISTINCT (v.tree_id, v."begin")) FROM nodes v JOIN w ON v.tree_id = w.tree_id AND v.parent = p AND v."begin" != b
    UNION ALL SELECT 'leaves', count(*) FROM nodes WHERE "end" = "begin" + 1
    UNION ALL SELECT 'roots', count(*) FROM nodes WHERE level = 0""")
def navigation_relatives(spark, d):
    nodes = stage(sources.dialogue(spark, d), "dialogue")
    wanted = nodes.where("label = 'assistant'")
    found = {"children": navigate.children(nodes, wanted), "parent": navigate.parent_of(nodes, wanted), "ancestors": navigate.ancestors_of(nodes, wanted), "descendants": navigate.descendants_of(nodes, wanted), "siblings": navigate.siblings_of(nodes, wanted), "leaves": navigate.leaves(nodes), "roots": navigate.roots(nodes)}
    return occlist.union_all([df.select("tree_id", "begin").distinct().agg(F.lit(k).alias("relation"), F.count(F.lit(1)).alias("n")) for k, df in found.items()])


@query("lowest_common_ancestor", f"""WITH {O.dialogue()}, p AS (SELECT u.tree_id, u."begin" a, v."begin" b, u."end" ae, v."end" be FROM nodes u JOIN nodes v ON u.tree_id = v.tree_id AND u."begin" < v."begin" WHERE u.label LIKE 'len=%' AND v.label LIKE 'len=%')
    SELECT p.tree_id, a, b, max(n."begin") AS lca FROM p JOIN nodes n ON n.tree_id = p.tree_id AND n."begin" <= a AND n."end" >= ae AND n."begin" <= b AND n."end" >= be GROUP BY p.tree_id, a, b""")
def lowest_common_ancestor(spark, d):
    nodes = stage(sources.dialogue(spark, d), "dialogue")
    leaf = nodes.where("label LIKE 'len=%'").select("tree_id", "begin")
    pairs = leaf.withColumnRenamed("begin", "a").join(leaf.withColumnRenamed("begin", "b"), "tree_id").where("a < b")
    return navigate.lowest_common_ancestor(nodes, pairs)


# structural joins and 2-patterns


@query("ancestor_pairs", f"WITH {O.dialogue()}, {O.dialogue_pairs()} SELECT t AS tree_id, a, ae AS a_end, al AS a_label, d, de AS d_end, dl AS d_label FROM pairs")
def ancestor_pairs(spark, d):
    return structural.ancestor_pairs(stage(sources.dialogue(spark, d), "dialogue"))


@query("ancestor_pairs_range", ORACLES["ancestor_pairs"])
def ancestor_pairs_range(spark, d):
    return structural.ancestor_pairs(stage(sources.dialogue(spark, d), "dialogue"), how="range")


F2_SQL = "SELECT al AS anc_label, dl AS desc_label, count(DISTINCT (t, a)) AS support, count(*) AS n_pairs FROM pairs GROUP BY al, dl"


@query("f2_dialogue", f"WITH {O.dialogue()}, {O.PAIRS} {F2_SQL}")
def f2_dialogue(spark, d):
    return structural.pair_table(stage(sources.dialogue(spark, d), "dialogue"))


@query("f2_star", f"WITH {O.star()}, {O.star_pairs()} {F2_SQL}")
def f2_star(spark, d):
    return structural.pair_table(star(spark, d))


# twig queries

FLAGS = "(SELECT DISTINCT l_orderkey FROM lineitem {})"
TWIGS = {
    "line_r_f": ("order(line(flag=R,ls=F))", "SELECT count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_returnflag = 'R' AND l_linestatus = 'F'", None),
    "two_r": (
        "order(line(flag=R),line(flag=R))",
        "SELECT count(*) AS n FROM (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R' GROUP BY l_orderkey HAVING count(*) > 1)",
        "SELECT count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_returnflag = 'R'",
    ),
    "skip_levels": (
        "nation(order(flag=R),seg=BUILDING)",
        "SELECT count(DISTINCT c_nationkey) AS n FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND c_nationkey IN (SELECT c_nationkey FROM customer WHERE c_mktsegment = 'BUILDING')",
        None,
    ),
    "customer_urgent": ("customer(seg=BUILDING,order(prio=1-URGENT))", "SELECT count(DISTINCT o_custkey) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING' AND o_orderpriority = '1-URGENT'", None),
}


def twig_query(text: str, kind: str) -> Query:
    return lambda spark, d: twig.roots(star(spark, d), text, kind).agg(F.count(F.lit(1)).alias("n"))


for _name, (_text, _emb, _hom) in TWIGS.items():
    for _kind in twig.KINDS:
        _sql = _hom if _kind == "hom" and _hom else "SELECT 0::BIGINT AS n" if _kind == "iso" and _name == "skip_levels" else _emb
        query(f"{_kind}_roots_{_name}", _sql)(twig_query(_text, _kind))


@query("support_three_ways", """WITH x AS (SELECT l_orderkey, count(*) n FROM lineitem WHERE l_returnflag = 'R' GROUP BY l_orderkey HAVING count(*) > 1), r AS (SELECT l_orderkey, n, n_regionkey FROM x JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)
    SELECT count(*) AS root_support, sum(n * (n - 1))::BIGINT AS occ_support, count(DISTINCT n_regionkey) AS doc_support FROM r""")
def support_three_ways(spark, d):
    return twig.find(star(spark, d), "order(line(flag=R),line(flag=R))", what="counts")


@query("twig_semi_join", "SELECT 0 AS pos, count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_returnflag = 'R' AND l_linestatus = 'F' UNION ALL SELECT p, count(*) FROM lineitem, (VALUES (1), (2), (3)) v(p) WHERE l_returnflag = 'R' AND l_linestatus = 'F' GROUP BY p")
def twig_semi_join(spark, d):
    got = twig.reduced_lists(star(spark, d), parse("order(line(flag=R,ls=F))"))
    return occlist.union_all([x.agg(F.lit(n).alias("pos"), F.count(F.lit(1)).alias("n")) for n, x in enumerate(got)])


@query("sibling_filter", "WITH x AS (SELECT count(*) n FROM lineitem WHERE l_returnflag = 'R' GROUP BY l_orderkey) SELECT sum(n * n)::BIGINT AS n_hom, sum(n * (n - 1))::BIGINT AS n_emb FROM x")
def sibling_filter(spark, d):
    p = parse("order(line(flag=R),line(flag=R))")
    hom = stage(twig.occurrences(star(spark, d), p, "hom"), "hom")
    n = hom.agg(F.count(F.lit(1)).alias("n_hom"))
    return n.crossJoin(sibling.keep_embedded(hom, p).agg(F.count(F.lit(1)).alias("n_emb")))  # one row each


@query("twig_dialogue_chain", f"WITH {O.dialogue()}, {O.PAIRS} SELECT count(DISTINCT (p.t, p.a)) AS n FROM pairs p JOIN pairs q ON p.t = q.t AND p.d = q.a JOIN pairs s ON q.t = s.t AND q.d = s.a WHERE p.al = 'conv' AND p.dl = 'user' AND q.dl = 'assistant' AND s.dl = 'user'")
def twig_dialogue_chain(spark, d):
    return twig.roots(stage(sources.dialogue(spark, d), "dialogue"), "conv(user(assistant(user)))").agg(F.count(F.lit(1)).alias("n"))


@query("twig_dom", f"""{DOM_SQL}
    SELECT 'p(p)' AS pattern, count(DISTINCT (t, a)) AS n FROM pairs WHERE al = 'p' AND dl = 'p'
    UNION ALL SELECT 'body(article(p(b)))', count(DISTINCT (x.t, x.a)) FROM pairs x JOIN pairs y ON y.t = x.t AND y.a = x.d JOIN pairs z ON z.t = y.t AND z.a = y.d WHERE x.al = 'body' AND x.dl = 'article' AND y.dl = 'p' AND z.dl = 'b'
    UNION ALL SELECT 'html(a,p)', count(DISTINCT (x.t, x.a)) FROM pairs x JOIN pairs y ON y.t = x.t AND y.a = x.a WHERE x.al = 'html' AND x.dl = 'a' AND y.dl = 'p' AND (x.de < y.d OR y.de < x.d)""")
def twig_dom(spark, d):
    nodes = stage(sources.dom(spark, d), "dom")
    rows = [twig.roots(nodes, t).agg(F.lit(t).alias("pattern"), F.count(F.lit(1)).alias("n")) for t in ("p(p)", "body(article(p(b)))", "html(a,p)")]
    return occlist.union_all(rows)


# bitmaps


def flag_bitmaps(spark, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    nodes = star(spark, d)
    orders = stage(lists.build(nodes.where("label = 'order'")), "lists")
    tops = occlist.union_all([twig.roots(nodes, f"order(flag={x})").withColumn("flag", F.lit(x)) for x in "RA"]).withColumn("label", F.lit("order"))
    return orders, occlist.to_bitmaps(tops, orders, ["flag"]), tops


BOTH = "SELECT l_orderkey FROM lineitem WHERE l_returnflag IN ('R', 'A') GROUP BY l_orderkey"


@query("bitmap_and", f"SELECT count(*) AS n FROM ({BOTH} HAVING count(DISTINCT l_returnflag) = 2)")
def bitmap_and(spark, d):
    return occlist.bit_count(occlist.bit_and(flag_bitmaps(spark, d)[1], ["label"], 2), []).select(F.col("n").cast("long").alias("n"))


@query("bitmap_or", f"SELECT count(*) AS n FROM ({BOTH})")
def bitmap_or(spark, d):
    return occlist.bit_count(occlist.bit_or(flag_bitmaps(spark, d)[1], ["label"]), []).select(F.col("n").cast("long").alias("n"))


@query("bitmap_unpack", "SELECT l_returnflag AS flag, count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_returnflag IN ('R', 'A') GROUP BY l_returnflag")
def bitmap_unpack(spark, d):
    orders, bits, _ = flag_bitmaps(spark, d)
    return occlist.unpack(bits, orders, ["flag"]).groupBy("flag").agg(F.count(F.lit(1)).alias("n"))


# miners inside the universe of patterns of three nodes at most

STAR3 = f"WITH {O.star()}, {O.star_pairs(STAR_ROOTS)}, m AS (SELECT (count(*) * {{p}} + 99) // 100 AS n FROM orders), {O.small_patterns('(SELECT n FROM m)', STAR_ROOTS)}"
DIALOGUE3 = f"WITH {O.dialogue()}, {O.PAIRS}, {O.small_patterns(50)}"


def star3(miner: Callable, spark, d, percent: int = 20, **kw) -> result.MiningResult:
    minsup = order_minsup(spark, d, percent)
    return miner(order_trees(spark, d, minsup), minsup, max_size=3, roots=set(STAR_ROOTS), **kw)


@query("frequent_k3_star", STAR3.format(p=20) + " SELECT code, k, support FROM frequent")
def frequent_k3_star(spark, d):
    return star3(miners.mine_frequent, spark, d).result().select("code", "k", "support")


@query("class_expansion", STAR3.format(p=30) + """, kinds AS (SELECT x.al AS root, x.dl AS a, y.dl AS b, x.al || '(' || x.dl || ')' AS left_code, x.al || '(' || y.dl || ')' AS right_code FROM members x JOIN members y ON x.al = y.al)
    SELECT left_code, right_code, 'child' AS kind, root || '(' || a || '(' || b || '))' AS code FROM kinds UNION ALL SELECT left_code, right_code, 'cousin', root || '(' || a || ',' || b || ')' FROM kinds""".replace("kinds AS", "members AS (SELECT al, dl FROM pairs GROUP BY al, dl HAVING al || '(' || dl || ')' IN (SELECT code FROM two)), kinds AS", 1))
def class_expansion(spark, d):
    """Child and cousin joins of all members of the classes of order and line."""
    found = star3(miners.mine_frequent, spark, d, 30).search
    members = [m for m in found.reported() if m.size == 2]
    rows = [(show(x), show(y), kind, show(q)) for root in STAR_ROOTS for x, y, kind, q in expand_class([m.pattern for m in members if m.pattern.labels[0] == root])]
    return spark.createDataFrame(rows, "left_code string, right_code string, kind string, code string")


@query("class_joins", STAR3.format(p=30) + """ SELECT code, k, CASE WHEN shape = 'chain' THEN 'child' ELSE 'cousin' END AS kind FROM three""")
def class_joins(spark, d):
    """How the frequent 3-patterns came about."""
    return star3(miners.mine_frequent, spark, d, 30).patterns().where("k = 3").select("code", "k", F.col("join_kind").alias("kind"))


@query("pattern_functions", STAR3.format(p=30) + """ SELECT code AS text, k AS size, 1 AS depth, 1 AS fanout, 1 AS leaves, true AS is_path, code, split_part(code, '(', 1) AS prefix, true AS canonical FROM two
    UNION ALL SELECT code, 3, CASE shape WHEN 'chain' THEN 2 ELSE 1 END, CASE shape WHEN 'chain' THEN 1 ELSE 2 END, CASE shape WHEN 'chain' THEN 1 ELSE 2 END, shape = 'chain', code, x || '(' || y || ')', true FROM three""")
def pattern_functions(spark, d):
    t = star3(miners.mine_frequent, spark, d, 30).result().select(F.col("code").alias("text"))
    return t.select("text", pf.p_size("text").alias("size"), pf.p_depth("text").alias("depth"), pf.p_fanout("text").alias("fanout"), pf.p_leaves("text").alias("leaves"), pf.p_is_path("text").alias("is_path"), pf.p_code("text").alias("code"), pf.p_prefix("text").alias("prefix"), pf.p_canonical("text").alias("canonical"))


@query("search_tree_star", STAR3.format(p=30) + " SELECT NULL AS parent, split_part(code, '(', 1) AS root, code, k FROM two UNION ALL SELECT x || '(' || y || ')', x, code, k FROM three")
def search_tree_star(spark, d):
    """The tree of the search: every frequent pattern under its prefix."""
    return result.search_tree(star3(miners.mine_frequent, spark, d, 30).patterns())


@query("occurrence_join_k3_star", ORACLES["frequent_k3_star"])
def occurrence_join_k3_star(spark, d):
    return star3(mine_occurrence_join, spark, d).result().select("code", "k", "support")


@query("lists_k3_star", STAR3.format(p=50) + " SELECT code, k, support FROM frequent")
def lists_k3_star(spark, d):
    return star3(mine_lists, spark, d, 50).result().select("code", "k", "support")


@query("apriori_k3_star", ORACLES["frequent_k3_star"])
def apriori_k3_star(spark, d):
    return star3(miners.mine_frequent, spark, d, apriori=True).result().select("code", "k", "support")


@query("postfilter_k3_star", STAR3.format(p=20) + " SELECT code, k, support, is_closed, is_maximal FROM flagged")
def postfilter_k3_star(spark, d):
    return star3(miners.mine_postfilter, spark, d).result()


@query("eager_k3_star", ORACLES["postfilter_k3_star"])
def eager_k3_star(spark, d):
    return star3(miners.mine_eager, spark, d).result()


@query("eager_lists_k3_star", STAR3.format(p=50) + " SELECT code, k, support, is_closed, is_maximal FROM flagged")
def eager_lists_k3_star(spark, d):
    return star3(miners.mine_eager, spark, d, 50, strategy="lists").result()


@query("postfilter_bitmaps_k3_star", ORACLES["eager_lists_k3_star"])
def postfilter_bitmaps_k3_star(spark, d):
    return star3(miners.mine_postfilter, spark, d, 50, strategy="lists", lists="bitmap").result()


@query("closed_k3_star", STAR3.format(p=30) + " SELECT code, k, support FROM flagged WHERE is_closed")
def closed_k3_star(spark, d):
    return star3(miners.mine_eager, spark, d, 30).result().where("is_closed").select("code", "k", "support")


@query("maximal_k3_star", STAR3.format(p=30) + " SELECT code, k, support FROM flagged WHERE is_maximal")
def maximal_k3_star(spark, d):
    return star3(miners.mine_eager, spark, d, 30).result().where("is_maximal").select("code", "k", "support")


# full runs, without a size cap, where SQL can list all patterns: a line's path has five nodes below the order, a part three leaves

PATHS = """WITH v AS (SELECT 'flag=' || l_returnflag AS f, 'ls=' || l_linestatus AS s, 'prio=' || o_orderpriority AS p, 'status=' || o_orderstatus AS t FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
    m AS (SELECT (count(*) + 19) // 20 AS n FROM v),
    sets AS (SELECT f, s, p, t, (f IS NOT NULL)::INT + (s IS NOT NULL)::INT + (p IS NOT NULL)::INT + (t IS NOT NULL)::INT AS size, count(*) AS support FROM v GROUP BY CUBE (f, s, p, t) HAVING count(*) >= (SELECT n FROM m)),
    larger AS (SELECT a.f, a.s, a.p, a.t, b.support FROM sets a JOIN sets b ON b.size > a.size AND (a.f IS NULL OR a.f = b.f) AND (a.s IS NULL OR a.s = b.s) AND (a.p IS NULL OR a.p = b.p) AND (a.t IS NULL OR a.t = b.t)),
    flagged AS (SELECT 'order(' || concat_ws(',', 'line' || CASE WHEN f IS NULL AND s IS NULL THEN '' ELSE '(' || concat_ws(',', f, s) || ')' END, p, t) || ')' AS code, size + 2 AS k, support,
      NOT EXISTS (SELECT 1 FROM larger g WHERE (g.f, g.s, g.p, g.t) IS NOT DISTINCT FROM (a.f, a.s, a.p, a.t) AND g.support = a.support) AS is_closed,
      NOT EXISTS (SELECT 1 FROM larger g WHERE (g.f, g.s, g.p, g.t) IS NOT DISTINCT FROM (a.f, a.s, a.p, a.t)) AS is_maximal FROM sets a)"""
#: Without the line, a pattern is not closed: the line can always be added. So all closed ones have it.
PATHS_CLOSED = PATHS + " SELECT code, k::INT AS k, support, is_maximal FROM flagged WHERE is_closed"


def path_run(miner: Callable, spark, d, **kw) -> result.MiningResult:
    n = spark.read.parquet(f"{d}/lineitem.parquet").count()
    return miner(stage(sources.line_paths(spark, d), "paths"), max(1, -(-n // 20)), roots={"order"}, label_order="depth", **kw)


def closed_of(r: result.MiningResult) -> DataFrame:
    return r.result().where("is_closed").select("code", "k", "support", "is_maximal")


for _miner, _name, _kw in (
    (miners.mine_postfilter, "postfilter", {}),
    (miners.mine_eager, "eager", {}),
    (miners.mine_pruned, "pruned", {}),
    (miners.mine_pruned, "pruned_filters", {"rule": "filters"}),
    (miners.mine_pruned, "pruned_definition", {"rule": "definition"}),
    (miners.mine_pruned, "pruned_bitmaps", {"strategy": "lists", "lists": "bitmap"}),
):
    query(f"closed_full_paths_{_name}", PATHS_CLOSED)(lambda spark, d, miner=_miner, kw=_kw: closed_of(path_run(miner, spark, d, **kw)))


@query("maximal_full_paths", PATHS + " SELECT code, k::INT AS k, support FROM flagged WHERE is_maximal")
def maximal_full_paths(spark, d):
    return path_run(lambda *a, **kw: miners.mine_pruned(*a, **kw), spark, d).result().where("is_maximal").select("code", "k", "support")


@query("surrogates_full_paths", PATHS + " SELECT 'order(' || x || ')' AS code, 'child' AS kind, 'order(line)' AS by_code FROM (SELECT f AS x, size FROM sets UNION ALL SELECT s, size FROM sets) WHERE size = 1 AND x IS NOT NULL")
def surrogates_full_paths(spark, d):
    """The 2-patterns that the pruned miner drops: leaves of a line, which always have the line above them."""
    mined = path_run(miners.mine_pruned, spark, d).search
    rows = [(mined.code(m), m.pruned_by[1], mined.code(mined.mined[m.pruned_by[0]])) for m in mined.mined.values() if m.pruned_by and m.size == 2]
    return spark.createDataFrame(rows, "code string, kind string, by_code string")


@query("computed_full_paths", "SELECT true AS pruned_computes_fewer, true AS eager_computes_as_many, true AS pruned_drops_some")
def computed_full_paths(spark, d):
    post, eager, pruned = (path_run(m, spark, d) for m in (miners.mine_postfilter, miners.mine_eager, miners.mine_pruned))
    row = (pruned.counters.computed < eager.counters.computed, eager.counters.computed == post.counters.computed, any(m.pruned_by for m in pruned.search.mined.values()))
    return spark.createDataFrame([row], "pruned_computes_fewer boolean, eager_computes_as_many boolean, pruned_drops_some boolean")


GOODS = f"""WITH {O.supply()}, v AS (SELECT n, s, p, [brand, kind, size] AS leaves FROM goods),
    sets AS (SELECT n, s, p, list_sort(unnest([[leaves[1]], [leaves[2]], [leaves[3]], [leaves[1], leaves[2]], [leaves[1], leaves[3]], [leaves[2], leaves[3]], leaves])) AS x FROM v),
    frequent AS (SELECT x, count(*) AS support FROM sets GROUP BY x HAVING count(*) >= (SELECT (count(*) + 49) // 50 FROM goods))
    SELECT 'part(' || array_to_string(x, ',') || ')' AS code, len(x)::INT + 1 AS k, support, NOT EXISTS (SELECT 1 FROM frequent g WHERE len(g.x) > len(f.x) AND list_has_all(g.x, f.x)) AS is_maximal FROM frequent f
    WHERE NOT EXISTS (SELECT 1 FROM frequent g WHERE len(g.x) > len(f.x) AND list_has_all(g.x, f.x) AND g.support = f.support)"""


@query("closed_full_supply_pruned", GOODS)
def closed_full_supply_pruned(spark, d):
    nodes = stage(sources.supply(spark, d), "supply")
    n = nodes.where("label = 'part'").count()
    return closed_of(miners.mine_pruned(nodes, -(-n // 50), roots={"part"}, label_order="frequency"))


def dialogue3(miner: Callable, spark, d, **kw) -> result.MiningResult:
    return miner(stage(sources.dialogue(spark, d), "dialogue"), 50, max_size=3, **kw)


@query("frequent_k3_dialogue", DIALOGUE3 + " SELECT code, k, support FROM frequent")
def frequent_k3_dialogue(spark, d):
    return dialogue3(miners.mine_frequent, spark, d).result().select("code", "k", "support")


DOC3 = f"""WITH {O.dialogue()}, {O.PAIRS},
    shapes AS (SELECT al || '(' || dl || ')' AS code, 2 AS k, t FROM pairs
      UNION ALL SELECT p.al || '(' || p.dl || '(' || q.dl || '))', 3, p.t FROM pairs p JOIN pairs q ON p.t = q.t AND p.d = q.a
      UNION ALL SELECT p.al || '(' || p.dl || ',' || q.dl || ')', 3, p.t FROM pairs p JOIN pairs q ON p.t = q.t AND p.a = q.a AND p.dl <= q.dl AND (p.de < q.d OR q.de < p.d))
    SELECT code, k, count(DISTINCT t) AS support FROM shapes GROUP BY code, k HAVING count(DISTINCT t) >= 50"""


@query("document_support_k3_dialogue", DOC3)
def document_support_k3_dialogue(spark, d):
    return dialogue3(miners.mine_frequent, spark, d, support="document").result().select("code", "k", "support")


LOCAL = " , kids AS (SELECT x || '(' || y || ')' AS p, support FROM three UNION ALL SELECT x || '(' || z || ')', support FROM three) SELECT code, NOT EXISTS (SELECT 1 FROM kids WHERE p = code AND kids.support = two.support) AS is_locally_closed FROM two"


@query("locally_closed_k2_star", STAR3.format(p=20) + LOCAL)
def locally_closed_k2_star(spark, d):
    return star3(miners.mine_eager, spark, d).patterns().where("k = 2").select("code", "is_locally_closed")


INDUCED3 = f"""WITH {O.star()}, e AS (SELECT u.tree_id t, u."begin" a, u.label al, v."begin" d, v.label dl FROM nodes u JOIN nodes v ON u.tree_id = v.tree_id AND v.parent = u."begin"), m AS (SELECT (count(*) * 30 + 99) // 100 AS n FROM orders)
    SELECT al || '(' || dl || ')' AS code, 2 AS k, count(DISTINCT (t, a)) AS support FROM e GROUP BY al, dl HAVING count(DISTINCT (t, a)) >= (SELECT n FROM m)
    UNION ALL SELECT p.al || '(' || p.dl || '(' || q.dl || '))', 3, count(DISTINCT (p.t, p.a)) FROM e p JOIN e q ON p.t = q.t AND p.d = q.a GROUP BY p.al, p.dl, q.dl HAVING count(DISTINCT (p.t, p.a)) >= (SELECT n FROM m)
    UNION ALL SELECT p.al || '(' || p.dl || ',' || q.dl || ')', 3, count(DISTINCT (p.t, p.a)) FROM e p JOIN e q ON p.t = q.t AND p.a = q.a AND p.dl <= q.dl AND p.d != q.d GROUP BY p.al, p.dl, q.dl HAVING count(DISTINCT (p.t, p.a)) >= (SELECT n FROM m)"""


INDUCED_FLAGS = f"""WITH {O.star()}, e AS (SELECT u.tree_id t, u."begin" a, u.label al, v."begin" d, v.label dl FROM nodes u JOIN nodes v ON u.tree_id = v.tree_id AND v.parent = u."begin"), m AS (SELECT (count(*) * 30 + 99) // 100 AS n FROM orders),
    two AS (SELECT al || '(' || dl || ')' AS code, count(DISTINCT (t, a)) AS support FROM e GROUP BY al, dl HAVING count(DISTINCT (t, a)) >= (SELECT n FROM m)),
    chain AS (SELECT p.al x, p.dl y, q.dl z, count(DISTINCT (p.t, p.a)) AS support FROM e p JOIN e q ON p.t = q.t AND p.d = q.a GROUP BY p.al, p.dl, q.dl HAVING count(DISTINCT (p.t, p.a)) >= (SELECT n FROM m)),
    fork AS (SELECT p.al x, p.dl y, q.dl z, count(DISTINCT (p.t, p.a)) AS support FROM e p JOIN e q ON p.t = q.t AND p.a = q.a AND p.dl <= q.dl AND p.d != q.d GROUP BY p.al, p.dl, q.dl HAVING count(DISTINCT (p.t, p.a)) >= (SELECT n FROM m)),
    inside AS (SELECT x || '(' || y || ')' AS p, support FROM chain UNION ALL SELECT y || '(' || z || ')', support FROM chain UNION ALL SELECT x || '(' || y || ')', support FROM fork UNION ALL SELECT x || '(' || z || ')', support FROM fork)
    SELECT code, 2 AS k, support, NOT EXISTS (SELECT 1 FROM inside i WHERE p = code AND i.support = two.support) AS is_closed, NOT EXISTS (SELECT 1 FROM inside WHERE p = code) AS is_maximal FROM two
    UNION ALL SELECT x || '(' || y || '(' || z || '))', 3, support, true, true FROM chain UNION ALL SELECT x || '(' || y || ',' || z || ')', 3, support, true, true FROM fork"""


@query("induced_k3_star", INDUCED_FLAGS)
def induced_k3_star(spark, d):
    minsup = order_minsup(spark, d, 30)
    return mine_induced(order_trees(spark, d, minsup), minsup, max_size=3).result()


@query("induced_frequent_k3_star", INDUCED3)
def induced_frequent_k3_star(spark, d):
    return induced_k3_star(spark, d).select("code", "k", "support")


@query("closed_by_support_k3_star", STAR3.format(p=20) + """, pairs_in AS (SELECT x || '(' || y || ')' AS p, code q FROM three UNION SELECT x || '(' || z || ')', code FROM three UNION SELECT y || '(' || z || ')', code FROM three WHERE shape = 'chain')
    SELECT f.code FROM frequent f WHERE NOT EXISTS (SELECT 1 FROM pairs_in i JOIN frequent g ON g.code = i.q WHERE i.p = f.code AND g.support = f.support)""")
def closed_by_support_k3_star(spark, d):
    r = star3(miners.mine_frequent, spark, d)
    keep = closed.by_support(r.search.reported())
    return spark.createDataFrame([(r.search.code(m),) for m in r.search.reported() if m.id in keep], "code string")


@query("constrained_text", f"{TEXT_SQL}, {O.small_patterns(3, ('doc',))} SELECT code, k, support, is_closed, is_maximal FROM flagged WHERE code LIKE '%toxic=1%'")
def constrained_text(spark, d):
    required = {"toxic=1"}
    nodes = stage(sources.text_trees(spark, d, required), "text")
    return miners.mine_constrained(nodes, 3, required=required, root="doc", max_size=3, max_depth=2).select("code", "k", "support", "is_closed", "is_maximal")


@query("onestep_k3_star", STAR3.format(p=40) + " SELECT code, is_closed, is_maximal FROM flagged")
def onestep_k3_star(spark, d):
    r = star3(mine_onestep, spark, d, 40)
    return spark.createDataFrame([(c, c in r.closed, c in r.maximal) for c in sorted(r.result.codes())], "code string, is_closed boolean, is_maximal boolean")


# surrogates

CANDIDATES = f"""WITH {O.star()}, {O.star_pairs(('order', 'line'))}
    SELECT q.dl AS y FROM (SELECT * FROM pairs WHERE al = 'order') q LEFT JOIN (SELECT DISTINCT t, d FROM pairs WHERE al = 'line') x ON q.t = x.t AND q.d = x.d
    WHERE q.dl != 'line' GROUP BY q.dl HAVING count(*) = count(x.d)"""


@query("surrogate_child_star", CANDIDATES)
def surrogate_child_star(spark, d):
    """Labels below order that always have a line above: line is their child surrogate in the class of order."""
    from canopy.mine.engine import Search

    search = Search(star(spark, d), miners.options(None, 1, {"roots": {"order"}, "label_order": "depth", "compress": False, "max_size": 3}))
    frequent = search.seed()
    new = [q for members in search.classes(frequent).values() for q in search.candidates(members, members)]
    search.evaluated(3, new, search.join(3, new), part=True)
    found = surrogate.find_candidates(search, new)
    y = sorted({search.mined[p.y].pattern.labels[-1] for p in found if p.kind == "child" and search.mined[p.x].pattern.labels[-1] == "line"})
    return spark.createDataFrame([(x,) for x in y], "y string")


def nav(spark, d, label: str = "type") -> DataFrame:
    return stage(sources.navigation(spark, d, label), "nav")


@query("pruning_rules_star")
def pruning_rules_star(spark, d):
    """Counters of the pruned miner under each rule, and what it loses or adds against the definition."""
    nodes, minsup = star(spark, d), order_minsup(spark, d, 80)
    truth = miners.mine_postfilter(nodes, minsup, roots=set(STAR_ROOTS), label_order="depth").codes("closed")
    rows = []
    for rule in surrogate.RULES:
        r = miners.mine_pruned(nodes, minsup, rule=rule, roots=set(STAR_ROOTS), label_order="depth")
        got = r.codes("closed")
        rows.append((rule, r.counters.computed, r.counters.freq, len(got), len(truth - got), len(got - truth)))
    return spark.createDataFrame(rows, "rule string, computed long, freq long, closed long, lost long, added long")


def closed_runs(spark, name: str, nodes: DataFrame, minsup: int, order: str = "depth") -> DataFrame:
    """Counters of the closed miners on full runs, all with the labels in one order."""
    kw = {"label_order": order}
    runs = [(name, miners.mine_postfilter(nodes, minsup, **kw)), (name, miners.mine_eager(nodes, minsup, **kw)), *((name, miners.mine_pruned(nodes, minsup, rule=r, **kw)) for r in ("uniform", "filters"))]
    return miners.counters_frame(spark, runs).drop("seconds", "closed_seconds", "stored_bytes")


@query("counters_nav")
def counters_nav(spark, d):
    """Counters of the closed miners on a full run over navigation trees."""
    nodes = nav(spark, d)
    n = max(2, nodes.where("level = 0").count() * 85 // 100)
    return closed_runs(spark, "nav", nodes, n)


SKELETON = ["html", "body", "nav", "ul", "article", "h1", "footer"]


@query("counters_dom")
def counters_dom(spark, d):
    """Counters of the closed miners on the skeleton of pages, where containers are surrogates of their content."""
    nodes = stage(sources.dom(spark, d, labels=SKELETON, dedupe_siblings=True), "dom")
    n = -(-spark.read.parquet(f"{d}/pages.parquet").count() * 9 // 10)
    return closed_runs(spark, "dom", nodes, n)


AGREE = """SELECT 'uniform' AS rule, 0::BIGINT AS lost_closed, 0::BIGINT AS added_closed, 0::BIGINT AS lost_maximal, 0::BIGINT AS added_maximal, true AS computes_fewer"""


def completeness(spark, nodes: DataFrame, minsup: int, **kw) -> DataFrame:
    """The pruned miner against the definition, by a full run of both over labels in one order."""
    truth, got = miners.mine_postfilter(nodes, minsup, **kw), miners.mine_pruned(nodes, minsup, **kw)
    sets = [(truth.codes(which), got.codes(which)) for which in ("closed", "maximal")]
    rows = [("uniform", *(n for a, b in sets for n in (len(a - b), len(b - a))), got.counters.computed < truth.counters.computed)]
    return spark.createDataFrame(rows, "rule string, lost_closed long, added_closed long, lost_maximal long, added_maximal long, computes_fewer boolean")


@query("completeness_dom", AGREE)
def completeness_dom(spark, d):
    nodes = stage(sources.dom(spark, d, labels=SKELETON, dedupe_siblings=True), "dom")
    return completeness(spark, nodes, page_minsup(spark, d, 90), label_order="depth")


@query("completeness_star", AGREE)
def completeness_star(spark, d):
    minsup = order_minsup(spark, d, 80)
    return completeness(spark, order_trees(spark, d, minsup), minsup, roots=set(STAR_ROOTS), label_order="depth")


@query("witness_modes_dialogue", f"WITH {O.dialogue()}, {O.PAIRS}, {O.small_patterns(70)} SELECT code, 'both' AS side FROM flagged WHERE is_closed")
def witness_modes_dialogue(spark, d):
    """Up to three nodes, no witness can be evicted, so both modes agree; a test has an input on which they do not."""
    nodes = stage(sources.dialogue(spark, d), "dialogue")
    a = miners.mine_eager(nodes, 70, max_size=3).result().where("is_closed")
    b = miners.mine_eager(nodes, 70, witness="retained", max_size=3).result().where("is_closed")
    return result.agreement(a, b)


# reading results

FLAGGED = STAR3.format(p=20)
TARGETS = ", tg AS (SELECT code, k, support, 'frequent' AS target FROM flagged UNION ALL SELECT code, k, support, 'closed' FROM flagged WHERE is_closed UNION ALL SELECT code, k, support, 'maximal' FROM flagged WHERE is_maximal)"


@query("distribution_by_size", FLAGGED + TARGETS + " SELECT target, k, count(*) AS n, max(support) AS best FROM tg GROUP BY ROLLUP (target, k)")
def distribution_by_size(spark, d):
    return result.distribution(star3(miners.mine_eager, spark, d).result())


@query("distribution_cube", FLAGGED + TARGETS + " SELECT target, k, count(*) AS n, max(support) AS best FROM tg GROUP BY CUBE (target, k)")
def distribution_cube(spark, d):
    return result.distribution(star3(miners.mine_eager, spark, d).result(), "cube")


@query("compression", FLAGGED + " SELECT count(*) AS n_frequent, sum(is_closed::INT)::BIGINT AS n_closed, sum(is_maximal::INT)::BIGINT AS n_maximal FROM flagged")
def compression(spark, d):
    return result.compression(star3(miners.mine_eager, spark, d).result())


@query("topk_patterns", FLAGGED + " SELECT code, k, support, place FROM (SELECT code, k, support, (row_number() OVER (PARTITION BY k ORDER BY support DESC, code))::INT AS place FROM flagged) WHERE place <= 5")
def topk_patterns(spark, d):
    return result.top(star3(miners.mine_eager, spark, d).result(), 5).select("code", "k", "support", "place")


@query("setops_closed_maximal", FLAGGED + " SELECT code, CASE WHEN is_closed AND is_maximal THEN 'both' WHEN is_closed THEN 'first' ELSE 'second' END AS side FROM flagged WHERE is_closed OR is_maximal")
def setops_closed_maximal(spark, d):
    r = star3(miners.mine_eager, spark, d).result()
    return result.agreement(r.where("is_closed"), r.where("is_maximal"))


@query("running_pattern_count", FLAGGED + " SELECT k, count(*) AS n, (sum(count(*)) OVER (ORDER BY k))::BIGINT AS so_far FROM flagged GROUP BY k")
def running_pattern_count(spark, d):
    by_size = star3(miners.mine_eager, spark, d).result().groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    return by_size.withColumn("so_far", F.sum("n").over(Window.orderBy("k").rowsBetween(Window.unboundedPreceding, 0)))  # a row for each size


# experiments: counts by minsup and by size of the input, for three shapes of data, three nodes at most

COUNTS = "count(*) AS n_frequent, coalesce(sum(is_closed::INT), 0)::BIGINT AS n_closed, coalesce(sum(is_maximal::INT), 0)::BIGINT AS n_maximal"
LADDER = "minsup int, n_frequent long, n_closed long, n_maximal long"


def counted(r: result.MiningResult) -> tuple[int, int, int]:
    return r.counters.freq, r.counters.closed, r.counters.maximal


def ladder(name: str, sql: Callable[[int], str], nodes: Callable[[SparkSession, str], DataFrame], steps: tuple[int, ...], minsup: Callable[[SparkSession, str, int], int], **kw) -> None:
    """Registers the counts of frequent, closed and maximal patterns over the steps of minsup."""

    def run(spark, d):
        frame = nodes(spark, d)
        return spark.createDataFrame([(p, *counted(miners.mine_eager(frame, minsup(spark, d, p), max_size=3, **kw))) for p in steps], LADDER)

    query(name, " UNION ALL ".join(f"SELECT * FROM ({sql(p)} SELECT {p} AS minsup, {COUNTS} FROM flagged)" for p in steps))(run)


def dom(spark, d) -> DataFrame:
    return stage(sources.page_trees(spark, d), "dom")


NAV3, DOM3 = (lambda p: f"{NAV_SQL}, {O.small_patterns(p)}"), (lambda p: f"{DOM_SQL}, {O.small_patterns(f'(SELECT (count(*) * {p} + 99) // 100 FROM pages)')}")


def page_minsup(spark, d, percent: int) -> int:
    return -(-spark.read.parquet(f"{d}/pages.parquet").count() * percent // 100)


ladder("ladder_star", lambda p: STAR3.format(p=p), star, (60, 50, 40, 30, 20), order_minsup, roots=set(STAR_ROOTS))
ladder("ladder_nav", NAV3, lambda spark, d: stage(sources.navigation(spark, d), "nav"), (800, 600, 500, 400, 300), lambda spark, d, p: p)
ladder("ladder_dom", DOM3, dom, (400, 300, 200, 150, 100), page_minsup, few_copies=True)


def distribution_sql(flagged: str) -> str:
    return flagged + TARGETS + " SELECT target, k, count(*) AS n, max(support) AS best FROM tg GROUP BY ROLLUP (target, k)"


@query("distribution_nav", distribution_sql(NAV3(300)))
def distribution_nav(spark, d):
    return result.distribution(miners.mine_eager(nav(spark, d), 300, max_size=3).result())


@query("distribution_dom", distribution_sql(DOM3(100)))
def distribution_dom(spark, d):
    return result.distribution(miners.mine_eager(dom(spark, d), page_minsup(spark, d, 100), max_size=3, few_copies=True).result())


@query("growing_tree", " UNION ALL ".join(f"SELECT * FROM (WITH {O.star(t)}, {O.star_pairs(STAR_ROOTS)}, {O.small_patterns('(SELECT (count(*) + 4) // 5 FROM orders)', STAR_ROOTS)} SELECT {t} AS tenths, (SELECT count(*) FROM nodes) AS n_nodes, count(*) AS n_frequent FROM frequent)" for t in (4, 7, 10)))
def growing_tree(spark, d):
    """Frequent patterns of a glued tree that grows by customers, at one minsup; ``bench.py --experiments`` takes the times.

    Only labels below orders can be under the roots asked for, so equal orders are glued once, with a weight; the nodes
    above them are counted where they are. Trees are made once, with a weight for each size.
    """
    steps = (4, 7, 10)
    weight = {t: F.sum(F.when(F.lit(t == 10) | (F.col("tenth") < t), F.col("w"))).alias(f"w{t}") for t in steps}
    shapes = sources.order_shapes(spark, d, (F.col("o_custkey") % 10).alias("tenth")).groupBy("status", "prio", "every").agg(*weight.values())
    trees = stage(sources.shape_trees(shapes), "orders")
    minsup, above, rows = order_minsup(spark, d, 20), sources.above_orders(spark, d, steps), []
    for t in steps:
        some = trees.withColumn("w", F.col(f"w{t}")).where("w IS NOT NULL").drop(*(f"w{k}" for k in steps))
        nodes = stage(encode.glue(some), "glued")
        got = miners.mine_frequent(nodes, minsup, max_size=3, roots=set(STAR_ROOTS), few_copies=True)
        below = nodes.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("n")).first()["n"]
        rows.append((t, below + above[t], got.counters.freq))
    return spark.createDataFrame(rows, "tenths int, n_nodes long, n_frequent long")


def forest_sql(keep: int) -> str:
    return f"SELECT * FROM ({encoded(O.navigation_edges(*NAV, keep=keep))}, {O.small_patterns(200)} SELECT {keep} AS percent, (SELECT count(DISTINCT tree_id) FROM nodes) AS n_trees, {COUNTS} FROM flagged)"


@query("growing_forest", " UNION ALL ".join(map(forest_sql, (40, 70, 100))))
def growing_forest(spark, d):
    """Patterns of random samples of navigation trees, at one minsup."""
    rows = []
    for keep in (40, 70, 100):
        nodes = stage(sources.navigation(spark, d, keep=keep), "sample")
        rows.append((keep, nodes.where("level = 0").count(), *counted(miners.mine_eager(nodes, 200, max_size=3))))
    return spark.createDataFrame(rows, "percent int, n_trees long, n_frequent long, n_closed long, n_maximal long")


@query("result_hierarchy", STAR3.format(p=40) + " SELECT DISTINCT p AS smaller, q AS larger FROM inside JOIN flagged f ON f.code = p AND f.is_closed")
def result_hierarchy(spark, d):
    codes = star3(miners.mine_eager, spark, d, 40).codes("closed")
    return spark.createDataFrame(result.hierarchy(codes), "smaller string, larger string")


@query("implied_patterns", STAR3.format(p=40) + " SELECT count(*) AS implied, count(*) AS frequent FROM frequent")
def implied_patterns(spark, d):
    r = star3(miners.mine_eager, spark, d, 40)
    implied = {c for c in result.implied(r.codes("maximal")) if c.split("(")[0] in STAR_ROOTS}
    return spark.createDataFrame([(len(implied), len(r.codes()))], "implied long, frequent long")


# streams: the batch form of the windows; tests run the streaming form


def events(spark, d) -> DataFrame:
    return spark.read.parquet(f"{d}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def window_sql(size: int, slide: int) -> str:
    n = size // slide
    return f"""WITH e AS (SELECT epoch_us(ts::TIMESTAMP) // 1000000 AS s, event_type FROM events), w AS (SELECT (s // {slide} - i) * {slide} AS start_s, event_type FROM e, range({n}) r(i))
    SELECT start_s, event_type, count(*) AS n FROM w GROUP BY start_s, event_type"""


@query("window_tumbling", window_sql(86_400, 86_400))
def window_tumbling(spark, d):
    return sessions.windowed(events(spark, d), "1 day").select(F.unix_seconds("start").alias("start_s"), "event_type", "n")


@query("window_sliding", window_sql(86_400, 21_600))
def window_sliding(spark, d):
    return sessions.windowed(events(spark, d), "1 day", "6 hours").select(F.unix_seconds("start").alias("start_s"), "event_type", "n")


@query("window_session", """WITH e AS (SELECT user_id, epoch_us(ts::TIMESTAMP) AS t FROM events), c AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) < 43200000000 THEN 0 ELSE 1 END AS cut FROM e),
    s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM c)
    SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, k""")
def window_session(spark, d):
    return sessions.sessions(events(spark, d), "12 hours").select("user_id", F.unix_micros("start").alias("start_us"), F.col("n").cast("long").alias("n"))


@query("session_pair_counts", f"""{encoded(O.session_edges(STAGES, 12 * 3600))}
    SELECT label AS anc_label, '' AS desc_label, count(*) AS support FROM nodes GROUP BY label
    UNION ALL SELECT al, dl, count(DISTINCT (t, a)) FROM pairs GROUP BY al, dl""")
def session_pair_counts(spark, d):
    pairs = sessions.session_pairs(sessions.sessions(events(spark, d), "12 hours"))
    return pairs.groupBy("anc_label", "desc_label").agg(F.sum("support").alias("support"))


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Closed and maximal patterns of the star hierarchy, three nodes at most."""
    return postfilter_k3_star(spark, d)
