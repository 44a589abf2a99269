import random

from pyspark.sql import functions as F

from canopy.forest import encode, lists, navigate, sources, stats
from canopy.forest.compress import canonical_tree
from canopy.pattern.codec import forest, parse
from tests.conftest import SF
from tests.test_pattern import random_tree

CODE = ["tree_id", "begin", "end", "level", "parent", "label", "anc"]


def rows(df):
    return sorted(tuple(map(str, r)) for r in df.select(CODE).collect())


def test_encode_edges_matches_hand_coding(spark):
    rng = random.Random(5)
    trees = [random_tree(rng, n) for n in (1, 5, 9)]
    edges = [(100 * t + n, 100 * t + p.parent[n] if n else None, p.labels[n]) for t, p in enumerate(trees) for n in range(p.size)]
    got = encode.encode_edges(spark.createDataFrame(edges, "id long, parent long, label string").repartition(3))
    want = encode.from_patterns(spark, trees).withColumn("tree_id", F.col("tree_id") * 100)
    assert rows(got) == rows(want)


def test_cycles_and_lost_parents_are_left_out(spark):
    edges = spark.createDataFrame([(1, None, "a"), (2, 1, "b"), (3, 9, "c"), (4, 5, "d"), (5, 4, "e")], "id long, parent long, label string")
    assert encode.encode_edges(edges).count() == 2


def test_glue_and_split(spark):
    nodes = encode.from_patterns(spark, forest("A(B,C(D)); E; F(G(H))"))
    glued = encode.glue(nodes)
    flat = sorted((r["begin"], r["end"], r["label"]) for r in glued.collect())
    assert [x for _, _, x in flat] == list("ABCDEFGH") and flat[0][:2] == (1, 8) and flat[-1][1] == 14 and glued.where("level = 1").count() == 3
    back = encode.split(glued)
    drop = lambda df: sorted(tuple(map(str, r)) for r in df.drop("tree_id").select(CODE[1:]).collect())
    assert drop(back) == drop(nodes)


def test_numbering_does_not_depend_on_partitions(spark):
    a = sources.star(spark, SF)
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", 7)
    try:
        b = sources.star(spark, SF)
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def test_lists_and_statistics(spark):
    nodes = encode.from_patterns(spark, forest("A(B(A),C); A(B)"))
    got = {(r["label"], r["ord"]): (r["tree_id"], r["begin"]) for r in lists.build(nodes).collect()}
    assert got["A", 0] == (0, 0) and got["A", 2][0] == 1 and len(got) == 6
    s = stats.describe(nodes).first()
    assert (s["n_nodes"], s["n_trees"], s["n_labels"], s["max_depth"], s["n_paths"], s["n_recursive"]) == (6, 2, 3, 2, 4, 1)
    assert [r["label"] for r in lists.frequent_labels(nodes, 3).collect()] == ["A"]


def test_navigation(spark):
    nodes = encode.from_patterns(spark, forest("A(B(C,D),E)"))
    at = {r["label"]: r["begin"] for r in nodes.collect()}
    one = lambda x: nodes.where(F.col("label") == x)
    labels = lambda df: sorted(r["label"] for r in df.collect())
    assert labels(navigate.children(nodes, one("B"))) == ["C", "D"] and labels(navigate.parent_of(nodes, one("C"))) == ["B"]
    assert labels(navigate.ancestors_of(nodes, one("C"))) == ["A", "B"] and labels(navigate.descendants_of(nodes, one("A"))) == ["B", "C", "D", "E"]
    assert labels(navigate.siblings_of(nodes, one("B"))) == ["E"] and labels(navigate.subtree(nodes, 0, at["B"])) == ["B", "C", "D"]
    pair = spark.createDataFrame([(0, at["C"], at["D"]), (0, at["C"], at["E"])], "tree_id long, a long, b long")
    assert sorted(r["lca"] for r in navigate.lowest_common_ancestor(nodes, pair).collect()) == [at["A"], at["B"]]


def test_dom_fold():
    assert sources.fold("<html><p>a<b>x<br>y<p>z</b></div></html>") == [(-1, "html"), (0, "p"), (1, "b"), (2, "br"), (2, "p")]
    assert sources.fold('<div class="ad x"><img/></div>', classes=True) == [(-1, "div.ad"), (0, "img")]
    assert sources.fold("") == []
    assert [r[:3] for r in sources.coded([(-1, "a"), (0, "b"), (-1, "c")])] == [(0, 3, 0), (1, 2, 1), (4, 5, 0)]
    assert sources.only([(-1, "a"), (0, "b"), (1, "c")], {"a", "c"}) == [(-1, "a"), (0, "c")]
    assert sources.without_repeats([(-1, "a"), (0, "b"), (0, "b"), (0, "c")]) == [(-1, "a"), (0, "b"), (0, "c")]


def test_canonical_tree_ignores_order():
    def coded(text):
        return [(b, e, x) for b, e, _, _, x, _ in sources.coded([(p, x) for p, x in zip(parse(text).parent, parse(text).labels)])]

    a, b = canonical_tree(coded("A(C(D),B)")), canonical_tree(coded("A(B,C(D))"))
    assert a == b and a[0] == "A(B,C(D))" and sorted(a[1]) == sorted(coded("A(B,C(D))"))


def test_sources_make_trees(spark):
    for make in (sources.star, sources.supply, sources.navigation, sources.dialogue, sources.text, sources.dom):
        nodes = make(spark, SF)
        bad = nodes.where("end <= begin OR size(anc) != level OR (level > 0 AND parent != anc[level - 1]) OR label IS NULL")
        assert bad.isEmpty() and not nodes.isEmpty()
