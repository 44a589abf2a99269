import random

from pyspark.sql import functions as F

from canopy.forest.encode import from_patterns
from canopy.forest.lists import build
from canopy.match import occlist, sibling, structural, support, twig
from canopy.pattern.codec import forest, parse
from canopy.pattern.morph import maps
from tests.oracle import brute
from tests.test_pattern import random_tree


def test_chain_and_sibling_constraint(spark):
    nodes = from_patterns(spark, forest("A(B(C))"))
    assert support.root(nodes, "A(B(C))") == 1 and support.root(nodes, "A(C)") == 1
    assert support.root(nodes, "A(B,C)") == 0 and support.root(nodes, "A(B,C)", "hom") == 1


def test_worked_example_of_coverage(spark):
    nodes = from_patterns(spark, forest("A(A(B,C),A(B,C))"))
    occ = twig.find(nodes, "A(B,C)", what="occurrences")
    assert occ.count() == 6 and support.root(nodes, "A(B,C)") == 3
    outer = twig.find(nodes, "A(A(B,C))", what="occurrences")
    assert outer.count() == 2 and support.root(nodes, "A(A(B,C))") == 1
    images = outer.select("b0").union(outer.select("b1")).distinct()
    assert images.count() == 3


def test_siblings_of_one_label(spark):
    nodes = from_patterns(spark, forest("A(B,B); A(B)"))
    s = twig.find(nodes, "A(B,B)", what="counts").first()
    assert (s["root_support"], s["occ_support"], s["doc_support"]) == (1, 2, 1)


def test_random_matches_against_brute_force(spark):
    rng = random.Random(4)
    trees = [random_tree(rng, rng.randint(3, 8), "abc") for _ in range(6)]
    nodes = from_patterns(spark, trees).cache()
    for _ in range(6):
        p = random_tree(rng, rng.randint(2, 4), "abc")
        assert twig.occurrences(nodes, p).count() == sum(len(set(brute.embeddings(p, t))) for t in trees)
        for kind in ("hom", "iso"):
            assert twig.occurrences(nodes, p, kind).count() == sum(len(set(maps(p, t, kind))) for t in trees)
            assert twig.roots(nodes, p, kind).count() == sum(len({m[0] for m in maps(p, t, kind)}) for t in trees)
        hom = twig.occurrences(nodes, p, "hom")
        assert sibling.keep_embedded(hom, p).count() == twig.occurrences(nodes, p).count()
        got = occlist.lists_of(hom, p)
        assert got.count() == sum(x.count() for x in twig.reduced_lists(nodes, p))


def test_child_edges_in_queries(spark):
    nodes = from_patterns(spark, forest("A(B(C))"))
    assert twig.find(nodes, "A(/C)").count() == 0 and twig.find(nodes, "A(//C)").count() == 1 and twig.find(nodes, "A/B/C", "hom").count() == 1


def test_conflict_free(spark):
    nodes = from_patterns(spark, forest("A(B(C),D); A(D,B)"))
    above = sibling.nested_labels(nodes)
    assert sibling.conflict_free(parse("A(B,D)"), above) and not sibling.conflict_free(parse("A(B,C)"), above) and not sibling.conflict_free(parse("A(D,D)"), above)
    assert twig.roots(nodes, parse("A(B,D)"), "emb", above).count() == 2


def test_structural_joins_agree(spark):
    nodes = from_patterns(spark, forest("A(B(A,B),B); B(A)"))
    a, b = structural.ancestor_pairs(nodes), structural.ancestor_pairs(nodes, how="range").select("tree_id", "a", "a_end", "a_label", "d", "d_end", "d_label")
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and structural.plan_join(nodes) == "equi"
    only = structural.ancestor_pairs(nodes, below=spark.createDataFrame([("A",)], "label string"))
    assert only.count() == a.where("d_label = 'A'").count()


def test_bitmaps(spark):
    nodes = from_patterns(spark, [parse("A(B)")] * 5 + [parse("A(C)")] * 3 + [parse("A(B,C)")] * 2)
    lists = build(nodes.where("label = 'A'"))
    rows = occlist.union_all([twig.roots(nodes, f"A({x})").withColumn("x", F.lit(x)).withColumn("label", F.lit("A")) for x in "BC"])
    bits = occlist.to_bitmaps(rows, lists, ["x"])
    assert {r["x"]: r["n"] for r in occlist.bit_count(bits, ["x"]).collect()} == {"B": 7, "C": 5}
    assert occlist.bit_count(occlist.bit_and(bits, ["label"], 2), ["label"]).first()["n"] == 2
    assert occlist.bit_count(occlist.bit_or(bits, ["label"]), ["label"]).first()["n"] == 10
    back = occlist.unpack(bits, lists, ["x"])
    assert back.select("x", "tree_id", "begin").exceptAll(rows.select("x", "tree_id", "begin")).isEmpty() and back.count() == 12
