"""Equal trees given once, with a weight, and the budget of stored rows."""

from __future__ import annotations

import random

import duckdb
import pytest

from canopy import queries
from canopy.forest import encode, sources
from canopy.forest.encode import from_patterns
from canopy.mine import miners
from canopy.pattern.codec import parse
from tests.conftest import SF


def test_order_trees_hold_what_the_star_holds(spark):
    whole = {r["label"]: r["count"] for r in sources.star(spark, SF).groupBy("label").count().collect()}
    trees = sources.order_trees(spark, SF)
    got = {r["label"]: r["n"] for r in trees.groupBy("label").agg({"w": "sum"}).withColumnRenamed("sum(w)", "n").collect()}
    assert got == {k: n for k, n in whole.items() if k not in ("region", "nation", "customer") and not k.startswith("seg=")}
    want = duckdb.connect().execute(f"SELECT count(*) FROM (SELECT DISTINCT status, prio, x FROM (SELECT o_orderstatus AS status, o_orderpriority AS prio, (SELECT list_sort(list(l_returnflag || l_linestatus)) FROM '{SF}/lineitem.parquet' WHERE l_orderkey = o_orderkey) AS x FROM '{SF}/orders.parquet'))").fetchone()
    assert trees.where("level = 0").count() == want[0]


def test_many_kinds_of_lines_are_gathered(spark, monkeypatch):
    few = sources.order_trees(spark, SF).groupBy("label").agg({"w": "sum", "tree_id": "count"}).collect()
    monkeypatch.setattr(sources, "MOST_KINDS", 1)
    assert sorted(sources.order_trees(spark, SF).groupBy("label").agg({"w": "sum", "tree_id": "count"}).collect()) == sorted(few)


def test_the_budget_counts_stored_rows(spark):
    """Forty equal trees are stored once, so their occurrences are no more than one tree's."""
    from canopy.pattern.codec import parse

    nodes = from_patterns(spark, [parse("A(B,C)")] * 40)
    assert miners.mine_frequent(nodes, 40, max_occurrences=20).counters.occ_rows > 20


def test_lines_paths_are_merged(spark):
    paths = sources.line_paths(spark, SF)
    assert paths.where("level = 0").count() < 100
    assert queries.path_run(miners.mine_eager, spark, SF).codes("closed")


def test_a_glued_tree_keeps_weights(spark):
    """growing_tree glues distinct orders, which stand for all."""
    trees = sources.order_trees(spark, SF)
    glued = encode.glue(trees)
    assert glued.agg({"w": "sum"}).first()[0] == trees.agg({"w": "sum"}).first()[0] > trees.count()
    kw = {"max_size": 3, "roots": set(queries.STAR_ROOTS)}
    assert miners.mine_frequent(glued, 600, **kw).codes() == miners.mine_frequent(sources.star(spark, SF), 600, **kw).codes()


def test_growing_tree_counts_all_nodes(spark):
    got = {r["tenths"]: r["n_nodes"] for r in queries.growing_tree(spark, SF).collect()}
    assert got == {t: sources.star(spark, SF, t).count() for t in (4, 7, 10)}


def test_text_trees_hold_what_texts_hold(spark):
    """documents of equal lines are mined once, and only those that hold the required labels."""
    whole = {tuple(r)[:2]: r["count"] for r in sources.text(spark, SF).groupBy("label", "level").count().collect()}
    trees = sources.text_trees(spark, SF)
    assert {(r["label"], r["level"]): r["n"] for r in trees.groupBy("label", "level").agg({"w": "sum"}).withColumnRenamed("sum(w)", "n").collect()} == whole
    some = sources.text_trees(spark, SF, {"toxic=1"}).where("label = 'toxic=1'").agg({"w": "sum"}).first()[0]
    assert some == sources.text_trees(spark, SF, {"toxic=1"}).where("level = 0").agg({"w": "sum"}).first()[0] == whole["toxic=1", 1]


def test_required_labels_and_copies_change_no_row(spark):
    nodes = from_patterns(spark, [parse(x) for x in ("D(L(s,s,s,t),L(s,s,s,t),L(s,s,s,t),q)", "D(L(s,t),L(s),q)", "D(L(t,t,t),L(s))")])
    kw = {"max_size": 3, "roots": {"D"}}
    whole = miners.mine_eager(nodes, 2, **kw)
    want = {tuple(r) for r in whole.result().where("code LIKE '%q%'").select("code", "support", "is_closed", "is_maximal").collect()}
    got = miners.mine_constrained(nodes, 2, required={"q"}, root="D", max_size=3)
    assert {tuple(r) for r in got.select("code", "support", "is_closed", "is_maximal").collect()} == want
    few = miners.mine_eager(nodes, 2, few_copies=True, **kw)
    assert sorted(map(tuple, few.result().collect())) == sorted(map(tuple, whole.result().collect()))
    assert few.counters.occ_rows < whole.counters.occ_rows


def test_page_trees_hold_what_pages_hold(spark):
    """equal pages are mined once."""
    whole = {r["label"]: r["count"] for r in sources.dom(spark, SF).groupBy("label").count().collect()}
    trees = sources.page_trees(spark, SF)
    assert {r["label"]: r["n"] for r in trees.groupBy("label").agg({"w": "sum"}).withColumnRenamed("sum(w)", "n").collect()} == whole
    assert trees.where("level = 0").count() < sources.dom(spark, SF).where("level = 0").count()


def forest_of_copies(spark, roots: tuple[str, ...]):
    """Trees whose roots stand in each other and whose siblings are often equal, from a fixed seed."""
    draw = random.Random(7)

    def tree(level: int) -> str:
        label = draw.choice(roots if level < 2 else (*roots, "x", "y"))
        inner = [tree(level + 1) for _ in range(draw.randint(0, 2) if level else 2)] if level < 3 else []
        inner = [x for x in inner for _ in range(draw.choice((1, 1, 2, 4)))]
        return f"{label}({','.join(inner)})" if inner else label

    return from_patterns(spark, [parse(tree(0)) for _ in range(12)])


def test_few_copies_of_nested_roots(spark):
    """equal subtrees are cut to what a pattern can use although roots stand in them; their nodes count for all."""
    nodes = forest_of_copies(spark, ("A", "B"))
    for minsup in (4, 12):
        whole = miners.mine_eager(nodes, minsup, max_size=3, compress=False)
        few = miners.mine_eager(nodes, minsup, max_size=3, few_copies=True)
        assert sorted(map(tuple, few.result().collect())) == sorted(map(tuple, whole.result().collect()))
        assert few.search.rows_held < whole.search.rows_held / 2
    lists = miners.mine_eager(nodes, 4, max_size=3, few_copies=True, strategy="lists")
    assert sorted(map(tuple, lists.result().collect())) == sorted(map(tuple, miners.mine_eager(nodes, 4, max_size=3).result().collect()))
    with pytest.raises(ValueError):
        miners.mine_pruned(nodes, 4, few_copies=True)


def test_glued_orders_of_many_lines_are_cut(spark):
    """what a glued tree stores does not grow with the lines of an order, or with orders that differ in their number."""
    order = lambda n: parse("order(" + ",".join(["line(flag=A,ls=F)"] * n) + ",status=F)")
    kw = {"max_size": 3, "roots": {"order", "line"}, "few_copies": True}
    small, large = ([order(n) for n in k] for k in ((2, 2, 2, 2), (2, 20, 30, 40)))
    few, many = (miners.mine_frequent(encode.glue(from_patterns(spark, x)), 4, **kw) for x in (small, large))
    assert few.codes() == many.codes() and few.search.rows_held == many.search.rows_held
    got = {r["code"]: r["support"] for r in many.result().collect()}
    assert got["line(flag=A,ls=F)"] == 92 and got["order(line,line)"] == 4


def test_pages_of_many_equal_siblings(spark, tmp_path, monkeypatch):
    """what distribution_dom stores does not grow with the square of a page's siblings."""
    item = "<li><a></a></li>"
    html = [f"<html><body><ul>{item * n}</ul><div>{'<p></p>' * n}</div></body></html>" for n in (1, 60, 70, 80)]
    spark.createDataFrame(list(enumerate(html)), "page_id long, html string").write.parquet(str(tmp_path / "pages.parquet"))
    want = sorted(map(str, queries.distribution_dom(spark, str(tmp_path)).collect()))
    eager = miners.mine_eager
    monkeypatch.setattr(queries.miners, "mine_eager", lambda *a, **kw: eager(*a, **kw, max_occurrences=5000))
    assert sorted(map(str, queries.distribution_dom(spark, str(tmp_path)).collect())) == want
    whole = eager(sources.dom(spark, str(tmp_path)), 4, max_size=3, compress=False)
    assert sorted(map(str, queries.result.distribution(whole.result()).collect())) == want
