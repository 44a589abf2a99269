import random

import pytest

from canopy.forest.encode import from_patterns, glue
from canopy.mine import closed, measure, miners, result
from canopy.mine.engine import TooMany
from canopy.mine.induced import mine_induced
from canopy.mine.lists import mine_lists
from canopy.mine.onestep import mine_onestep
from canopy.mine.scopejoin import mine_occurrence_join
from canopy.pattern.codec import forest, show
from tests.oracle import brute
from tests.test_pattern import random_tree

LOST_COUSIN = "A(c,d(b),e(b)); A(c,d(b),e(b))"
LOST_CHILD = "A(b(b(c,d,f),d(f),e(g)),e,g); A(b(c,d(f)),e(g))"
RETAINED = "R(A(B),A(B,C)); R(A(B,C)); R(A(B,C))"


def flags(r):
    return {x["code"]: (x["support"], x["is_closed"], x["is_maximal"]) for x in r.result().collect()}


@pytest.fixture(scope="module")
def made(spark):
    cache = {}

    def make(text):
        if text not in cache:
            cache[text] = from_patterns(spark, forest(text)).repartition(2).cache()
        return cache[text]

    return make


def test_coverage_example(made):
    text = "A(A(B,C),A(B,C))"
    r = miners.mine_postfilter(made(text), 1)
    assert flags(r) == brute.mine(text, 1)
    assert len(r.codes()) == 34 and r.codes("closed") == {text}
    assert closed.by_support([m for m in r.search.reported()])  # the naive rule keeps others too
    assert "A(B,C)" in {r.search.code(r.search.mined[k]) for k in closed.by_support(r.search.reported())}


def test_retained_example(made):
    assert miners.mine_eager(made(RETAINED), 3).codes("closed") == {"R(A(B,C))"}
    assert miners.mine_eager(made(RETAINED), 3, witness="retained").codes("closed") == {"R(A(B,C))", "A(B)"}


def test_pruning_rules_on_the_cousin_example(made):
    whole = {"A(c,d(b),e(b))"}
    for rule in ("uniform", "none", "filters"):
        r = miners.mine_pruned(made(LOST_COUSIN), 2, rule=rule)
        assert r.codes("closed") == r.codes("maximal") == whole
    assert miners.mine_pruned(made(LOST_COUSIN), 2, rule="definition").codes("maximal") != whole


def test_pruning_rules_on_the_child_example(made):
    nodes, lost = made(LOST_CHILD), "A(c,d(f),e(g))"
    want = brute.mine(LOST_CHILD, 2)
    closed_codes = {k for k, v in want.items() if v[1]}
    assert len(want) == 72 and len(closed_codes) == 6 and lost in closed_codes
    r = miners.mine_pruned(nodes, 2)
    eager = miners.mine_eager(nodes, 2)
    assert r.codes("closed") == eager.codes("closed") == closed_codes
    assert r.counters.computed < eager.counters.computed
    for rule in ("definition", "filters"):
        assert lost not in miners.mine_pruned(nodes, 2, rule=rule).codes("closed")


def test_shortcut_example(made):
    text = "A(c(b),c(b)); A(c(b),c(b))"
    r = miners.mine_pruned(made(text), 2)
    assert r.codes("maximal") == {"A(c(b),c(b))"} and len(miners.mine_frequent(made(text), 2).codes()) == 10


@pytest.mark.parametrize("seed", range(4))
def test_miners_against_brute_force(spark, seed):
    rng = random.Random(seed)
    trees = [random_tree(rng, rng.randint(3, 7), "abc") for _ in range(rng.randint(1, 3))]
    minsup = rng.randint(1, 2)
    nodes = from_patterns(spark, trees).repartition(2).cache()
    want = brute.mine(trees, minsup)
    post, eager, pruned = miners.mine_postfilter(nodes, minsup), miners.mine_eager(nodes, minsup), miners.mine_pruned(nodes, minsup)
    assert flags(post) == flags(eager) == want
    assert {k for k in want if want[k][1]} == pruned.codes("closed") and {k for k in want if want[k][2]} == pruned.codes("maximal")
    assert pruned.counters.computed <= eager.counters.computed == post.counters.computed
    plain = miners.mine_frequent(nodes, minsup, compress=False)
    assert {k: v[0] for k, v in want.items()} == {k: v[0] for k, v in flags(plain).items()}
    assert mine_lists(nodes, minsup, max_size=3).codes() == mine_occurrence_join(nodes, minsup, max_size=3).codes() == {c for c in want if len(c.replace("(", ",").split(",")) <= 3}
    assert miners.mine_frequent(nodes, minsup, apriori=True).codes() == set(want)
    if seed == 0:
        depth = miners.mine_pruned(nodes, minsup, label_order="depth")
        assert depth.codes("closed") == pruned.codes("closed")
        glued = miners.mine_postfilter(glue(nodes), minsup)
        assert flags(glued) == want


def test_root_support_is_not_cut_at_leaves(made):
    deep = "A(" * 10 + "B" + ")" * 10
    assert "A(B)" in miners.mine_frequent(made(deep), 10, max_size=2).codes()


def test_no_pattern_spans_trees(made):
    assert miners.mine_frequent(made("A(B); C(D)"), 1).codes() == {"A(B)", "C(D)"}


def test_child_surrogate_by_depth(made):
    # every C below A has a B between, always in the same way
    nodes = made("A(B(C),D); A(B(C),D)")
    r = miners.mine_pruned(nodes, 2)
    pruned = {show(m.pattern) for m in r.search.mined.values() if m.pruned_by}
    assert "A(C)" in pruned and r.codes("closed") == {"A(B(C),D)"}


def test_child_joins_of_a_spared_pattern_are_not_computed(made):
    # A(B) stands for A(C) at once, so only the cousin joins of A(C) are needed to see that
    nodes = made("A(B(C)); A(B(C))")
    pruned, post = miners.mine_pruned(nodes, 2, label_order="depth"), miners.mine_postfilter(nodes, 2, label_order="depth")
    assert pruned.counters.computed < post.counters.computed
    assert all(pruned.codes(which) == post.codes(which) for which in ("closed", "maximal"))


def test_document_and_occurrence_support(made):
    nodes = made("A(B,B); A(B)")
    doc = {r["code"]: r["support"] for r in miners.mine_frequent(nodes, 1, support="document").result().collect()}
    occ = {r["code"]: r["support"] for r in miners.mine_frequent(nodes, 1, support="occurrence").result().collect()}
    assert doc == {"A(B)": 2, "A(B,B)": 1} and occ == {"A(B)": 3, "A(B,B)": 2}


def test_induced(made):
    nodes = made("A(B(C)); A(B(C)); A(X(C))")
    r = mine_induced(nodes, 2)
    assert r.codes() == {"A(B)", "B(C)", "A(B(C))"} and r.codes("maximal") == {"A(B(C))"}
    assert r.codes() <= miners.mine_frequent(nodes, 2).codes()
    assert mine_induced(nodes, 2, support="document").codes("closed") == {"A(B(C))"}


def test_onestep(made):
    got = mine_onestep(made(RETAINED), 3)
    assert got.maximal == {"R(A(B,C))"} and got.closed >= {"R(A(B,C))"} and got.generated > got.distinct > 0


def test_limits_and_constraints(made):
    with pytest.raises(TooMany) as e:
        miners.mine_frequent(made(LOST_CHILD), 1, max_candidates=5)
    assert e.value.counters.computed > 0 and not e.value.counters.complete
    with pytest.raises(TooMany):
        miners.mine_frequent(made(LOST_CHILD), 1, max_occurrences=5)
    got = {r["code"] for r in miners.mine_constrained(made(LOST_COUSIN), 2, forbidden={"c"}, required={"b"}, max_depth=1, root="A").collect()}
    assert got == {"A(b)", "A(b,b)", "A(b,d)", "A(b,e)"}
    assert miners.threshold(made(LOST_COUSIN), 0.5, "A") == 1


def test_reading_results(made, tmp_path):
    r = miners.mine_eager(made(LOST_COUSIN), 2, compress=False)
    p = r.patterns()
    assert result.compression(p).first().asDict() == {"n_frequent": 31, "n_closed": 1, "n_maximal": 1}
    assert result.implied(r.codes("maximal")) >= r.codes()
    assert result.top(p, 2).groupBy("k").count().agg({"count": "max"}).first()[0] == 2
    assert ("A(b)", "A(b,b)") in result.hierarchy({"A(b)", "A(b,b)", "A(b,b,c)"})
    assert r.occurrence_lists().where("pos = 0").groupBy("pattern_id").count().agg({"count": "min"}).first()[0] >= 2
    result.write(r, str(tmp_path))
    assert sorted(x.name for x in tmp_path.iterdir()) == ["counters", "olist", "patterns", "result"]
    assert result.to_dot(["A(b)"]).startswith("digraph")


@pytest.mark.parametrize("lists", ["rows", "bitmap"])
def test_list_strategy_against_brute_force(made, lists):
    """Siblings that may meet on a path, recursive labels, and pruning, without stored occurrences."""
    text = "A(b(c),b(b(c)),d); A(b(c),d)"
    want, kw = brute.mine(text, 2), {"strategy": "lists", "lists": lists}
    eager = miners.mine_eager(made(text), 2, **kw)
    assert flags(eager) == want and eager.counters.stored_bytes > 0
    pruned = miners.mine_pruned(made(text), 2, **kw)
    assert pruned.codes("closed") == eager.codes("closed") and pruned.codes("maximal") == eager.codes("maximal")
    got = eager.occurrence_lists().count() if not eager.search.options.compress else 0
    assert got == 0 and pruned.counters.computed <= eager.counters.computed


def test_lists_hold_no_occurrences(made):
    """Ten equal siblings have ninety pairs, but ten images for each node."""
    nodes = made("A(" + ",".join("B" * 10) + ")")
    tuples, lists = (miners.mine_frequent(nodes, 1, max_size=3, strategy=s) for s in ("tuples", "lists"))
    assert flags(tuples).keys() == flags(lists).keys() == {"A(B)", "A(B,B)"}
    assert tuples.counters.occ_rows == 100 and lists.counters.occ_rows == 11 + 21


def test_strategies_are_checked(made):
    with pytest.raises(ValueError):
        miners.mine_frequent(made("A(B)"), 1, strategy="trees")
    with pytest.raises(ValueError):
        miners.mine_frequent(made("A(B)"), 1, strategy="lists", support="occurrence")
    with pytest.raises(ValueError):
        miners.mine_pruned(made("A(B)"), 1, max_size=3)
    assert miners.mine_pruned(made("A(B)"), 1, max_size=3, allow_boundary=True).codes() == {"A(B)"}


def test_measures(spark, made):
    measure.reset_peak(spark)
    rows = [measure.row("w", m(made(LOST_COUSIN), 2), measure.peak_mb(spark)) for m in (miners.mine_eager, miners.mine_pruned)]
    assert rows[0]["peak_mb"] > 0 and rows[0]["computed"] >= rows[1]["computed"]
    (ratio,) = measure.ratios(rows, "pruned-uniform")
    assert ratio["miner"] == "eager" and ratio["computed"] >= 1
    assert measure.frame(spark, rows).count() == 2


def test_empty_forest(spark):
    nodes = from_patterns(spark, []).cache()
    for m in (miners.mine_postfilter, miners.mine_eager, miners.mine_pruned):
        assert m(nodes, 1).codes() == set()


def test_pruned_lists_build_and_ask_once(made, monkeypatch):
    """F8: no pattern's occurrences are built twice, and no pair of a level is asked about twice."""
    from canopy.mine import liststore, surrogate

    built, asked, tuples, uniform = [], [], liststore.tuples, surrogate.uniform
    monkeypatch.setattr(liststore.ListSearch, "join", lambda self, size, new, join=liststore.ListSearch.join: (built.append(None), join(self, size, new), built.append(0))[1])

    def counted(lists, patterns, *more):
        if not built or built[-1] is not None:  # not inside a join
            built.extend(("p", k) for k in patterns)
        return tuples(lists, patterns, *more)

    monkeypatch.setattr(liststore, "tuples", counted)
    monkeypatch.setattr(surrogate, "uniform", lambda search, size, pairs, followers: (asked.extend(p.q for p in pairs), uniform(search, size, pairs, followers))[1])
    text = "A(L(f,g),p,s); A(L(f,h),p,s)"
    pruned = miners.mine_pruned(made(text), 2, strategy="lists", lists="bitmap", label_order="depth")
    post = miners.mine_postfilter(made(text), 2, label_order="depth")
    ids = [b for b in built if isinstance(b, tuple)]
    assert ids and len(ids) == len(set(ids)) and len(asked) == len(set(asked))
    assert all(pruned.codes(which) == post.codes(which) for which in ("closed", "maximal"))


def test_large_lists_are_not_broadcast(made, monkeypatch):
    """F8: lists above the bound are dealt out by key, with the same result."""
    from canopy.mine import liststore

    nodes, kw = made("A(b(c),b); A(b(c))"), {"strategy": "lists", "max_size": 3}
    near = flags(miners.mine_eager(nodes, 2, **kw))
    monkeypatch.setattr(liststore, "NEAR", 0)
    assert flags(miners.mine_eager(nodes, 2, **kw)) == near
