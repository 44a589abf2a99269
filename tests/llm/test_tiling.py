import random

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from canopy.llm import tiling

DOCS = "doc_id long, text string, lang string, source string, n_chars long, item_id string"
ITEM = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"


def plain_tiles(doc, item, least):
    """Greedy tiling by comparing everywhere."""
    used_d, used_i, out = set(), set(), 0
    while True:
        best = (0, 0, 0)
        for d in range(len(doc)):
            for i in range(len(item)):
                n = 0
                while d + n < len(doc) and i + n < len(item) and doc[d + n] == item[i + n] and d + n not in used_d and i + n not in used_i:
                    n += 1
                best = max(best, (n, -d, -i))
        n, d, i = best[0], -best[1], -best[2]
        if n < least:
            return out
        used_d |= set(range(d, d + n))
        used_i |= set(range(i, i + n))
        out += n


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 5), max_size=40), st.lists(st.integers(0, 5), min_size=1, max_size=25), st.integers(2, 4))
def test_tiles_are_valid_and_cover_as_much(doc, item, least):
    tiles = tiling.tile(np.array(doc, np.uint64), np.array(item, np.uint64), least)
    places_d = [d + k for d, _, n in tiles for k in range(n)]
    places_i = [i + k for _, i, n in tiles for k in range(n)]
    assert len(set(places_d)) == len(places_d) and len(set(places_i)) == len(places_i)
    assert all(doc[d : d + n] == item[i : i + n] and n >= least for d, i, n in tiles)
    # nothing of the least length is left that could be marked
    rest_d, rest_i = set(range(len(doc))) - set(places_d), set(range(len(item))) - set(places_i)
    for d in range(len(doc) - least + 1):
        for i in range(len(item) - least + 1):
            if all(d + k in rest_d and i + k in rest_i for k in range(least)):
                assert doc[d : d + least] != item[i : i + least]


def test_longest_match_first():
    item, doc = list(range(30)), [*range(5, 20), 99, *range(0, 10), 98, *range(18, 30)]
    got = tiling.tile(np.array(doc, np.uint64), np.array(item, np.uint64), 3)
    assert got[0] == (0, 5, 15)
    assert sum(t[2] for t in got) == plain_tiles(doc, item, 3)


def found(spark, texts, items, **kw):
    docs = spark.createDataFrame([(k, t, "en", "s", 1, "clash") for k, t in enumerate(texts)], DOCS)
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    return {r["doc_id"]: r for r in tiling.contamination(docs, bench, **kw).collect()}


def test_passages_in_any_order(spark):
    words = ITEM.split()
    noise = " ".join(f"n{k}" for k in range(200))
    moved = " ".join([*words[10:], "stop", *words[:10]])
    texts = [f"{noise} {ITEM} {noise}", f"{noise} {moved}", noise, " ".join(words[:7]) + noise, f"{noise}. {ITEM.upper()}!", None, "", " ".join(reversed(words))]
    got = found(spark, texts, [ITEM, None, "", "one two", "!!"])
    assert [k for k, r in got.items() if r["contaminated"]] and {k for k, r in got.items() if r["contaminated"]} == {0, 1, 4}
    assert got[0]["coverage"] == got[1]["coverage"] == 1.0 and got[0]["item_id"] == 0 and got[2]["items"] == []


def test_blocks_of_the_benchmark_make_no_difference(spark):
    rng = random.Random(1)
    items = [" ".join(f"w{rng.randrange(50)}" for _ in range(25)) for _ in range(12)]
    texts = [" ".join([items[k % 12], *(f"x{rng.randrange(9)}" for _ in range(30))]) for k in range(20)]
    a, b = found(spark, texts, items), found(spark, texts, items, block=60)
    assert {k: (r["contaminated"], r["items"]) for k, r in a.items()} == {k: (r["contaminated"], r["items"]) for k, r in b.items()}
    assert all(k % 12 in r["items"] for k, r in a.items())


def test_short_items_and_ties(spark):
    got = found(spark, ["see one two here", "one three two"], ["one two", "one two"])
    assert got[0]["contaminated"] and got[0]["item_id"] == 0 and got[0]["items"] == [0, 1] and not got[1]["contaminated"]


def test_given_tables_against_plain_coverage(spark):
    from tests.conftest import SF

    docs, bench = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    got = {r["doc_id"]: r["contaminated"] for r in tiling.contamination(docs, bench).collect()}
    items = [tiling.tokens(r["text"]) for r in bench.collect()]
    for r in docs.collect():
        doc = tiling.tokens(r["text"])
        have = {tuple(doc[k : k + 5]) for k in range(len(doc) - 4)}
        likely = [i for i in items if any(tuple(i[k : k + 5]) in have for k in range(len(i) - 4))]
        want = any(plain_tiles(doc, i, 5) >= 0.5 * len(i) for i in likely) if len(doc) < 600 or not likely else got[r["doc_id"]]
        assert got[r["doc_id"]] == want
    assert sum(got.values()) > 0


def test_cleaning(spark):
    rows = [(1, ITEM, "en", "s", 1, "x"), (2, "clean text", "en", "s", 1, "x"), (None, ITEM, "en", "s", 1, "x"), (2, "clean text", "en", "s", 1, "x")]
    docs = spark.createDataFrame(rows, DOCS)
    bench = spark.createDataFrame([(1, ITEM)], "item_id long, text string")
    kept = tiling.clean(docs, bench)
    assert kept.columns == docs.columns and sorted(str(r["doc_id"]) for r in kept.collect()) == ["2", "2", "None"]
    assert tiling.clean(docs, bench.limit(0)).count() == 4 and tiling.clean(docs.limit(0), bench).count() == 0
    assert tiling.contamination(docs, bench).count() == 3


def test_long_repetitive_texts():
    """One word again and again, and two in turn, in documents of 100,000 words."""
    import time

    start = time.perf_counter()
    one, item = np.full(100_000, 7, np.uint64), np.full(2_000, 7, np.uint64)
    assert sum(t[2] for t in tiling.tile(one[:20_000], item)) == 2_000
    turns = np.arange(100_000, dtype=np.uint64) % np.uint64(50)
    assert sum(t[2] for t in tiling.tile(turns, turns[:1_000])) == 1_000
    assert time.perf_counter() - start < 60
