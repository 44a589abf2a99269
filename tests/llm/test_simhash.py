import random

import numpy as np
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from canopy.llm import simhash
from canopy.llm.components import components
from tests.conftest import SF

DOCS = "doc_id long, text string, extra string, fp string"


def plain_fingerprint(text):
    """Bit by bit, from the words."""
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    shingles = [" ".join(words[k : k + 3]) for k in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(prints):
    """(id, fingerprint) pairs to the smallest id reachable."""
    ids = sorted(prints)
    root = {k: k for k in ids}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= 2:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {k: find(k) for k in ids}


def test_fingerprints_of_odd_texts():
    for text in ("", " \n\t", "one", "Two Words", "a b c", "É é\u00a0x\x1cy z w", "a b c " * 70_000, "x " * 3):
        got = simhash.fingerprint_bytes(text.encode())
        assert got & (1 << 64) - 1 == plain_fingerprint(text)


def test_spark_hash_agrees(spark):
    from pyspark.sql import functions as F

    got = spark.createDataFrame([("a b c",)], "s string").select(F.xxhash64("s")).first()[0]
    assert got & (1 << 64) - 1 == xxhash.xxh64_intdigest(b"a b c", 42)


def test_masks_cover_two_bytes():
    assert len(simhash.free_positions()) == 28
    for free in simhash.free_positions():
        assert (~simhash.mask_of(free) & (1 << 64) - 1).bit_count() == 16


def unsigned(x):
    return x & (1 << 64) - 1


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 2**32), st.sampled_from([3, 40, 200]))
def test_lists_give_the_components_of_their_links(seed, n):
    rng = random.Random(seed)
    free = simhash.free_positions()[rng.randrange(28)]
    base = rng.getrandbits(64)
    fps = list({base & unsigned(simhash.mask_of(free)) | sum((rng.getrandbits(8) & rng.getrandbits(8)) << 8 * p for p in free) for _ in range(n)})
    reps = rng.sample(range(10_000), len(fps))
    links = simhash.list_links(np.array(reps), np.array(fps, np.uint64), free, 2)
    want = plain_components(dict(zip(reps, fps)))
    assert {b: a for a, b in links} == {k: v for k, v in want.items() if k != v}


def test_whole_operator_against_brute_force(spark):
    rng = random.Random(7)
    words = [f"w{k}" for k in range(400)]
    base = [[rng.choice(words) for _ in range(120)] for _ in range(6)]
    rows = []
    for k in range(160):
        text = list(rng.choice(base))
        for _ in range(rng.choice((0, 0, 1, 2, 3))):
            text[rng.randrange(len(text))] = rng.choice(words)
        rows.append((k, " ".join(text), "x", "clash"))
    rows += [(900, None, "x", "c"), (901, "", "x", "c"), (902, " ", "x", "c"), (5, rows[5][1], "x", "c")]
    docs = spark.createDataFrame(rows, DOCS).repartition(5)
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    prints = {r["doc_id"]: unsigned(r["fp"]) for r in got}
    assert prints == {k: plain_fingerprint(t) for k, t, _, _ in rows}
    assert {r["doc_id"]: r["component_id"] for r in got} == plain_components(prints)
    assert {r["doc_id"]: r["n_linked"] for r in got}[901] == 3


def test_given_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = simhash.near_duplicates(docs).collect()
    prints = {r["doc_id"]: unsigned(r["fp"]) for r in got}
    assert {r["doc_id"]: r["component_id"] for r in got} == plain_components(prints)
    kept = simhash.first_of_each(docs)
    assert kept.columns == docs.columns and sorted(r["doc_id"] for r in kept.collect()) == sorted(set(plain_components(prints).values()))


def test_nulls_and_empty(spark):
    docs = spark.createDataFrame([(None, "a b c d", "", ""), (4, "a b c d", "", "")], DOCS)
    assert {r["component_id"] for r in simhash.near_duplicates(docs).collect()} == {4}
    assert simhash.near_duplicates(spark.createDataFrame([], DOCS)).count() == 0
    assert simhash.first_of_each(docs).count() == 2


def test_components_of_chains_and_stars(spark):
    rng = random.Random(3)
    edges = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 130)] + [(200, 200), (None, 3)]
    rng.shuffle(edges)
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(41)} | {k: 100 for k in range(100, 130)}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
