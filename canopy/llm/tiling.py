"""Benchmark decontamination by greedy string tiling.

Texts become lower-case word tokens. Documents are joined to the benchmark by
hashes of ``SEED`` tokens in a row. For each document and item that share
enough seeds, matches are marked longest first, with rolling hashes over ever
shorter search lengths, so that no token is covered twice. The share of the
item's tokens that tiles cover decides, in whatever order the passages stand.

The benchmark is broadcast in blocks of ``BLOCK`` tokens at most; a larger one
takes more passes over the documents, none a larger broadcast.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import Shared, arrow_map
from canopy.storage import stage

SEED, COVERAGE, BLOCK = 5, 0.5, 2_000_000
#: Pairs of equal runs looked at together.
PAIRS = 1 << 20
TOKEN = re.compile(r"\w+")
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
FOUND = "doc_id long, item_id long, coverage double, tiles int"


def tokens(text: str) -> list[str]:
    return TOKEN.findall(text.lower())


def codes(words: list[str]) -> np.ndarray:
    from xxhash import xxh3_64_intdigest

    return np.fromiter((xxh3_64_intdigest(w) for w in words), np.uint64, len(words))


def rolling(h: np.ndarray, size: int) -> np.ndarray:
    """Karp-Rabin hashes of all runs of ``size`` codes (modulo 2^64), by prefix sums of powers."""
    n = len(h) - size + 1
    if n < 1:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for k in range(size):
        out = out * MULTIPLIER + h[k : k + n]
    return out ^ out >> np.uint64(32)


def free_runs(marked: np.ndarray, size: int) -> np.ndarray:
    """Starts of runs of ``size`` unmarked places."""
    if len(marked) < size:
        return np.zeros(0, np.int64)
    total = np.concatenate([[0], np.cumsum(marked)])
    return np.flatnonzero(total[size:] == total[:-size])


def maximal_matches(doc: np.ndarray, item: np.ndarray, taken_doc: np.ndarray, taken_item: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts in both and lengths of the free matches of at least ``size`` codes that cannot begin earlier.

    Runs of equal rolling hashes are paired in blocks of ``PAIRS``; most pairs of a repetitive text continue one that
    begins earlier, and fall away at once. The others are extended side by side, code by code.
    """
    of_item, of_doc = free_runs(taken_item, size), free_runs(taken_doc, size)
    hash_item, hash_doc = rolling(item, size)[of_item], rolling(doc, size)[of_doc]
    order = np.argsort(hash_item, kind="stable")
    hash_item, of_item = hash_item[order], of_item[order]
    first = np.searchsorted(hash_item, hash_doc, "left")
    n = np.searchsorted(hash_item, hash_doc, "right") - first
    hit = np.flatnonzero(n)
    starts = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
    blocks = np.searchsorted(np.cumsum(n[hit]), np.arange(PAIRS, int(n.sum()) + PAIRS, PAIRS)) + 1 if len(hit) else []
    for mine in np.split(hit, blocks):
        d = np.repeat(of_doc[mine], n[mine])
        i = of_item[np.repeat(first[mine] - np.cumsum(n[mine]) + n[mine], n[mine]) + np.arange(len(d))]
        earlier = (d > 0) & (i > 0)
        earlier[earlier] = (doc[d[earlier] - 1] == item[i[earlier] - 1]) & ~taken_doc[d[earlier] - 1] & ~taken_item[i[earlier] - 1]
        starts.append((d[~earlier], i[~earlier]))
    d, i = (np.concatenate(x) for x in zip(*starts))
    length, going = np.zeros(len(d), np.int64), np.arange(len(d))
    while len(going):
        x, y = d[going] + length[going], i[going] + length[going]
        inside = (x < len(doc)) & (y < len(item))
        going, x, y = going[inside], x[inside], y[inside]
        going = going[(doc[x] == item[y]) & ~taken_doc[x] & ~taken_item[y]]
        length[going] += 1
    long = length >= size
    return d[long], i[long], length[long]


def tile(doc: np.ndarray, item: np.ndarray, least: int = SEED) -> list[tuple[int, int, int]]:
    """Greedy tiles (place in doc, place in item, length) of at least ``least`` codes, longest first."""
    taken_doc, taken_item, tiles = np.zeros(len(doc), bool), np.zeros(len(item), bool), []
    size = min(len(item), len(doc))
    while size >= least:
        d, i, n = maximal_matches(doc, item, taken_doc, taken_item, size)
        longest = int(n.max(initial=0))
        if longest > 2 * size:  # search the long ones first
            size = longest
            continue
        blocked = False
        for k in np.lexsort((i, d, -n)).tolist():
            mine, its = slice(d[k], d[k] + n[k]), slice(i[k], i[k] + n[k])
            if taken_doc[mine].any() or taken_item[its].any():
                blocked = True
                continue
            taken_doc[mine] = taken_item[its] = True
            tiles.append((int(d[k]), int(i[k]), int(n[k])))
        if blocked:  # what a tile left free of a longer match may still fit
            continue
        if size == least:
            break
        size = max(size // 2 if size > 2 * least else least, least)
    return tiles


class Items:
    """A block of the benchmark and its sorted seeds."""

    def __init__(self, items: list[tuple[int, str]], seed: int):
        self.ids = [k for k, _ in items]
        self.codes = [codes(tokens(t)) for _, t in items]
        seeds = [(h, n) for n, c in enumerate(self.codes) for h in np.unique(rolling(c, min(seed, max(len(c), 1)))).tolist()]
        self.short = {n for n, c in enumerate(self.codes) if len(c) < seed}
        self.sizes = sorted({min(seed, len(c)) for c in self.codes if len(c)})
        self.by_seed: dict[int, list[int]] = defaultdict(list)
        for h, n in seeds:
            self.by_seed[h].append(n)
        self.sorted = np.array(sorted(self.by_seed), np.uint64)
        self.seed = seed

    def matches(self, doc: np.ndarray, coverage: float) -> Iterator[tuple[int, float, int]]:
        """(item, coverage, tiles) of items that tiles of the document cover well enough."""
        near: dict[int, list[np.ndarray]] = defaultdict(list)
        for size in self.sizes:
            h = rolling(doc, size)
            at = np.minimum(np.searchsorted(self.sorted, h), len(self.sorted) - 1)
            hit = np.flatnonzero(self.sorted[at] == h)
            for p, key in zip(hit.tolist(), h[hit].tolist()):
                for n in self.by_seed[key]:
                    if min(self.seed, len(self.codes[n])) == size:
                        near[n].append(p)
        for n, places in near.items():
            item = self.codes[n]
            least = min(self.seed, len(item))
            inside = np.unique((np.array(places)[:, None] + np.arange(least)[None]).ravel())
            # only tokens inside shared seeds can be tiled; a gap breaks the row
            part, breaks = doc[inside], np.flatnonzero(np.diff(inside) > 1) + 1
            part = np.insert(part, breaks, np.arange(len(breaks), dtype=np.uint64))
            covered = np.isin(rolling(item, least), rolling(part, least))
            most = np.convolve(covered, np.ones(least, int))[: len(item)].astype(bool).sum() / len(item)
            if most < coverage:
                continue
            tiles = tile(part, item, least)
            share = sum(t[2] for t in tiles) / len(item)
            if share >= coverage:
                yield self.ids[n], share, len(tiles)


def blocks(benchmark: DataFrame, most: int) -> Iterator[list[tuple[int, str]]]:
    """The benchmark in lists of items of at most ``most`` words (or one item)."""
    block, size = [], 0
    for r in benchmark.where("item_id IS NOT NULL AND text IS NOT NULL").select("item_id", "text").orderBy("item_id", "text").toLocalIterator():
        n = len(r["text"].split()) + 1
        if block and size + n > most:
            yield block
            block, size = [], 0
        block.append((r["item_id"], r["text"]))
        size += n
    if block:
        yield block


def matches(docs: DataFrame, benchmark: DataFrame, seed: int = SEED, coverage: float = COVERAGE, block: int = BLOCK) -> DataFrame:
    """``(doc_id, item_id, coverage, tiles)`` of all pairs whose tiles cover enough of the item."""
    spark, source, out = docs.sparkSession, docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), None
    for items in blocks(benchmark, block):
        shared = Shared(spark, Items(items, seed))

        def make(shared=shared):
            def step(ids: list, texts: list) -> Iterator[tuple]:
                for doc_id, text in zip(ids, texts):
                    if text:
                        yield from ((doc_id, *m) for m in shared.value.matches(codes(tokens(text)), coverage))

            return step

        found = arrow_map(source, make, FOUND)
        out = found if out is None else out.union(found)
    return spark.createDataFrame([], FOUND) if out is None else out


def contamination(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """One row per doc_id: contaminated, the best covered item, its coverage, all items.

    A null or empty text matches nothing, and neither does an item without a
    token. Rows that repeat a doc_id are one document; null ids are another.
    Items shorter than the seed match as a whole. Equal coverages give the
    smaller item. An empty benchmark leaves every document clean. Whole texts
    count, however long; extra columns are ignored.
    """
    found = stage(matches(docs, benchmark, **options), "tiled")
    best = found.groupBy("doc_id").agg(
        F.min(F.struct((-F.col("coverage")).alias("c"), "item_id")).alias("best"), F.array_sort(F.collect_set("item_id")).alias("items")
    )
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id")).distinct()
    return ids.join(best, ids["doc_id"].eqNullSafe(best["doc_id"]), "left").select(
        ids["doc_id"],
        F.col("best").isNotNull().alias("contaminated"),
        F.col("best.item_id").alias("item_id"),
        F.round(-F.col("best.c"), 6).alias("coverage"),
        F.coalesce("items", F.array().cast("array<bigint>")).alias("items"),
    )


def clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """``docs`` without the contaminated ones; rows without an id stay."""
    gone = matches(docs, benchmark, **options).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)
