"""Documents of high shingle overlap, found exactly by a prefix index.

Two sets of distinct shingles have Jaccard similarity 4/5 or more only if they
share ceil(4n/5) of the n shingles of either. With one order for all sets, the
first n - ceil(4n/5) + 1 shingles of both then have one in common, so postings
of these prefixes miss no pair. Any order is exact; shingles that are common
in a sample of the documents come last in it, which keeps the lists short. From
their first common shingle on, similar sets still have enough shingles to share;
pairs for which a key comes too late in one of them do not meet there. So copies
that differ by more than a ninth or so share lists without forming pairs.

A document goes if a smaller id is similar, so one such id settles it. Lists are
first checked against their smallest member, round by round, which settles groups
of near copies without forming their pairs; then what is open is checked against
the smaller members left. A quarter of the shingles rules most candidates out; what is left is verified on
whole sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import Shared, arrow_map, parts, to_batch
from canopy.llm.columns import text_bytes
from canopy.storage import stage

#: Words of a shingle, and the least similarity as a fraction.
SHINGLE, NUM, DEN, SEED = 5, 4, 5, 42
#: For the order only: documents of the sample, copies in it that make a shingle common, and how many are kept.
SAMPLE, COMMON, ORDERED = 10_000, 2, 200_000
#: Rounds against single members go on while they drop one in so many documents of the lists.
WORTH = 20
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
#: Postings packed at once by a task; bytes of text whose postings share a bucket.
PACK, BUCKET_BYTES = 1 << 19, 1 << 26
PACKED = pa.schema([("bucket", pa.int64()), *((c, pa.binary()) for c in ("keys", "ids", "n", "place", "pos"))])


def shingles(text: bytes, size: int = SHINGLE) -> np.ndarray:
    """The sorted hashes of the distinct shingles; one for a shorter text, none without words.

    A shingle's hash mixes the hashes of its words in their order.
    """
    from xxhash import xxh64_intdigest

    words = text.lower().split()
    if not words:
        return np.empty(0, np.int64)
    known = {w: xxh64_intdigest(w, SEED) for w in set(words)}
    each = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    n = max(len(words) - size + 1, 1)
    mixed = np.zeros(n, np.uint64)
    for k in range(min(size, len(words))):
        mixed = (mixed ^ each[k : k + n]) * MULTIPLIER
        mixed ^= mixed >> np.uint64(29)
    return np.unique(mixed.view(np.int64))


def prefix(found: np.ndarray, common: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The shingles that any similar set must share one of, in the common order."""
    n = len(found)
    last = np.zeros(n, np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, found), len(common) - 1)
        last = np.where(common[at] == found, rank[at], 0)
    return found[np.lexsort((found, last))[: n - -(-NUM * n // DEN) + 1]] if n else found


def common_shingles(docs: DataFrame, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that come last in the order, and their places; decides the cost, never the result."""
    every = max(1, docs.count() // SAMPLE)

    def make():
        def step(texts: list) -> Iterator[tuple]:
            for text in texts:
                yield from ((int(h),) for h in shingles(text, size))

        return step

    sample = docs.where(F.pmod(F.xxhash64("id"), F.lit(every)) == 0).select("text")
    rows = arrow_map(sample, make, "key long").groupBy("key").count().where(F.col("count") >= COMMON).orderBy(F.desc("count"), "key").limit(ORDERED).collect()
    by_key = sorted((r["key"], r["count"]) for r in rows)
    return np.array([k for k, _ in by_key], np.int64), np.array([n for _, n in by_key], np.int64)


def postings(docs: DataFrame, size: int) -> DataFrame:
    """``(bucket, keys, ids, n, place, pos)``: postings of every prefix, dealt by key to buckets and packed there.

    A row holds what some documents of one task put into one bucket: the keys, for each key the place of its document
    in ``ids`` and its own place in that document's order (65,535 if later), and the documents' numbers of shingles. So
    a posting takes twelve bytes on its way, not a whole row.
    """
    order = Shared(docs.sparkSession, common_shingles(docs, size))
    words = docs.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    buckets = max(1, words // BUCKET_BYTES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common, rank = order.value
        keys, ids, sizes, held = [], [], [], 0

        def packed() -> pa.RecordBatch:
            lengths = [len(k) for k in keys]
            every, place = np.concatenate(keys).view(np.uint64), np.repeat(np.arange(len(ids), dtype=np.uint16), lengths)
            pos = np.concatenate([np.minimum(np.arange(k), 0xFFFF) for k in lengths]).astype(np.uint16)
            dealt = (every >> np.uint64(20)) % np.uint64(buckets)
            by = np.argsort(dealt, kind="stable")
            every, place, pos, dealt = every[by], place[by], pos[by], dealt[by].astype(np.int64)
            starts = np.flatnonzero(np.concatenate([[True], dealt[1:] != dealt[:-1]]))
            rows, own, n = [], np.array(ids, np.int64), np.array(sizes, np.int32)
            for start, stop in zip(starts.tolist(), [*starts[1:].tolist(), len(every)]):
                docs_here, at = np.unique(place[start:stop], return_inverse=True)
                rows.append((int(dealt[start]), every[start:stop].tobytes(), own[docs_here].tobytes(), n[docs_here].tobytes(), at.astype(np.uint16).tobytes(), pos[start:stop].tobytes()))
            return to_batch(rows, PACKED)

        for batch in batches:
            for part in parts(batch):
                for key, text in zip(*(c.to_pylist() for c in part.columns)):
                    found = shingles(text, size)
                    if not len(found):
                        continue
                    keys.append(prefix(found, common, rank))
                    ids.append(key)
                    sizes.append(len(found))
                    held += len(keys[-1])
                    if held >= PACK or len(ids) == 1 << 16:
                        yield packed()
                        keys, ids, sizes, held = [], [], [], 0
        if ids:
            yield packed()

    return docs.select("id", "text").mapInArrow(run, "bucket long, keys binary, ids binary, n binary, place binary, pos binary")


def members(docs: DataFrame, size: int) -> DataFrame:
    """``(key, id, n, reach)`` of the keys that two or more ids have in their prefixes.

    ``reach`` is how many shingles the document has from the key on, at most.
    """
    out = pa.schema([("key", pa.int64()), ("id", pa.int64()), ("n", pa.int32()), ("reach", pa.int32())])

    def shared(bucket: pa.Table) -> pa.Table:
        keys, ids, sizes, reaches = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int32)], [np.zeros(0, np.int32)]
        for k, i, n, place, pos in zip(*(bucket.column(c).to_pylist() for c in ("keys", "ids", "n", "place", "pos"))):
            at = np.frombuffer(place, np.uint16)
            keys.append(np.frombuffer(k, np.int64))
            ids.append(np.frombuffer(i, np.int64)[at])
            sizes.append(np.frombuffer(n, np.int32)[at])
            reaches.append(sizes[-1] - np.frombuffer(pos, np.uint16).astype(np.int32))
        key, own, n, reach = map(np.concatenate, (keys, ids, sizes, reaches))
        order = np.argsort(key, kind="stable")
        key, own, n, reach = key[order], own[order], n[order], reach[order]
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        several = np.minimum.reduceat(own, first) != np.maximum.reduceat(own, first) if len(first) else np.zeros(0, bool)
        keep = np.repeat(several, np.diff(first, append=len(key)))
        return pa.table([key[keep], own[keep], n[keep], reach[keep]], schema=out)

    return postings(docs, size).groupBy("bucket").applyInArrow(shared, "key long, id long, n int, reach int")


def fitting(open_: DataFrame, others: DataFrame) -> DataFrame:
    """Pairs ``(a, b)``, a < b and b open, that share a key and may be similar; ``others(key, a, m, ahead)``.

    Their sizes must allow it, and so must what both have from the key on: at the first shingle in common, similar sets do.
    """
    sizes = F.least("n", "m") * DEN >= NUM * F.greatest("n", "m")
    enough = F.least("reach", "ahead") * (NUM + DEN) >= NUM * (F.col("n") + F.col("m"))
    both = open_.where("open").join(others, "key").where((F.col("a") < F.col("id")) & sizes & enough)
    return stage(both.select("a", F.col("id").alias("b")).distinct(), "candidates")


def quarters(docs: DataFrame, size: int) -> DataFrame:
    """``(id, n, part)`` of every document: its number of shingles, and a quarter of them, chosen by hash, in 32 bits."""

    def make():
        def step(ids: list, texts: list) -> Iterator[tuple]:
            for key, text in zip(ids, texts):
                found = shingles(text, size)
                if len(found):
                    yield key, len(found), (found[found & 3 == 0] >> 32).astype(np.int32)

        return step

    return stage(arrow_map(docs.select("id", "text"), make, "id long, n int, part array<int>"), "quarters")


def possible(pairs: DataFrame, parts: DataFrame) -> DataFrame:
    """The pairs that their quarters do not rule out: what a quarter lacks in common is lacking in the whole."""
    left, right = parts.toDF("a", "na", "pa"), parts.toDF("b", "nb", "pb")
    both = pairs.join(left, "a").join(right, "b")
    most = F.size(F.array_intersect("pa", "pb")) + F.least(F.col("na") - F.size(F.array_distinct("pa")), F.col("nb") - F.size(F.array_distinct("pb")))
    return stage(both.where(most * (NUM + DEN) >= NUM * (F.col("na") + F.col("nb"))).select("a", "b").distinct(), "possible")


def similar(docs: DataFrame, pairs: DataFrame, parts: DataFrame, size: int) -> DataFrame:
    """The pairs whose whole sets are similar."""

    def make():
        def step(ids: list, texts: list) -> Iterator[tuple]:
            for key, text in zip(ids, texts):
                yield key, shingles(text, size)

        return step

    pairs = possible(pairs, parts)
    asked = pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()
    sets = stage(arrow_map(docs.join(asked, "id", "left_semi").select("id", "text"), make, "id long, s array<long>"), "sets")
    both = pairs.join(sets.toDF("a", "sa"), "a").join(sets.toDF("b", "sb"), "b")
    return both.where(F.size(F.array_intersect("sa", "sb")) * (NUM + DEN) >= NUM * (F.size("sa") + F.size("sb"))).select("a", "b")


def without(shared: DataFrame, found: DataFrame) -> DataFrame:
    """Lists whose members in ``found`` are settled; those without an open member are left out."""
    marked = shared.join(found.withColumn("found", F.lit(True)), "id", "left").select("key", "id", "n", "reach", (F.col("open") & F.col("found").isNull()).alias("open"))
    return marked.join(marked.where("open").select("key").distinct(), "key", "left_semi")


def repeats(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """``docs(id, text as bytes)`` to the ids that are similar to a smaller id.

    No two of the other ids are similar; the smaller one may itself go. Null ids and texts without words take
    no part.
    """
    docs = docs.where("id IS NOT NULL")
    shared, gone, parts = stage(members(docs, size).withColumn("open", F.lit(True)), "members"), None, quarters(docs, size)
    while True:
        pivot = stage(shared.groupBy("key").agg(F.min(F.struct("id", "n", "reach")).alias("p")).select("key", F.col("p.id").alias("a"), F.col("p.n").alias("m"), F.col("p.reach").alias("ahead")), "pivots")
        pairs = fitting(shared, pivot)
        if gone is None:  # lists of one group have many pivots: the smallest that a document meets settles most of it
            gone = stage(similar(docs, pairs.groupBy("b").agg(F.min("a").alias("a")).select("a", "b"), parts, size).select(F.col("b").alias("id")).distinct(), "repeats")
            shared, pairs = stage(without(shared, gone), "members"), stage(pairs.join(gone.withColumnRenamed("id", "b"), "b", "left_anti").select("a", "b"), "candidates")
        found = stage(similar(docs, pairs, parts, size).select(F.col("b").alias("id")).distinct(), "repeats")
        gone = gone.union(found)
        dropped, held = found.count(), shared.where("open").select("id").distinct().count()
        # a pivot has met the rest of its list
        shared = stage(without(shared.join(pivot.select("key", "a"), "key").where("id > a"), found), "members")
        if dropped * WORTH <= held:
            break
    rest = similar(docs, fitting(shared, shared.select("key", F.col("id").alias("a"), F.col("n").alias("m"), F.col("reach").alias("ahead"))), parts, size).select(F.col("b").alias("id"))
    return stage(gone.union(rest).distinct(), "repeats")


def similar_to_smaller(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE) -> DataFrame:
    """The ids of rows that are similar to a row of smaller id."""
    found = repeats(docs.select(F.col(id_col).cast("long").alias("id"), text_bytes(text_col)).withColumnRenamed(text_col, "text"), size)
    return found.withColumnRenamed("id", id_col)


def first_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE) -> DataFrame:
    """``docs`` without the rows similar to a row of smaller id; rows that repeat an id share its fate."""
    return docs.join(similar_to_smaller(docs, id_col, text_col, size), id_col, "left_anti").select(docs.columns)
