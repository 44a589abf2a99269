"""SimHash near duplicates by a byte-position inverted index.

A fingerprint has eight bytes. Two fingerprints at ``distance`` 2 or less
differ in two bytes at most, so they share at least six (position, byte)
entries: six is the guaranteed minimum that the count filter asks for.
Postings of single bytes have only 2,048 keys and hold N/256 entries each, so
tallying over them costs N^2/64 pairs. The filter is therefore folded into
the key: every choice of six positions, 28 in all, is a key made of those six
positional bytes. Two fingerprints meet in a posting list exactly if their
tally reaches six, and no pair below it is ever formed.

The members of one list differ in two bytes, so a list holds 65,536 distinct
fingerprints at most, whatever the corpus. Lists are verified and reduced to
star links of their own components; pairs are never emitted.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import arrow_map
from canopy.llm.columns import text_bytes
from canopy.llm.components import components
from canopy.storage import stage

DISTANCE, SHINGLE, SEED = 2, 3, 42
#: Hashes whose bits are counted at once.
CHUNK = 1 << 15


def fingerprint_bytes(text: bytes, size: int = SHINGLE, seed: int = SEED) -> int:
    """The signed 64-bit fingerprint of a text; zero without words."""
    from xxhash import xxh64_intdigest

    words = text.lower().split()  # of bytes: A-Z only, and white space x20, x09-x0D only
    if not words:
        return 0
    n = len(words) - size + 1
    if n < 1:
        shingles, n = [b" ".join(words)], 1
    else:
        shingles = map(b" ".join, zip(*(words[k:] for k in range(size))))
    hashes = np.fromiter(map(xxh64_intdigest, shingles, repeat(seed)), np.uint64, n).view(np.uint8).reshape(n, 8)
    ones = sum(np.unpackbits(hashes[k : k + CHUNK], axis=1, bitorder="little").sum(axis=0, dtype=np.int64) for k in range(0, n, CHUNK))
    return int(np.packbits(2 * ones > n, bitorder="little").view(np.int64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE) -> DataFrame:
    """``(id, fp)`` for every row; a null text counts as an empty one."""

    def make():
        def step(ids: list, texts: list) -> Iterator[tuple]:
            for key, text in zip(ids, texts):
                yield key, fingerprint_bytes(text, size)

        return step

    return arrow_map(docs.select(F.col(id_col).cast("long").alias(id_col), text_bytes(text_col)), make, f"{id_col} long, fp long")


def free_positions(distance: int = DISTANCE) -> list[tuple[int, ...]]:
    return list(combinations(range(8), distance))


def mask_of(free: tuple[int, ...]) -> int:
    """A signed 64-bit mask of the byte positions that are not free."""
    mask = ~sum(0xFF << (8 * p) for p in free) & (1 << 64) - 1
    return mask - (1 << 64) if mask >> 63 else mask


def postings(distinct: DataFrame, distance: int = DISTANCE) -> DataFrame:
    """``distinct(rep, fp)`` to posting lists ``(free, key, members)`` of two or more."""
    keys = F.array(*(F.struct(F.lit(k).cast("tinyint").alias("free"), F.col("fp").bitwiseAND(F.lit(mask_of(p)).cast("long")).alias("key")) for k, p in enumerate(free_positions(distance))))
    return (
        distinct.select(F.struct("rep", "fp").alias("m"), F.explode(keys).alias("k"))
        .groupBy("k.free", "k.key")
        .agg(F.collect_list("m").alias("members"))
        .where(F.size("members") > 1)
    )


def least_shared(distance: int) -> int:
    """The positional bytes that fingerprints within ``distance`` have in common at least."""
    return 8 - distance


def masks_within(bits: int, distance: int) -> list[int]:
    return [sum(1 << b for b in c) for d in range(1, distance + 1) for c in combinations(range(bits), d)]


def list_links(reps: np.ndarray, fps: np.ndarray, free: tuple[int, ...], distance: int) -> list[tuple[int, int]]:
    """Star links (smallest rep, rep) of the components within one posting list."""
    order = np.argsort(reps)
    reps, fps = reps[order], fps[order]
    n, label = len(reps), np.arange(len(reps))
    if n <= 64:
        apart = fps[:, None] ^ fps[None, :]
        tally = (apart.reshape(n, n, 1).view(np.uint8) == 0).sum(axis=2)  # positional bytes in common
        near = (tally >= least_shared(distance)) & (np.bitwise_count(apart) <= distance)
        while True:
            new = np.where(near, label[None, :], n).min(axis=1)
            if (new == label).all():
                break
            label = new
    else:
        rest = sum(((fps >> np.uint64(8 * p)) & np.uint64(0xFF)) << np.uint64(8 * k) for k, p in enumerate(free)).astype(np.int64)
        at = np.full(1 << 8 * len(free), -1)
        at[rest] = np.arange(n)
        masks = masks_within(8 * len(free), distance)
        while True:
            old = label.copy()
            for m in masks:
                other = at[rest ^ m]
                hit = other >= 0
                label[hit] = np.minimum(label[hit], label[other[hit]])
            label = label[label]
            if (label == old).all():
                break
    return [(int(reps[r]), int(reps[k])) for k, r in enumerate(label) if r != k]


def links(distinct: DataFrame, distance: int = DISTANCE) -> DataFrame:
    """Star links between representatives whose fingerprints are within ``distance``."""
    positions = free_positions(distance)

    def make():
        def step(free: list, members: list) -> Iterator[tuple]:
            for k, group in zip(free, members):
                if len(group) == 2:
                    (a, b) = group
                    apart = (a["fp"] ^ b["fp"]) & (1 << 64) - 1
                    if apart.to_bytes(8).count(0) >= least_shared(distance) and apart.bit_count() <= distance:
                        yield min(a["rep"], b["rep"]), max(a["rep"], b["rep"])
                    continue
                reps = np.array([m["rep"] for m in group], np.int64)
                fps = np.array([m["fp"] for m in group], np.int64).view(np.uint64)
                yield from list_links(reps, fps, positions[k], distance)

        return step

    return arrow_map(postings(distinct, distance).select("free", "members"), make, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", distance: int = DISTANCE, size: int = SHINGLE) -> DataFrame:
    """``(id, fp, component_id, n_linked)`` for every row.

    ``component_id`` is the smallest id reachable over links of ``distance``
    or fewer differing bits; ``n_linked`` counts the rows of the component.
    Equal fingerprints are one node, so a group of copies costs one entry.
    A null id keeps its row, is no representative if another id shares its
    fingerprint, and may leave ``component_id`` null. Extra columns of ``docs``
    are ignored. Empty input gives an empty result.
    """
    prints = stage(fingerprints(docs, id_col, text_col, size), "fingerprints")
    distinct = stage(prints.groupBy("fp").agg(F.min(id_col).alias("rep"), F.count(F.lit(1)).alias("n")), "distinct")
    found = components(links(distinct.where("rep IS NOT NULL").select("rep", "fp"), distance))
    classes = distinct.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("fp", "n", F.coalesce("component", "rep").alias("component_id"))
    classes = stage(classes, "classes")
    sizes = classes.groupBy("component_id").agg(F.sum("n").alias("n_linked"))
    classes = classes.join(sizes, "component_id", "left").select("fp", "component_id", "n_linked")
    return prints.join(classes, "fp").select(id_col, "fp", "component_id", "n_linked")


def hex_fingerprint(fp: str = "fp") -> F.Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def stood_for(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The ids that a smaller id of their group stands for, written."""
    classes = near_duplicates(docs, id_col, **options)
    return stage(classes.where(F.col(id_col) != F.col("component_id")).select(id_col).distinct(), "stood_for")


def first_of_each(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """``docs`` without the rows that another document of their group stands for.

    Rows that repeat an id share its fate; rows without an id stay.
    """
    return docs.join(stood_for(docs, id_col, **options), id_col, "left_anti").select(docs.columns)
