"""Windows and session trees over a stream of events.

Rows later than the watermark are dropped by the stateful operators; their
number is in the query's progress (``rows_dropped``). Every function takes a
batch frame as well and gives the result over all of it, which is the oracle.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from canopy.forest.sources import STAGES

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """A stream over a folder of Parquet files of events."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def windowed(events: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events, users and value of tumbling or sliding windows, by type."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    got = marked.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("value"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "event_type", "n", "value")


def sessions(events: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """Sessions of each user: their events in order of time."""
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    steps = F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type")))
    got = marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(steps.alias("steps"))
    return got.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), F.size("steps").alias("n"), "steps")


def tree_of(types: list[str]) -> list[tuple[int, str]]:
    """(parent, label) of a session's tree: a visit, and each event below the latest earlier one of a smaller stage."""
    rank = {s: k for k, s in enumerate(STAGES)}
    out, last = [(-1, "visit")], [0] * (len(STAGES) + 1)
    for x in types:
        r = rank.get(x, len(STAGES))
        out.append((max(last[:r], default=0), x))
        last[r] = len(out) - 1
    return out


def pair_counts(types: list[str]) -> dict[tuple[str, str], int]:
    """Root counts of the tree's 1-patterns (label, '') and 2-patterns."""
    tree, roots = tree_of(types), {}
    for n, (_, label) in enumerate(tree):
        roots.setdefault((label, ""), set()).add(n)
        up = tree[n][0]
        while up >= 0:
            roots.setdefault((tree[up][1], label), set()).add(up)
            up = tree[up][0]
    return {k: len(v) for k, v in roots.items()}


def session_pairs(closed: DataFrame) -> DataFrame:
    """``(anc_label, desc_label, support)`` of each closed session's tree."""

    def each(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = [(a, b, n) for steps in pdf["steps"] for (a, b), n in pair_counts([s["event_type"] for s in steps]).items()]
            yield pd.DataFrame(rows, columns=["anc_label", "desc_label", "support"])

    return closed.select("steps").mapInPandas(each, "anc_label string, desc_label string, support long")


def running_pairs(pairs: DataFrame) -> DataFrame:
    """Counts kept up to date over a stream of session pairs, with a state for each pair of labels."""

    def add(key: tuple, pdfs: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = (state.get[0] if state.exists else 0) + int(sum(p["support"].sum() for p in pdfs))
        state.update((total,))
        yield pd.DataFrame([(*key, total)], columns=["anc_label", "desc_label", "support"])

    return pairs.groupBy("anc_label", "desc_label").applyInPandasWithState(add, "anc_label string, desc_label string, support long", "support long", "update", GroupStateTimeout.NoTimeout)


def mine_batches(closed: DataFrame, minsup: int, sink: Callable[[DataFrame, int], None], checkpoint: str, **kw) -> StreamingQuery:
    """Closed patterns of the session trees of every micro-batch."""
    from canopy.forest.encode import from_patterns
    from canopy.mine.miners import mine_eager
    from canopy.pattern.model import Pattern

    def mine(batch: DataFrame, epoch: int) -> None:
        trees = batch.select(F.transform("steps", lambda s: s["event_type"]).alias("types")).toLocalIterator()
        shapes = []
        for r in trees:  # the micro-batch is bounded by its trigger
            nodes = tree_of(r["types"])
            shapes.append(depth_first(nodes))
        if shapes:
            frame = from_patterns(batch.sparkSession, [Pattern(tuple(x), tuple(p)) for x, p in shapes])
            sink(mine_eager(frame, minsup, **kw).result(), epoch)

    return closed.writeStream.foreachBatch(mine).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def depth_first(tree: list[tuple[int, str]]) -> tuple[list[str], list[int]]:
    children: dict[int, list[int]] = {}
    for n, (up, _) in enumerate(tree):
        children.setdefault(up, []).append(n)
    labels, parent, stack = [], [], [(0, -1)]
    while stack:
        n, up = stack.pop()
        labels.append(tree[n][1])
        parent.append(up)
        stack += [(c, len(labels) - 1) for c in reversed(children.get(n, []))]
    return labels, parent


def rows_dropped(query: StreamingQuery) -> int:
    """Late rows that the query's stateful operators have dropped so far."""
    progress = [p if isinstance(p, str) else p.json for p in query.recentProgress]
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in progress for op in json.loads(p)["stateOperators"])
