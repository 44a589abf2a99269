"""Quality classifier by co-training of a text view and a page-metadata view.

Two logistic models see different columns of a document: one its text, the
other its language, source and length. The views of all rows are written once.
Over some rounds, both models judge every unlabelled row; each labels those it
is confident of by its calibrated probability, and the other learns from the
most confident different ones. Calibration is on held-out labelled rows (a
fitted slope and offset, so that a view without information stays near the
prior, and teaches nothing). At the end the views' log odds are added, counting
the prior once.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import Shared, arrow_map, to_batch
from canopy.llm.features import hashed_ngrams, shape
from canopy.storage import stage

NGRAMS, META = 512, 256
#: Bounds on the rows the models are fitted on: labelled ones, and pseudo-labelled ones of a view, label and round.
LABELLED, TAUGHT = 6000, 400
#: A row is confident if its calibrated probability of either label is so high.
ROUNDS, CONFIDENT, THRESHOLD = 3, 0.9, 0.5
TEXT = NGRAMS + len(shape(b"", []))
SURE = pa.schema([("view", pa.int32()), ("label", pa.int32()), ("odds", pa.float64()), ("code", pa.int64()), ("x", pa.binary())])


def text_view(text: str | None) -> np.ndarray:
    raw = (text or "").encode("utf-8", "replace")
    counts = np.sqrt(hashed_ngrams(raw, NGRAMS))
    return np.concatenate([counts / max(float(np.linalg.norm(counts)), 1e-9), np.array(shape(raw, raw.split()), np.float32)]).astype(np.float32)


def meta_view(lang: str | None, source: str | None, n_chars: int | None) -> np.ndarray:
    out = np.zeros(META, np.float32)
    size = -1 if n_chars is None else int(np.log2(n_chars + 1))
    for x in (f"lang={lang}", f"source={source}", f"size={size}"):
        out[crc32(x.encode("utf-8", "replace")) % META] = 1
    return out


@dataclass
class Linear:
    weights: np.ndarray
    offset: float

    def odds(self, x: np.ndarray) -> np.ndarray:
        return x @ self.weights + self.offset


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3, steps: int = 12) -> Linear:
    """Logistic regression by Newton steps."""
    x1 = np.hstack([x, np.ones((len(x), 1), x.dtype)]).astype(np.float64)
    w, penalty = np.zeros(x1.shape[1]), np.full(x1.shape[1], ridge * len(x))
    penalty[-1] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x1 @ w, -30, 30)))
        grad = x1.T @ (p - y) + penalty * w
        move = np.linalg.solve((x1 * (p * (1 - p) + 1e-6)[:, None]).T @ x1 + np.diag(penalty), grad)
        w -= move
        if np.abs(move).max() < 1e-4:
            break
    return Linear(w[:-1].astype(np.float32), float(w[-1]))


@dataclass
class CoTrained:
    views: list[Linear]
    scale: list[tuple[float, float]]
    prior: float

    def calibrated(self, xs: list[np.ndarray]) -> list[np.ndarray]:
        return [a * v.odds(x) + b for v, x, (a, b) in zip(self.views, xs, self.scale)]

    def log_odds(self, xs: list[np.ndarray]) -> np.ndarray:
        parts = self.calibrated(xs)
        return np.sum(parts, axis=0) - (len(parts) - 1) * self.prior


@dataclass
class Labelled:
    """Rows with their views and labels; every fifth given label is held out for calibration."""

    xs: list[np.ndarray]
    y: np.ndarray

    @property
    def held(self) -> np.ndarray:
        return np.arange(len(self.y)) % 5 == 0


def calibrated(views: list[Linear], rows: Labelled) -> CoTrained:
    """The views with a slope and an offset each, fitted on the rows held out."""
    rate = float(np.clip(rows.y.mean(), 1e-3, 1 - 1e-3))
    scale = []
    for v, x in zip(views, rows.xs):
        line = logistic(v.odds(x[rows.held])[:, None].astype(np.float32), rows.y[rows.held].astype(float))
        scale.append((max(float(line.weights[0]), 0.0), line.offset))
    return CoTrained(views, scale, float(np.log(rate / (1 - rate))))


def co_train(rows: Labelled, teach: Callable[[CoTrained], list[tuple[np.ndarray, np.ndarray]]], rounds: int = ROUNDS) -> CoTrained:
    """``teach`` returns, for each view, the other view's rows of what it is confident of, and their labels.

    A row that both label anew in a later round counts with its newest labels only.
    """
    fit = ~rows.held
    own = [(x[fit], rows.y[fit].astype(float)) for x in rows.xs]
    model = calibrated([logistic(x, t) for x, t in own], rows)
    for _ in range(rounds):
        taught = teach(model)
        if not any(len(t) for _, t in taught):
            break
        # what view 0 is sure of teaches view 1, and the other way round
        views = [logistic(np.vstack([x, more]), np.concatenate([t, labels])) for (x, t), (more, labels) in zip(own, taught[::-1])]
        model = calibrated(views, rows)
    return model


def confident(views: DataFrame, model: CoTrained, most: int = TAUGHT, least: float = CONFIDENT) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each view, the other view's rows of the ``most`` different rows it is surest of, by label.

    All unlabelled rows are judged where they lie; a task returns its best ones.
    """
    shared = Shared(views.sparkSession, model)
    bar = float(np.log(least / (1 - least)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[tuple[int, int], dict[int, tuple]] = defaultdict(dict)
        for batch in batches:
            xs = [np.frombuffer(b"".join(c.to_pylist()), np.float16).reshape(batch.num_rows, -1).astype(np.float32) for c in batch.columns[1:]]
            for v, odds in enumerate(shared.value.calibrated(xs)):
                for k in np.flatnonzero(np.abs(odds) >= bar).tolist():
                    mine = best[v, int(odds[k] > 0)]
                    other = batch.column(2 - v)[k].as_py()
                    mine[crc32(other)] = (float(abs(odds[k])), crc32(other), other)
                    if len(mine) > 4 * most:
                        best[v, int(odds[k] > 0)] = {x[1]: x for x in sorted(mine.values(), reverse=True)[:most]}
        rows = [(v, y, *x) for (v, y), mine in best.items() for x in sorted(mine.values(), reverse=True)[:most]]
        yield to_batch(rows, SURE)

    found = stage(views.where("quality IS NULL").select("doc_id", "text_x", "meta_x").mapInArrow(run, "view int, label int, odds double, code long, x binary").dropDuplicates(["view", "label", "code"]), "confident")
    out = []
    for v in range(2):
        part = [r for y in (0, 1) for r in found.where(f"view = {v} AND label = {y}").orderBy(F.desc("odds"), "code").limit(most).collect()]
        x = np.array([np.frombuffer(r["x"], np.float16) for r in part], np.float32).reshape(len(part), META if v == 0 else TEXT)
        out.append((x, np.array([float(r["label"]) for r in part])))
    return out


def smallest(ids: DataFrame, n: int) -> DataFrame:
    """The n ids of the smallest hashes: a fixed, even choice."""
    return ids.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)


def viewed(docs: DataFrame, quality: dict[int, int]) -> DataFrame:
    """Both views of every row, written, with the label of the ids in ``quality`` (of bounded size)."""
    shared = Shared(docs.sparkSession, quality)

    def make():
        known = shared.value

        def step(ids: list, texts: list, langs: list, sources: list, sizes: list) -> Iterator[tuple]:
            for doc_id, text, *meta in zip(ids, texts, langs, sources, sizes):
                yield doc_id, known.get(doc_id), text_view(text).astype(np.float16).tobytes(), meta_view(*meta).astype(np.float16).tobytes()

        return step

    return stage(arrow_map(view_columns(docs), make, "doc_id long, quality int, text_x binary, meta_x binary"), "views", "zstd")


def train(docs: DataFrame, labels: DataFrame, labelled: int = LABELLED, taught: int = TAUGHT) -> CoTrained | None:
    """Fit on at most ``labelled`` labelled rows and, in a round, ``taught`` confident ones of each view and label.

    Whole texts count, and all unlabelled rows are judged in every round. Rows that repeat a labelled doc_id are
    one row, that of the smallest views. None if the labelled rows hold fewer than ten of either class.
    """
    known = labels.where("quality IS NOT NULL AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    here = known.join(docs.select("doc_id").distinct(), "doc_id", "left_semi")
    quality = {r["doc_id"]: r["quality"] for r in smallest(here, labelled).collect()}
    if min(sum(q > 0 for q in quality.values()), sum(q <= 0 for q in quality.values())) < 10:
        return None
    views = viewed(docs, quality)
    got: dict[int, tuple] = {}
    for r in views.where("quality IS NOT NULL").collect():  # at most ``labelled`` ids
        mine = (r["text_x"], r["meta_x"], r["quality"])
        got[r["doc_id"]] = min(got.get(r["doc_id"], mine), mine)
    order = sorted(got, key=lambda k: (crc32(str(k).encode()), k))
    xs = [np.array([np.frombuffer(got[k][c], np.float16) for k in order], np.float32) for c in (0, 1)]
    rows = Labelled(xs, np.array([int(got[k][2] > 0) for k in order], np.int64))
    return co_train(rows, lambda model: confident(views, model, taught))


def view_columns(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), F.col("n_chars").cast("long").alias("n_chars"))


def classify(docs: DataFrame, model: CoTrained | None, threshold: float = THRESHOLD) -> DataFrame:
    """``(doc_id, p_good, kept)`` for every row, from its whole text and metadata.

    A null text or null metadata is a value like any other. Without a model
    every row is kept with a null probability. Extra columns are ignored.
    """
    shared = Shared(docs.sparkSession, model)

    def make():
        model = shared.value

        def step(ids: list, *columns: list) -> Iterator[tuple]:
            if model is None:
                yield from ((k, None, True) for k in ids)
                return
            for at in range(0, len(ids), 512):
                part = [c[at : at + 512] for c in columns]
                xs = [np.array([text_view(t) for t in part[0]]), np.array([meta_view(*m) for m in zip(*part[1:])])]
                for k, odds in zip(ids[at : at + 512], model.log_odds(xs)):
                    p = float(1 / (1 + np.exp(-np.clip(odds, -30, 30))))
                    yield k, p, p >= threshold

        return step

    return arrow_map(view_columns(docs), make, "doc_id long, p_good double, kept boolean")


def keep(docs: DataFrame, model: CoTrained | None, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` without the rows that the model rejects, judged where they lie (no join)."""
    shared, names = Shared(docs.sparkSession, model), docs.columns

    @F.pandas_udf("boolean")
    def good(text: pd.Series, lang: pd.Series, source: pd.Series, n_chars: pd.Series) -> pd.Series:
        if shared.value is None:
            return pd.Series(True, index=text.index)
        out = []
        for at in range(0, len(text), 512):
            part = slice(at, at + 512)
            meta = [meta_view(a, b, None if pd.isna(c) else int(c)) for a, b, c in zip(lang[part], source[part], n_chars[part])]
            odds = shared.value.log_odds([np.array([text_view(t) for t in text[part]]), np.array(meta)])
            out.append(1 / (1 + np.exp(-np.clip(odds, -30, 30))) >= threshold)
        return pd.Series(np.concatenate(out) if out else np.zeros(0, bool), index=text.index)

    return docs.where(good("text", F.col("lang").cast("string"), F.col("source").cast("string"), F.col("n_chars").cast("long"))).select(names)
