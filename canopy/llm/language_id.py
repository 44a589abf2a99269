"""Language identification with error-correcting output codes.

Each language has a codeword of +1 and -1. One linear classifier per bit,
over hashed byte n-grams, predicts that bit; a document's language is the one
whose codeword has the least weighted loss. Bits weigh by how well they do on
the training rows. A small gap to the runner-up is flagged as ambiguous.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.arrow import Shared, arrow_map
from canopy.llm.features import hashed_ngrams

DIMENSIONS, RIDGE = 2048, 1e-3
#: Training rows of each language, about (a hash picks them); the one bound on rows.
ROWS_PER_LANGUAGE = 1500
UNKNOWN, AMBIGUOUS = "und", 0.6
#: By Unicode category, so neither fractions nor Roman numerals are letters.
LETTER = regex.compile(r"\p{L}")


def vector(text: str, dimensions: int = DIMENSIONS) -> np.ndarray:
    """Hashed 1- to 3-grams of the bytes of the lower-cased whole text, square-rooted and of length one."""
    counts = np.sqrt(hashed_ngrams(text.lower().encode("utf-8", "replace"), dimensions))
    return (counts / max(float(np.linalg.norm(counts)), 1e-9)).astype(np.float32)


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """n rows of +1 and -1: every split of the languages for few, far random rows for many."""
    if n <= 7:
        splits = [(0, *rest) for size in range(n) for rest in combinations(range(1, n), size)][: 2 ** max(n - 1, 0) - 1] or [(0,)]
        return np.array([[1 if k in s else -1 for s in splits] for k in range(n)], np.float32)
    bits, rng = int(np.ceil(10 * np.log2(n))), np.random.default_rng(seed)
    tries = [np.where(rng.random((n, bits)) < 0.5, 1, -1).astype(np.float32) for _ in range(20)]
    return max(tries, key=lambda c: -np.max(c @ c.T - bits * np.eye(n)))


class Codes:
    """Bit classifiers, codewords and bit weights."""

    def __init__(self, texts: np.ndarray, langs: list[str]):
        self.langs = sorted(set(langs))
        self.words = codewords(len(self.langs))
        index = {x: k for k, x in enumerate(self.langs)}
        y = np.array([index[x] for x in langs], np.int64)
        x = np.hstack([texts, np.ones((len(texts), 1), np.float32)])
        share = 1 / np.maximum(np.bincount(y, minlength=len(self.langs)), 1)[y][:, None]  # every language counts the same
        gram = (x * share).T @ x + RIDGE * np.eye(x.shape[1], dtype=np.float32)
        target = self.words[y]
        self.weights = np.linalg.solve(gram, (x * share).T @ target).astype(np.float32)
        right = ((x @ self.weights) * target > 0).mean(axis=0) if len(texts) else np.zeros(self.words.shape[1])
        self.bit_weight = np.maximum(right - 0.5, 0.01)
        self.bit_weight = (self.bit_weight / self.bit_weight.sum()).astype(np.float32)

    def decode(self, texts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index and probability of the language of the least weighted logistic loss."""
        margins = texts @ self.weights[:-1] + self.weights[-1]
        loss = np.log1p(np.exp(-4 * margins[:, None, :] * self.words[None])) @ self.bit_weight
        odds = np.exp(4 * (loss.min(axis=1, keepdims=True) - loss))
        return loss.argmin(axis=1), odds.max(axis=1) / odds.sum(axis=1)


def held_out(id_col: str = "doc_id") -> Column:
    """By the id's checksum; a null id is not held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, trainable: Column, per_language: int = ROWS_PER_LANGUAGE) -> Codes | None:
    """Fit on about ``per_language`` rows of each language, chosen by a hash of the id.

    The rows chosen keep their whole texts; a task returns their vectors.
    """
    rows = docs.where(trainable & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return None
    share = F.create_map(*(F.lit(v) for k, n in counts.items() for v in (k, min(1.0, per_language / n))))
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    some = rows.where(draw < share[F.col("lang")]).select("lang", F.col("text"))

    def make():
        def step(langs: list, texts: list) -> Iterator[tuple]:
            for lang, text in zip(langs, texts):
                if LETTER.search(text):
                    yield lang, vector(text).astype(np.float16).tobytes()

        return step

    got = arrow_map(some, make, "lang string, x binary").collect()
    if not got:
        return None
    got.sort(key=lambda r: (r["lang"], r["x"]))
    return Codes(np.array([np.frombuffer(r["x"], np.float16) for r in got], np.float32), [r["lang"] for r in got])


def identify(docs: DataFrame, codes: Codes | None) -> DataFrame:
    """``(doc_id, lang_pred, score, ambiguous)`` for every row.

    ``und`` with score 0 stands for a null text, a text without letters, or no
    language to learn from. Whole texts count, in parts of bounded size; rows
    that repeat an id are judged one by one; languages of equal loss give the
    first in order of name. Extra columns are ignored, and empty input gives
    no row.
    """
    shared = Shared(docs.sparkSession, codes)

    def make():
        codes = shared.value

        def step(ids: list, texts: list) -> Iterator[tuple]:
            known = [k for k, t in enumerate(texts) if codes and t and LETTER.search(t)]
            best: dict[int, tuple] = {}
            for k in range(0, len(known), 256):
                part = known[k : k + 256]
                which, p = codes.decode(np.array([vector(texts[i]) for i in part]))
                best |= {i: (codes.langs[w], float(s)) for i, w, s in zip(part, which, p)}
            for k, doc_id in enumerate(ids):
                lang, score = best.get(k, (UNKNOWN, 0.0))
                yield doc_id, lang, score, lang == UNKNOWN or score < AMBIGUOUS

        return step

    return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), make, "doc_id long, lang_pred string, score double, ambiguous boolean")
