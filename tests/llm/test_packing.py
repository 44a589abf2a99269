import random
import zlib
from collections import defaultdict

import numpy as np
from tokenizers import Tokenizer

from canopy.llm import packing
from tests.conftest import SF

DOCS = "doc_id long, text string, lang string, source string, n_chars long, start string"


def plain_ids(tokenizer, text):
    return [*tokenizer.encode(text or "", add_special_tokens=False).ids, 1]


def check(rows, texts, window=packing.WINDOW):
    tokenizer = Tokenizer.from_file(packing.default_tokenizer())
    ids = {k: plain_ids(tokenizer, t) for k, t in texts.items()}
    by_doc, by_window = defaultdict(list), defaultdict(list)
    for r in rows:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] > 0 and r["doc_tokens"] == len(ids[r["doc_id"]])
        assert zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"]
        by_doc[r["doc_id"]].append((r["start"], r["length"]))
        by_window[r["sequence_id"]].append((r["offset"], r["length"]))
    assert set(by_doc) == set(ids)
    for k, parts in by_doc.items():
        at = 0
        for start, length in sorted(parts):
            assert start == at
            at += length
        assert at == len(ids[k])
    for parts in by_window.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= window and at & (at - 1) == 0  # full, or a power of two
    return by_window


def test_given_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    check(packing.pack(docs).collect(), texts)
    check(packing.pack(docs, shard_tokens=20_000).collect(), texts)


def test_odd_texts(spark):
    texts = {0: None, 1: "", 2: "x", 3: "word " * 9000, 4: "a\x1cb <|endoftext|> c", 5: " \n", 6: "Ünï-cödé !!", 7: "z" * 70_000}
    rows = [(k, t, "en", "s", 1, "clash") for k, t in texts.items()]
    check(packing.pack(spark.createDataFrame(rows, DOCS)).collect(), texts)
    assert packing.pack(spark.createDataFrame([], DOCS)).count() == 0
    twice = packing.pack(spark.createDataFrame([(1, "a b", "", "", 1, ""), (1, "a b", "", "", 1, ""), (None, "c", "", "", 1, "")], DOCS)).collect()
    assert sum(r["length"] for r in twice) == 8


def test_word_cache_equals_the_tokenizer():
    words, rng = packing.WordIds(packing.default_tokenizer()), random.Random(1)
    signs = "aAbZéÉßñİıſK’'sSdt.,!%$&_-<|>1٣0 \n\t\u00a0\u2003µÿŸŉǅΣσ\u0301ﬁlvermœ²½"
    for _ in range(3000):
        text = "".join(rng.choice(signs) for _ in range(rng.randint(0, 12)))
        assert words.of(text) == words.whole(text), repr(text)


def test_a_word_has_one_entry_in_any_case():
    """Every way to write a word had an entry of its own, which was tokenized again once the cache was full."""
    words = packing.WordIds(packing.default_tokenizer())
    text = "Straße STRASSE straße, STRAßE Élan élan ÉLAN it's IT'S"
    assert words.of(text) == words.whole(text) and {w for w in words if w.isalpha()} == {"straße", "strasse", "élan"}
    for odd in ("<|ENDOFTEXT|> A", "A<|endoftext|>B", "İ Ŀ ŉ Ÿ A"):
        assert words.of(odd) == words.whole(odd)


def test_cache_may_be_cleared(monkeypatch):
    monkeypatch.setattr(packing, "CACHE", 3)
    words = packing.WordIds(packing.default_tokenizer())
    text = "one two three four five six one two"
    assert words.of(text) == words.of(text) == words.whole(text)


def plain_bm25(docs, idf, mean, seed, terms):
    """Scores of all documents for the terms of largest weight of the seed."""
    def weight(t, d):
        tf = int((docs[d] == t).sum())
        return idf[t] * tf * (packing.K1 + 1) / (tf + packing.K1 * (1 - packing.B + packing.B * len(docs[d]) / mean)) if tf else 0.0

    own = sorted(set(docs[seed].tolist()), key=lambda t: -weight(t, seed))[:terms]
    return np.array([sum(weight(t, d) for t in own) for d in range(len(docs))])


def test_neighbours_are_those_of_bm25():
    rng = np.random.default_rng(3)
    docs = [rng.integers(0, 60, rng.integers(5, 40)).astype(np.uint16) for _ in range(25)]
    idf = rng.random(60) + 0.1
    mean = float(np.mean([len(d) for d in docs]))
    shard = packing.Shard(docs, idf, mean)
    for seed in range(25):
        used = np.zeros(25, bool)
        used[[seed, (seed + 1) % 25]] = True
        score = plain_bm25(docs, idf, mean, seed, packing.QUERY_TERMS)
        score[used] = 0
        got = shard.neighbours(seed, used)
        assert set(got.tolist()) == set(np.flatnonzero(score).tolist()) and np.allclose(score[got], np.sort(score[score > 0])[::-1], rtol=1e-4)


def test_related_documents_share_windows():
    rng = np.random.default_rng(4)
    docs, topic = [], []
    for k in range(40):
        topic.append(k % 4)
        docs.append((rng.integers(0, 30, 100) + 30 * (k % 4)).astype(np.uint16))
    shard = packing.Shard(docs, np.ones(120), 100.0, window=1000)
    for window in shard.windows():
        assert len({topic[d] for d, _, _ in window}) <= 2


def test_powers():
    assert packing.powers(1337) == [1024, 256, 32, 16, 8, 1] and packing.powers(0) == []
    window = [(0, 5, 3), (1, 0, 4)]
    assert list(packing.cut(window, [4, 2, 1])) == [[(0, 5, 3), (1, 0, 1)], [(1, 1, 2)], [(1, 3, 1)]]
