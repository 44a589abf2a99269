"""Lexical retrieval packing: BM25 neighbours of a seed fill its window.

1. Every text is tokenized once; ids go to a written table together with each
   task's document frequencies of the (fixed) vocabulary.
2. Documents are range-partitioned by a lexical key, so that near copies and
   common phrases share an index shard. The id of the document breaks ties,
   which splits a key of any size over shards.
3. Each shard builds a BM25 inverted index over its documents, with document
   frequencies of the whole corpus. A seed document queries it; the unused
   neighbours, best first, fill the window. The last one is cut at the edge
   and its rest seeds the next window, so windows are full. The end of a shard
   is cut into windows whose sizes are powers of two, which need no padding.
"""

from __future__ import annotations

import re
import struct
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import ROWS, Shared, arrow_map, parts, to_batch
from canopy.storage import stage

WINDOW, END_ID, VOCABULARY = 2048, 1, 49_408
#: Tokens that one index shard holds on average.
SHARD_TOKENS = 2_000_000
#: Terms of a seed that query the index, and the two BM25 parameters.
QUERY_TERMS, K1, B = 8, 1.2, 0.75
#: Entries of a worker's word cache before it starts afresh.
CACHE = 700_000
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, window_tokens long"


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


#: ASCII signs; letters whose lower case and composed form are the same for any library.
SIGNS = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum())
PLAIN = re.compile(r"[\x00-\u012f\u0131-\u0137\u014a-\u017e]*")


def byte_letters() -> dict[int, int]:
    """The byte-level alphabet: visible Latin-1 stands for itself, other bytes for code points from 256 on."""
    visible = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = [b for b in range(256) if b not in visible]
    return {b: 256 + k for k, b in enumerate(hidden)}


class WordIds(dict):
    """Token ids of a text as little-endian 16-bit bytes (the vocabulary fits), through a cache of words.

    The vocabulary's pre-tokenizer never joins characters over white space, and
    parts letters from the signs behind them, so the ids of stems and signs
    joined are the ids of the text. A stem of plain letters is one unit of the
    tokenizer's model and is given to it as such. Anything unusual, such as a
    possible special token, is tokenized as it stands; so are whole texts with
    control characters that only Python takes for white space. Texts of plain
    letters without special tokens are lower-cased at once, so a word has one
    entry, however it is written.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        model = self.tokenizer.model
        if hasattr(model, "_resize_cache"):  # a word is asked for once, so the model's own cache only costs time
            model._resize_cache(0)
        self.unit, self.letters = model.tokenize, byte_letters()

    def __missing__(self, word: str) -> bytes:
        if word.isalpha() and word.isascii() and word.islower():
            found = [t.id for t in self.unit(word)]
            self[word] = ids = struct.pack(f"<{len(found)}H", *found)
            return ids
        stem = word.rstrip(SIGNS)
        if not stem or "<|" in word or not stem[-1].isalnum() or not (stem.isascii() or PLAIN.fullmatch(stem)):
            ids = self.whole(word)
        elif len(stem) < len(word):
            ids = self[stem.lower()] + self[word[len(stem) :]]
        elif (low := word.lower()) != word:
            ids = self[low]
        elif word.isalpha():
            shown = word if word.isascii() else word.encode().decode("latin-1").translate(self.letters)
            found = [t.id for t in self.unit(shown)]
            ids = struct.pack(f"<{len(found)}H", *found)
        else:
            ids = self.whole(word)
        self[word] = ids
        return ids

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u2").tobytes()

    def of(self, text: str) -> bytes:
        if len(self) > CACHE:
            self.clear()
        if "\x1c" in text or "\x1d" in text or "\x1e" in text or "\x1f" in text:
            return self.whole(text)
        if "<|" not in text and (text.isascii() or PLAIN.fullmatch(text)):
            text = text.lower()
        return b"".join(map(self.__getitem__, text.split()))


def lexical_key(ids: np.ndarray) -> int:
    """The smallest hash of two neighbouring ids; near copies mostly agree on it."""
    pairs = (ids[:-1].astype(np.uint32) << np.uint32(16) | ids[1:]) if len(ids) > 1 else ids.astype(np.uint32)
    return int((pairs * np.uint32(2_654_435_761)).min())


def tokenized(docs: DataFrame, tokenizer: str) -> DataFrame:
    """Document rows, and a row with the document frequencies of each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, seen = WordIds(tokenizer), np.zeros(VOCABULARY, np.int64)
        schema = pa.schema([("doc_id", pa.int64()), ("key", pa.int64()), ("n", pa.int64()), ("ids", pa.binary()), ("is_doc", pa.bool_())])
        end = np.array([END_ID], "<u2").tobytes()
        for batch in batches:
            rows = []
            for doc_id, own in ((d, i) for part in parts(batch) for d, i in zip(part.column(0).to_pylist(), map(words.of, part.column(1).to_pylist()))):
                ids = np.frombuffer(own + end, "<u2")
                seen[ids] += 1  # once for each distinct id: repeated places are not added up
                rows.append((doc_id, lexical_key(ids), len(ids), own + end, True))
                if len(rows) >= ROWS:
                    yield to_batch(rows, schema)
                    rows = []
            yield to_batch(rows, schema)
        yield to_batch([(None, 0, 0, seen.tobytes(), False)], schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "doc_id long, key long, n long, ids binary, is_doc boolean")


def document_frequencies(tokens: DataFrame) -> np.ndarray:
    """Of every id of the vocabulary, over all documents; its size is fixed."""

    def make():
        def step(vectors: list) -> Iterator[tuple]:
            for v in vectors:
                counts = np.frombuffer(v, np.int64)
                for k in np.flatnonzero(counts):
                    yield int(k), int(counts[k])

        return step

    found = arrow_map(tokens.where("NOT is_doc").select("ids"), make, "id int, n long").groupBy("id").agg(F.sum("n").alias("n")).collect()
    out = np.zeros(VOCABULARY, np.int64)
    for r in found:
        out[r["id"]] = r["n"]
    return out


class Shard:
    """A BM25 inverted index over some documents, and the windows packed from it."""

    def __init__(self, docs: list[np.ndarray], idf: np.ndarray, mean: float, window: int = WINDOW, terms: int | None = QUERY_TERMS):
        self.docs, self.idf, self.window, self.terms = docs, idf, window, terms
        self.n = n = len(docs)
        length = np.fromiter(map(len, docs), np.int64, n)
        wide = np.uint32 if n * len(idf) < 1 << 32 else np.uint64
        owner = np.repeat(np.arange(n, dtype=wide), length)
        flat = np.concatenate(docs).astype(wide) if n else np.zeros(0, wide)
        pairs = np.sort(flat * wide(n) + owner)
        at = np.flatnonzero(np.concatenate([[True], pairs[1:] != pairs[:-1]])) if len(pairs) else np.zeros(0, np.int64)
        tf = np.diff(at, append=len(pairs))
        term, doc = np.divmod(pairs[at], wide(max(n, 1)))
        self.doc = doc.astype(np.int32)
        k = (K1 * (1 - B + B * length / mean)).astype(np.float32)
        self.weight = idf.astype(np.float32)[term] * (tf * np.float32(K1 + 1) / (tf + k[self.doc])).astype(np.float32)
        self.first = np.searchsorted(term, np.arange(len(idf) + 1)).tolist()
        # entries by document, for the terms that a seed asks for
        self.by_doc = np.argsort(doc.astype(np.uint16) if n < 1 << 16 else doc, kind="stable")
        self.doc_first = np.concatenate([[0], np.cumsum(np.bincount(self.doc, minlength=n))]).tolist()
        self.term = term.astype(np.int32)

    def neighbours(self, seed: int, used: np.ndarray) -> np.ndarray:
        """Unused documents that share a query term with the seed, best first."""
        score = np.zeros(self.n, np.float32)
        own = self.by_doc[self.doc_first[seed] : self.doc_first[seed + 1]]
        if self.terms is not None and len(own) > self.terms:
            own = own[np.argpartition(-self.weight[own], self.terms)[: self.terms]]
        for t in self.term[own].tolist():
            at = slice(self.first[t], self.first[t + 1])
            score[self.doc[at]] += self.weight[at]
        score[used] = 0
        found = np.flatnonzero(score)
        return found[np.argsort(-score[found], kind="stable")]

    def windows(self) -> Iterator[list[tuple[int, int, int]]]:
        """Windows as (document, start, length) pieces; every one but the last is full."""
        used, unused_from = np.zeros(self.n, bool), 0
        window: list[tuple[int, int, int]] = []
        room, seed = self.window, None
        queue: list[int] = []
        while True:
            if seed is None:
                while unused_from < self.n and used[unused_from]:
                    unused_from += 1
                if unused_from == self.n:
                    break
                seed, start = unused_from, 0
                used[seed] = True
            doc, at = seed, start
            while doc is not None:
                size = len(self.docs[doc])
                while size - at >= room:
                    window.append((doc, at, room))
                    yield window
                    at, window, room = at + room, [], self.window
                    queue = []
                if at < size:
                    window.append((doc, at, size - at))
                    room -= size - at
                if not queue:
                    queue = self.neighbours(doc, used)[::-1].tolist()
                doc, at = None, 0
                if queue:
                    doc = queue.pop()
                    used[doc] = True
            seed = None
        if window:
            yield window


def powers(n: int) -> list[int]:
    return [1 << b for b in reversed(range(n.bit_length())) if n >> b & 1]


def cut(window: list[tuple[int, int, int]], sizes: list[int]) -> Iterator[list[tuple[int, int, int]]]:
    """One window cut into windows of the given sizes, in order."""
    rest, window = list(reversed(window)), []
    for size in sizes:
        out, room = [], size
        while room:
            doc, start, length = rest.pop()
            take = min(room, length)
            out.append((doc, start, take))
            if take < length:
                rest.append((doc, start + take, length - take))
            room -= take
        yield out


def pack(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, shard_tokens: int = SHARD_TOKENS, terms: int | None = QUERY_TERMS) -> DataFrame:
    """Pieces of all documents in sequences of at most ``window`` tokens.

    Every row counts as a document of its own, with the end id behind its
    text; a null text is empty, so it is packed as its end id alone. Each id
    lies in exactly one piece. Sequences are ``window`` long, or a smaller
    power of two at the end of a shard. Empty input gives no piece. A null
    doc_id is carried; extra columns are ignored. Of neighbours with equal
    scores, the first in the order of the shard is taken; a text longer than a
    window fills several, and its rest is the next one's seed.

    ``terms`` is the number of a seed's heaviest terms that query the index
    (None: all of them). An index shard holds about ``shard_tokens``, and ends
    with the row that brings it over twice as many, so neither equal keys nor
    long texts make one larger than that and a document.
    """
    tokens = stage(tokenized(docs, tokenizer or default_tokenizer()), "tokens", "zstd")
    total = tokens.where("is_doc").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("n")).first()
    n_docs, n_tokens = total["docs"], total["n"] or 0
    df = document_frequencies(tokens)
    spark = docs.sparkSession
    idf = Shared(spark, np.log1p((n_docs - df + 0.5) / (df + 0.5)))  # one number for each id of the vocabulary
    mean = n_tokens / max(n_docs, 1)
    shards = max(1, -(-n_tokens // shard_tokens))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([(name, pa.int64()) for name in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "window_tokens")])
        number, out = TaskContext.get().partitionId() << 32, []
        for names, ids in shards_of(batches, 2 * shard_tokens):
            for full in Shard(ids, idf.value, mean, window, terms).windows():
                size = sum(p[2] for p in full)
                for pieces in [full] if size == window else cut(full, powers(size)):
                    offset, size = 0, sum(p[2] for p in pieces)
                    for doc, start, length in pieces:
                        code = crc32(ids[doc][start : start + length].astype("<u4").tobytes())
                        out.append((names[doc], start, length, code, len(ids[doc]), number, offset, size))
                        offset += length
                    number += 1
                if len(out) >= ROWS:
                    yield to_batch(out, schema)
                    out = []
        if out:
            yield to_batch(out, schema)

    # the place in the written table parts rows of equal key and id
    dealt = tokens.where("is_doc").select("doc_id", "ids", "key", F.monotonically_increasing_id().alias("place"))
    dealt = dealt.repartitionByRange(shards, "key", "doc_id", "place").sortWithinPartitions("key", "doc_id", "place")
    return dealt.select("doc_id", "ids").mapInArrow(run, PIECES)


def shards_of(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[tuple[list, list[np.ndarray]]]:
    """Ids and tokens of the documents of a task, in lists of at most ``most`` tokens and one document more."""
    names, ids, held = [], [], 0
    for batch in batches:
        for doc_id, own in zip(*(c.to_pylist() for c in batch.columns)):
            names.append(doc_id)
            ids.append(np.frombuffer(own, "<u2"))
            held += len(ids[-1])
            if held > most:
                yield names, ids
                names, ids, held = [], [], 0
    if names:
        yield names, ids
