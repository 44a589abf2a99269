"""Quality rules with n-gram perplexity under modified Kneser-Ney smoothing.

The n-grams are of characters, up to ``ORDER``, inside white-space words with a
start and an end mark. The model is a table with a row for every n-gram of the
corpus: it grows with the input, and no part of it is broadcast or collected
but the four counts of counts of each order.

Documents are coded once, in blocks: a block holds the distinct words of some
documents of one task, and each document its word numbers and counts. Only the
n-gram that predicts a character with all that may stand before is counted, as
sums over blocks; modified counts of lower orders follow from the distinct ones
above. Every block then gets the probabilities of its own n-grams as an array
in the order of their sorted 64-bit hashes, in which its words are looked up,
and its documents sum their words. So texts are never shuffled.

Each document gets a log-perplexity per word, drawn towards its language's
median the shorter it is. A language's band reaches ``REACH`` interquartile ranges beyond
the quartiles on both sides; documents outside are rejected.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from canopy.arrow import ROWS, parts, to_batch
from canopy.llm.columns import text_bytes
from canopy.storage import stage

ORDER = 4
#: From this order on, n-grams seen once are pruned: else a document of noise knows itself by heart.
PRUNED = 2
#: A block ends with the document that brings it over so many distinct words, bytes of coded documents or documents.
WORDS, CODED, DOCUMENTS = 250_000, 1 << 24, 50_000
# fixed values: no word holds these
START, END = " ", "\n"
#: Words of evidence that the language's median counts as, the band's reach, and the least share of the median that it reaches.
PRIOR, REACH, FLOOR = 40, 2.5, 0.02
SYMBOLS = "#*$%&|<>"
LEAST_WORDS, MOST_REPEATED = 10, 20
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def keys(words: list[bytes]) -> tuple[str, np.ndarray, np.ndarray, np.ndarray]:
    """All words with marks in one string; for every character after a start mark
    its word, the hash of the n-gram that ends there and the n-gram's length.

    The n-gram has ``ORDER`` characters, or fewer where the word starts.
    """
    texts = [w.decode("utf-8", "replace") for w in words]
    length = np.fromiter(map(len, texts), np.int64, len(texts)) + 2
    marked = "".join(f"{START}{t}{END}" for t in texts)
    codes = np.frombuffer(marked.encode("utf-32-le"), np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(texts)), length)
    place = np.arange(len(codes)) - np.repeat(np.cumsum(length) - length, length)
    key = np.zeros(len(codes), np.uint64)
    for k in range(ORDER):
        before = np.concatenate([np.zeros(k, np.uint64), codes[: max(len(codes) - k, 0)]])[: len(codes)]
        mixed = (key ^ before + np.uint64(k + 1)) * MULTIPLIER
        key = np.where(place >= k, mixed ^ mixed >> np.uint64(29), key)
    return marked, owner, key, np.minimum(place + 1, ORDER)


def in_parts(words: list[bytes], most: int = 250_000) -> Iterator[list[bytes]]:
    """Lists of words of about ``most`` bytes in all."""
    part, size = [], 0
    for w in words:
        part.append(w)
        size += len(w) + 2
        if size >= most:
            yield part
            part, size = [], 0
    if part:
        yield part


def repeated_words(words: list[bytes], size: int = 5) -> int:
    """Words in a window of ``size`` words that the text has twice or more."""
    n = len(words) - size + 1
    if n < 2:
        return 0
    h = np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64)
    windows = np.zeros(n, np.uint64)
    for k in range(size):
        windows = (windows ^ h[k : k + n]) * MULTIPLIER
        windows ^= windows >> np.uint64(31)
    order = np.argsort(windows, kind="stable")
    same = windows[order][1:] == windows[order][:-1]
    if not same.any():
        return 0
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, len(words))
    a, b = order[:-1][same], order[1:][same]
    if any((ids[a + k] != ids[b + k]).any() for k in range(size)):  # different windows of one hash: number them instead
        windows = ids[:n]
        for k in range(1, size):
            windows = np.unique(windows * len(number) + ids[k : k + n], return_inverse=True)[1]
        order = np.argsort(windows, kind="stable")
        same = windows[order][1:] == windows[order][:-1]
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    cover = np.zeros(len(words) + 1, np.int64)
    starts = np.flatnonzero(twice)
    np.add.at(cover, starts, 1)
    np.add.at(cover, starts + size, -1)
    return int((np.cumsum(cover)[:-1] > 0).sum())


def base_measures(text: bytes, words: list[bytes]) -> tuple[int, int, int, int]:
    """word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    lines, n_lines = set(), 0
    for line in text.split(b"\n"):
        if line and not line.isspace():
            n_lines += 1
            lines.add(line)
    chars = sum(map(len, (w.decode("utf-8", "replace") for w in words))) if not text.isascii() else sum(map(len, words))
    return chars, sum(map(text.count, (s.encode() for s in SYMBOLS))), n_lines - len(lines), repeated_words(words)


MEASURED = "doc_id long, lang string, text_hash long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"
MEASURES = f"{MEASURED}, log_perplexity double"
#: A row is a document (``body``) or a block (``words`` and its n-grams by sorted hash).
CODED_ROWS = f"block long, {MEASURED}, body binary, words binary, gram array<string>, n array<long>"


def pack(ids: np.ndarray, counts: np.ndarray) -> bytes:
    """Word numbers and their counts, by planes of as many bytes as they need."""
    order = np.argsort(ids)
    out = [b"", b""]
    for k, values in enumerate((np.diff(ids[order], prepend=0), counts[order])):
        planes = (int(values.max(initial=0)).bit_length() + 7) // 8
        out[k] = bytes([planes]) + values.astype("<i8").view(np.uint8).reshape(-1, 8)[:, :planes].T.tobytes()
    return len(ids).to_bytes(4, "little") + out[0] + out[1]


def unpack(body: bytes) -> tuple[np.ndarray, np.ndarray]:
    size, at, out = int.from_bytes(body[:4], "little"), 4, []
    for _ in range(2):
        planes, values = body[at], np.zeros(size, np.int64)
        for k in range(planes):
            values |= np.frombuffer(body, np.uint8, size, at + 1 + k * size).astype(np.int64) << 8 * k
        at += 1 + planes * size
        out.append(values)
    return np.cumsum(out[0]), out[1]


class Block:
    """The distinct words of some documents, numbered as they come, with their counts."""

    def __init__(self):
        self.number: defaultdict[bytes, int] = defaultdict()
        self.number.default_factory = self.number.__len__
        self.counts, self.coded, self.documents = np.zeros(1024, np.int64), 0, 0

    def add(self, words: list[bytes]) -> bytes:
        tally = Counter(words)
        ids = np.fromiter(map(self.number.__getitem__, tally), np.int64, len(tally))
        counts = np.fromiter(tally.values(), np.int64, len(tally))
        if len(self.number) > len(self.counts):
            self.counts = np.concatenate([self.counts, np.zeros(2 * len(self.number) - len(self.counts), np.int64)])
        self.counts[ids] += counts
        body = pack(ids, counts)
        self.coded += len(body)
        self.documents += 1
        return body

    def full(self) -> bool:
        return len(self.number) > WORDS or self.coded > CODED or self.documents >= DOCUMENTS

    def grams(self) -> tuple[list[str], np.ndarray]:
        """The n-grams of all words and their counts, in the order of their hashes."""
        found, begin = [], 0
        for part in in_parts(list(self.number)):
            weight = self.counts[begin : begin + len(part)]
            begin += len(part)
            marked, owner, key, length = keys(part)
            ends = np.flatnonzero(length > 1)
            hashes = np.unique(key[ends])
            at = np.searchsorted(hashes, key[ends])
            first = np.zeros(len(hashes), np.int64)
            first[at] = ends
            n = np.bincount(at, weights=weight[owner[ends]], minlength=len(hashes)).astype(np.int64)
            found.append((hashes, n, np.array([marked[e - k + 1 : e + 1] for e, k in zip(first.tolist(), length[first].tolist())], object)))
        if not found:
            return [], np.zeros(0, np.int64)
        hashes, first, of = np.unique(np.concatenate([f[0] for f in found]), return_index=True, return_inverse=True)
        n = np.zeros(len(hashes), np.int64)
        np.add.at(n, of, np.concatenate([f[1] for f in found]))
        return np.concatenate([f[2] for f in found])[first].tolist(), n


def code(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Base measures and coded words of every row, and a row for each block; not yet written.

    A block is numbered by its task, so the rows hold together only once written.
    """
    fields = to_arrow_schema(StructType.fromDDL(CODED_ROWS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        number, block, rows = TaskContext.get().partitionId() << 32, Block(), []

        def close() -> tuple:
            return (number, *[None] * 9, zstandard.compress(b"\n".join(block.number)), *block.grams())

        for batch in batches:
            for part in parts(batch):
                for doc_id, lang, text_hash, text in zip(*(c.to_pylist() for c in part.columns)):
                    words = text.split()
                    rows.append((number, doc_id, lang, text_hash, len(words), *base_measures(text, words), block.add(words), None, None, None))
                    if block.full():
                        rows.append(close())
                        number, block = number + 1, Block()
                    if len(rows) >= ROWS:
                        yield to_batch(rows, fields)
                        rows = []
        if block.documents:
            rows.append(close())
        if rows:
            yield to_batch(rows, fields)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.xxhash64(text_col).alias("text_hash"), text_bytes(text_col)).mapInArrow(run, CODED_ROWS)


def count_grams(coded: DataFrame) -> DataFrame:
    """Counts ``(gram, n)`` of the longest n-grams of coded documents."""
    return coded.where("words IS NOT NULL").select(F.inline(F.arrays_zip("gram", "n"))).groupBy("gram").agg(F.sum("n").alias("n"))


def all_orders(counted: DataFrame) -> DataFrame:
    """Modified counts ``(m, gram, n)`` of the n-grams of every order.

    Below the highest order, they are the distinct characters that stand before
    the n-gram; those with the start mark have none and keep their counts.
    """
    longer = stage(counted.select(F.length("gram").cast("int").alias("m"), "gram", "n"), "ngrams")
    anchored, out = longer, longer.where(F.col("m") == ORDER)
    longer = out
    for m in range(ORDER - 1, 0, -1):
        shorter = longer.groupBy(F.substring("gram", 2, m).alias("gram")).agg(F.count_if(F.col("n") > 0).alias("n"))
        longer = stage(shorter.select(F.lit(m).alias("m"), "gram", "n").union(anchored.where(F.col("m") == m)), "ngrams")
        out = out.union(longer)
    return out


def discounts(n1: int, n2: int, n3: int, n4: int) -> list[float]:
    """Of counts 0, 1, 2 and 3 or more, from the counts of counts."""
    n1, n2, n3, n4 = (max(n, 1) for n in (n1, n2, n3, n4))
    y = n1 / (n1 + 2 * n2)
    return [0.0, *(min(max(k + 1 - (k + 2) * y * b / a, 0.05), top) for k, (a, b, top) in enumerate(((n1, n2, 0.95), (n2, n3, 1.9), (n3, n4, 2.9))))]


def train(counted: DataFrame) -> DataFrame:
    """Interpolated probabilities ``(gram, logp)`` of the longest n-grams, those that are counted.

    Rows of count 0 are n-grams that are to be judged but were not in the corpus.
    """
    adjusted = all_orders(counted)
    of_counts = adjusted.groupBy("m").agg(*(F.count_if(F.col("n") == k).alias(f"n{k}") for k in range(1, 5)), F.count_if(F.col("n") > 0).alias("seen")).collect()
    floor = 1 / (sum(r["seen"] for r in of_counts if r["m"] == 1) + 1)
    taken = F.lit(0.0)
    for r in of_counts:
        by_count = F.array(*map(F.lit, discounts(*(r[f"n{k}"] for k in range(1, 5)))))
        taken = F.when(F.col("m") == r["m"], by_count[F.least("n", F.lit(3)).cast("int")]).otherwise(taken)
    # what is pruned leaves its whole mass to the back-off
    taken = F.when((F.col("m") >= PRUNED) & (F.col("n") <= 1), F.col("n").cast("double")).otherwise(taken)
    priced = adjusted.select("m", "gram", "n", taken.alias("taken"), F.expr("substring(gram, 1, m - 1)").alias("context"))
    contexts = priced.groupBy("context").agg(F.sum("n").alias("total"), F.sum("taken").alias("freed"))
    seen = F.col("total") > 0
    shares = stage(
        priced.join(contexts, "context").select(
            "m",
            "gram",
            F.when(seen, F.greatest(F.col("n") - F.col("taken"), F.lit(0.0)) / F.col("total")).otherwise(0.0).alias("own"),
            F.when(seen, F.col("freed") / F.col("total")).otherwise(1.0).alias("back_off"),
        ),
        "shares",
    )
    lower, model = None, None
    for m in range(1, ORDER + 1):
        order = shares.where(F.col("m") == m)
        if lower is None:
            order = order.withColumn("below", F.lit(floor))
        else:
            order = order.withColumn("suffix", F.substring("gram", 2, m)).join(lower.select(F.col("gram").alias("suffix"), F.col("p").alias("below")), "suffix")
        lower = stage(order.select("m", "gram", (F.col("own") + F.col("back_off") * F.col("below")).alias("p")), "probabilities")
        longest = lower.where((F.col("m") == ORDER) | F.startswith("gram", F.lit(START)))
        chosen = longest.select("gram", F.log(F.greatest("p", F.lit(1e-300))).alias("logp"))
        model = chosen if model is None else model.union(chosen)
    return model


def word_scores(words: list[bytes], logp: np.ndarray) -> np.ndarray:
    """Log-probability of each word with its end mark; ``logp`` is in the order of the hashes of all their n-grams."""
    hashes = [np.zeros(0, np.uint64)]
    for part in in_parts(words):
        _, _, key, length = keys(part)
        hashes.append(np.unique(key[length > 1]))
    hashes, out = np.unique(np.concatenate(hashes)), [np.zeros(0)]
    for part in in_parts(words):
        _, owner, key, length = keys(part)
        ends = length > 1
        out.append(np.bincount(owner[ends], weights=logp[np.searchsorted(hashes, key[ends])], minlength=len(part)))
    return np.concatenate(out)


def measures(docs: DataFrame, reference: DataFrame | None = None) -> DataFrame:
    """Base measures of every row, and its log-perplexity per word (null without words).

    The model is that of ``reference``, or of the documents themselves.
    """
    coded = stage(code(docs), "coded")
    counted = count_grams(coded)
    if reference is not None:
        corpus = count_grams(stage(code(reference), "coded"))
        counted = corpus.union(counted.withColumn("n", F.lit(0).cast("long"))).groupBy("gram").agg(F.sum("n").alias("n"))
    model = train(counted)
    wanted = coded.where("words IS NOT NULL").select("block", F.posexplode("gram").alias("k", "gram"))
    known = wanted.join(model, "gram").select("block", F.col("k").cast("int").alias("k"), F.col("logp").cast("float").alias("logp"), F.lit(None).cast("binary").alias("words"))
    blocks = coded.where("words IS NOT NULL").select("block", F.lit(-1).alias("k"), F.lit(0.0).cast("float").alias("logp"), "words").unionByName(known)
    fields = to_arrow_schema(StructType.fromDDL(MEASURES))

    def score(rows: pa.Table, block: pa.Table) -> pa.Table:
        import zstandard

        place, found = block.column("k").to_numpy(), block.column("logp").to_numpy()
        words = zstandard.decompress(block.column("words").drop_null()[0].as_py()).split(b"\n")
        each = word_scores([w for w in words if w], found[np.argsort(place)][1:].astype(np.float64))  # the words' own row is first
        logp = []
        for body in rows.column("body").to_pylist():
            ids, counts = unpack(body)
            logp.append(-float(each[ids] @ counts) / int(counts.sum()) if len(ids) else None)
        return pa.table([*(rows.column(f.name) for f in list(fields)[:-1]), pa.array(logp, pa.float64())], schema=fields)

    rows = coded.where("body IS NOT NULL").drop("words", "gram", "n").withColumnRenamed("block", "in_block")
    return rows.groupBy("in_block").cogroup(blocks.groupBy("block")).applyInArrow(score, MEASURES)


def bands(measured: DataFrame, reach: float = REACH) -> DataFrame:
    """Per language: median and the lower and upper bound of the shrunken log-perplexity.

    Every text counts once, however many copies it has. A band reaches at least
    ``FLOOR`` of the median beyond the quartiles, so near copies of one text
    cannot close it around themselves.
    """
    texts = measured.where("n_words > 0").groupBy("lang", "text_hash").agg(F.min("log_perplexity").alias("log_perplexity"))
    quarters = texts.groupBy("lang").agg(F.percentile_approx("log_perplexity", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 10_000).alias("q"))
    margin = F.greatest(F.lit(reach) * (F.col("q")[2] - F.col("q")[0]), F.lit(FLOOR) * F.col("q")[1])
    return quarters.select("lang", F.col("q")[1].alias("mid"), (F.col("q")[0] - margin).alias("low"), (F.col("q")[2] + margin).alias("high"))


def judge(docs: DataFrame, reference: DataFrame | None = None, reach: float = REACH) -> DataFrame:
    """Base measures, perplexity under the model of ``reference`` or ``docs``, band and verdict of every row.

    A null text has no words and fails the base rules, like an empty one. A
    null language is a language of its own. Rows that repeat a doc_id are
    judged one by one; extra columns are ignored; empty input gives no row.
    """
    measured = stage(measures(docs, reference), "measures")
    shrunk = (F.col("log_perplexity") * F.col("n_words") + F.col("mid") * PRIOR) / (F.col("n_words") + PRIOR)
    bound = bands(measured, reach).withColumnRenamed("lang", "band_lang")
    failed = (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * F.col("n_words"))
    return (
        measured.join(bound, F.col("lang").eqNullSafe(F.col("band_lang")), "left")
        .withColumn("banded", shrunk)
        .withColumn("base_failed", failed)
        .withColumn("kept", ~failed & F.coalesce(F.col("banded").between(F.col("low"), F.col("high")), F.lit(True)))
        .drop("band_lang")
    )
