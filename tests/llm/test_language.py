import zlib

import numpy as np

from canopy.llm import language_id
from tests.conftest import SF

BIG = SF.replace("0.001", "0.01")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, score string"


def test_held_out_rows(spark):
    docs = spark.range(300).withColumnRenamed("id", "doc_id").withColumn("h", language_id.held_out())
    assert all(r["h"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in docs.collect())


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{BIG}/documents.parquet")
    codes = language_id.train(docs, ~language_id.held_out(), per_language=60)
    got = language_id.identify(docs, codes).join(docs.select("doc_id", "lang"), "doc_id").where(language_id.held_out()).collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in got]) > 0.98 and all(0 <= r["score"] <= 1 for r in got)


def test_labels_of_held_out_rows_do_not_matter(spark):
    docs = spark.read.parquet(f"{BIG}/documents.parquet").limit(300)
    other = docs.withColumn("lang", __import__("pyspark").sql.functions.expr("CASE WHEN crc32(cast(doc_id AS string)) % 4 = 2 THEN 'xx' ELSE lang END"))
    a, b = (language_id.identify(docs, language_id.train(d, ~language_id.held_out())) for d in (docs, other))
    assert a.exceptAll(b).isEmpty()


def test_unknown_texts(spark):
    docs = spark.read.parquet(f"{BIG}/documents.parquet")
    codes = language_id.train(docs, ~language_id.held_out(), per_language=30)
    odd = [(1, None), (2, ""), (3, "123 ... !!"), (4, "the"), (4, "the"), (None, "der und die"), (5, "a" * 300_000), (6, "\u00bd \u00b2 \u2167"), (7, "\u01c5")]
    frame = spark.createDataFrame([(k, t, "en", "s", 1, "clash") for k, t in odd], DOCS)
    got = language_id.identify(frame, codes).collect()
    assert len(got) == len(odd)
    assert [(r["lang_pred"], r["score"]) for r in got if r["doc_id"] in (1, 2, 3, 6)] == [("und", 0.0)] * 4
    assert all(r["lang_pred"] in codes.langs for r in got if r["doc_id"] not in (1, 2, 3, 6))
    assert [r["h"] for r in frame.where("doc_id IS NULL").select(language_id.held_out().alias("h")).collect()] == [False]
    assert language_id.train(docs.limit(0), language_id.held_out()) is None
    assert {r["lang_pred"] for r in language_id.identify(frame, None).collect()} == {"und"}
    assert language_id.identify(frame.limit(0), codes).count() == 0


def test_codewords_differ():
    for n in (1, 2, 4, 7, 12):
        words = language_id.codewords(n)
        assert len({tuple(w) for w in words}) == n and set(np.unique(words)) <= {-1.0, 1.0}
    four = language_id.codewords(4)
    assert four.shape == (4, 7) and min((four[a] != four[b]).sum() for a in range(4) for b in range(a)) == 4


def test_one_wrong_bit_is_corrected():
    codes = language_id.Codes.__new__(language_id.Codes)
    codes.langs, codes.words = list("abcd"), language_id.codewords(4)
    codes.weights, codes.bit_weight = np.vstack([np.eye(7), np.zeros(7)]).astype(np.float32), np.full(7, 1 / 7, np.float32)
    for k in range(4):
        for bit in range(7):
            margins = codes.words[k].copy()
            margins[bit] *= -1
            assert codes.decode(margins[None])[0][0] == k
