import re
from collections import Counter

import numpy as np

from canopy.llm import cotraining, features, kneser_ney
from tests.conftest import SF
from tests.llm import kneser_ney_reference

DOCS = "doc_id long, text string, lang string, source string, n_chars long, n_words string"


def plain_measures(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    windows = Counter(tuple(words[k : k + 5]) for k in range(len(words) - 4))
    marked = {k + j for k in range(len(words) - 4) if windows[tuple(words[k : k + 5])] > 1 for j in range(5)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(marked)


ODD = ["", None, " \n ", "one", "a b c d e a b c d e", "x " * 300, "é à | # ü\n\n|\n|\né\n", "a\u00a0b c\x1cd", "line\nline\nline\r\nline", "ab " * 60_000]


def test_base_measures_against_brute_force(spark):
    rows = [(k, t, "en" if k % 2 else None, "s", 1, "clash") for k, t in enumerate(ODD)]
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").selectExpr("doc_id + 100 AS doc_id", "text", "lang", "source", "n_chars", "'x' AS n_words")
    docs = spark.createDataFrame(rows, DOCS).unionByName(docs)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = kneser_ney.judge(docs).collect()
    assert len(got) == len(texts)
    for r in got:
        want = plain_measures(texts[r["doc_id"]])
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want, r
        assert r["base_failed"] == (want[0] < 10 or 100 * want[4] > 20 * want[0])
        assert not (r["base_failed"] and r["kept"])


def test_empty_table(spark):
    assert kneser_ney.judge(spark.createDataFrame([], DOCS)).count() == 0


def test_probabilities_sum_to_one(spark):
    texts = ["the cat sat on the mat", "the hat on the cat", "a mat"]
    model = kneser_ney_reference.train(spark.createDataFrame([(1, None, t) for t in texts], "doc_id long, lang string, text string"))
    # after any context, the probabilities of all characters (with an unseen one) sum to one
    alphabet = sorted(set("".join(texts)) - {" "})
    for stem in ("", "t", "th", "ca", "zz"):
        words = [(stem + c).encode() for c in alphabet]
        whole = model.score(words)
        # the word's last letter and its end mark are scored; take the end mark off again
        total = 0.0
        for w, logp in zip(words, whole):
            owner, orders = kneser_ney_reference.grams([w])
            total += np.exp(position_scores(model, w)[len(stem)])
        total += np.exp(position_scores(model, stem.encode())[len(stem)])
        assert 0.9 < total <= 1.0 + 1e-6, (stem, total)


def position_scores(model, word):
    """Log-probability of each predicted character, by the definition, one at a time."""
    owner, orders = kneser_ney_reference.grams([word])
    out = []
    for k in range(len(owner)):
        logp = 0.0
        for m in range(kneser_ney.ORDER, 0, -1):
            gram, context, ok = (x[k] for x in orders[m - 1])
            if not ok:
                continue
            at = np.flatnonzero(model.gram[m] == gram)
            if len(at):
                logp += model.logp[m][at[0]]
                break
            c = np.flatnonzero(model.context[m] == context)
            logp += model.back_off[m][c[0]] if len(c) else 0.0
        else:
            logp += model.floor
        out.append(logp)
    return out


def test_scores_are_sums_of_positions(spark):
    model = kneser_ney_reference.train(spark.read.parquet(f"{SF}/documents.parquet"))
    words = [b"the", b"zqx", "\u00e9t\u00e9".encode(), b"The,", b"x" * 40]
    assert np.allclose(model.score(words), [sum(position_scores(model, w)) for w in words])
    assert all((np.diff(g) > 0).all() for g in model.gram[1:])


def test_counts_do_not_depend_on_partitions(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    one = kneser_ney.count_grams(kneser_ney.code(docs.coalesce(1)))
    many = kneser_ney.count_grams(kneser_ney.code(docs.repartition(7)))
    assert one.exceptAll(many).isEmpty() and many.exceptAll(one).isEmpty()


def test_scores_are_those_of_the_model_in_one_process(spark, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet").repartition(3)
    odd = spark.createDataFrame([(5000 + k, t, None, "s", 1, "x") for k, t in enumerate([*ODD, "\u00df \U0001f600\U0001f600 zz9zz"])], DOCS)
    docs = docs.unionByName(odd, allowMissingColumns=True)
    learned, other = docs.where("doc_id % 2 = 0"), docs.where("doc_id % 2 = 1")
    for scored, reference in ((docs, None), (other, learned)):
        model = kneser_ney_reference.train(docs if reference is None else reference)
        got = {r["doc_id"]: r["log_perplexity"] for r in kneser_ney.measures(scored, reference).collect()}
        for r in scored.collect():
            words = (r["text"] or "").encode().split()
            want = -model.score(words).mean() if words else None
            assert got[r["doc_id"]] == want or np.isclose(got[r["doc_id"]], want), r["doc_id"]


def test_blocks_end_where_they_are_full():
    block, texts = kneser_ney.Block(), [[b"a", b"b", b"a"], [], [b"c", b"a"], [b"%d" % k for k in range(kneser_ney.WORDS)]]
    bodies = [block.add(t) for t in texts]
    assert block.full() and block.counts[:3].tolist() == [3, 1, 1]
    names = list(block.number)
    for t, body in zip(texts, bodies):
        ids, counts = kneser_ney.unpack(body)
        assert sorted(t) == sorted(w for k, n in zip(ids, counts) for w in [names[k]] * n)


def test_gibberish_is_out_of_band(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rng = np.random.default_rng(1)
    junk = " ".join("".join(map(chr, rng.integers(33, 127, 9))) for _ in range(300))
    extra = spark.createDataFrame([(10_001, junk, "en", "s", 1)], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r["doc_id"]: r for r in kneser_ney.judge(docs.unionByName(extra)).collect()}
    assert not got[10_001]["kept"] and not got[10_001]["base_failed"]
    good = [r["doc_id"] for r in spark.read.parquet(f"{SF}/labels.parquet").where("quality = 1").collect()]
    assert np.mean([got[k]["kept"] for k in good if not got[k]["base_failed"]]) > 0.97


def test_hashed_ngrams_in_parts(monkeypatch):
    text = bytes(np.random.default_rng(2).integers(97, 110, 500, dtype=np.uint8))
    whole = features.hashed_ngrams(text, 256)
    monkeypatch.setattr(features, "PART", 33)
    assert (features.hashed_ngrams(text, 256) == whole).all() and whole.sum() == 500 + 499 + 498
    assert features.hashed_ngrams(b"", 256).sum() == 0


def test_cotraining_on_held_out_labels(spark):
    big = SF.replace("0.001", "0.01")
    docs, labels = spark.read.parquet(f"{big}/documents.parquet"), spark.read.parquet(f"{big}/labels.parquet")
    model = cotraining.train(docs, labels.where("doc_id % 3 != 0"), taught=100)
    got = cotraining.classify(docs, model).join(labels.where("doc_id % 3 = 0"), "doc_id").collect()
    right = np.mean([r["kept"] == (r["quality"] == 1) for r in got])
    assert right > 0.95
    kept = cotraining.keep(docs, model)
    assert kept.columns == docs.columns and kept.count() == cotraining.classify(docs, model).where("kept").count()


def test_cotraining_odd_rows(spark):
    big = SF.replace("0.001", "0.01")
    docs, labels = spark.read.parquet(f"{big}/documents.parquet"), spark.read.parquet(f"{big}/labels.parquet")
    model = cotraining.train(docs, labels, labelled=200, taught=20)
    odd = spark.createDataFrame([(None, None, None, None, None, "x"), (1, "", "en", "s", -5 + 5, "x"), (1, "", "en", "s", 0, "x")], DOCS)
    got = cotraining.classify(odd, model).collect()
    assert len(got) == 3 and all(0 <= r["p_good"] <= 1 for r in got)
    assert cotraining.train(docs, labels.limit(0)) is None
    assert cotraining.train(docs.limit(0), labels) is None
    assert cotraining.classify(odd, None).where("kept").count() == 3
    assert cotraining.classify(docs.limit(0), model).count() == 0 and cotraining.keep(docs.limit(0), model).count() == 0


def plain_teacher(a, b, bar=2.2):
    """What each view is confident of, with the other view's rows."""

    def teach(model):
        out = []
        for odds, other in zip(model.calibrated([a, b]), (b, a)):
            sure = np.flatnonzero(np.abs(odds) >= bar)
            out.append((other[sure], (odds[sure] > 0).astype(float)))
        return out

    return teach


def test_views_learn_from_each_other():
    rng = np.random.default_rng(0)
    y = rng.integers(0, 2, 400)
    a = (rng.normal(size=(400, 3)) + 2 * y[:, None]).astype(np.float32)
    b = (rng.normal(size=(400, 2)) + 1.5 * y[:, None]).astype(np.float32)
    model = cotraining.co_train(cotraining.Labelled([a[:40], b[:40]], y[:40]), plain_teacher(a[40:240], b[40:240]))
    right = ((model.log_odds([a[240:], b[240:]]) > 0) == y[240:]).mean()
    assert right > 0.9
    noise = rng.normal(size=(400, 2)).astype(np.float32)
    model = cotraining.co_train(cotraining.Labelled([a[:100], noise[:100]], y[:100]), plain_teacher(a[100:200], noise[100:200]))
    assert ((model.log_odds([a[200:], noise[200:]]) > 0) == y[200:]).mean() > 0.85


def test_a_view_without_information_teaches_nothing(spark):
    rng = np.random.default_rng(3)
    y = rng.integers(0, 2, 300)
    a = (rng.normal(size=(300, cotraining.TEXT)) * 0.1 + y[:, None]).astype(np.float32)
    noise = rng.normal(size=(300, cotraining.META)).astype(np.float32)
    rows = cotraining.Labelled([a[:200], noise[:200]], y[:200])
    model = cotraining.calibrated([cotraining.logistic(x[~rows.held], rows.y[~rows.held].astype(float)) for x in rows.xs], rows)
    views = spark.createDataFrame([(k, None, a[k].astype(np.float16).tobytes(), noise[k].astype(np.float16).tobytes()) for k in range(200, 300)], "doc_id long, quality int, text_x binary, meta_x binary")
    (by_text, labels), (by_meta, _) = cotraining.confident(views, model, most=30)
    assert len(by_meta) == 0 and 40 <= len(by_text) <= 60 and sorted(set(labels)) == [0, 1]


def test_bands_count_a_text_once(spark):
    """Copies of one text are over half of a language; other clean texts stay inside the band."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("lang = 'en'").select("doc_id", "text", "lang")
    copy = docs.where("length(text) > 800").orderBy("doc_id").limit(1).collect()[0]
    copies = spark.createDataFrame([(50_000 + k, copy["text"], "en") for k in range(300)], "doc_id long, text string, lang string")
    before = {r["doc_id"] for r in kneser_ney.judge(docs).where("kept").collect()}
    after = {r["doc_id"] for r in kneser_ney.judge(docs.unionByName(copies), docs).where("kept").collect()}
    assert len(before - after) <= 0.02 * len(before)


def test_equal_hashes_of_different_windows(monkeypatch):
    words = [b"%d" % (k % 50) for k in range(300)] + [b"x%d" % k for k in range(40)]
    want = kneser_ney.repeated_words(words)
    monkeypatch.setattr(kneser_ney, "MULTIPLIER", np.uint64(0))
    assert kneser_ney.repeated_words(words) == want == 300
