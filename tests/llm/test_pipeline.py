import re
import zlib

import corpus_pipeline
from canopy.llm import cotraining, registry, secrets, simhash, tiling
from canopy.llm.packing import default_tokenizer
from tests.conftest import SF


def test_stages_keep_the_columns_and_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    for name, step in corpus_pipeline.STAGES[:-1]:
        docs = step(spark, docs, SF)
        assert docs.columns == columns, name
        docs = docs.cache()
        sizes.append(docs.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[3] == sizes[4] > 0
    again = simhash.near_duplicates(docs)
    assert tiling.contamination(docs, spark.read.parquet(f"{SF}/benchmark.parquet")).where("contaminated").count() == 0
    assert secrets.digest(secrets.scan_versions(docs)).where("n_access + n_hex > 0").count() == 0
    assert again.count() == docs.count()


SPANS = [
    (re.compile(r"""(?a:(?i:(password|passwd|secret|token|api_?key)))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), 2, 6),
    (re.compile("AKIA[A-Z0-9]+"), 0, 20),
    (re.compile("[0-9a-f]+"), 0, 24),
    (re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\s]*-----END [A-Z ]*PRIVATE KEY-----"), 0, 0),
    (re.compile(r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+"), 0, 30),
    (re.compile("gh[pousr]_[A-Za-z0-9]+"), 0, 40),
]


def plain_mask(text):
    """Every character inside a finding goes; a run of them leaves one mark."""
    hidden = [False] * len(text)
    for pattern, group, least in SPANS:
        for m in pattern.finditer(text):
            if len(m[group]) >= least:
                hidden[m.start() : m.end()] = [True] * (m.end() - m.start())
    return "".join("[SECRET]" if h and (k == 0 or not hidden[k - 1]) else "" if h else c for k, (c, h) in enumerate(zip(text, hidden)))


def plain_contaminated(text, items):
    """Greedy tiling by comparing everywhere, for the items with five tokens in a row in common."""
    from tests.llm.test_tiling import plain_tiles

    doc = re.findall(r"\w+", text.lower())
    grams = {n: {tuple(doc[k : k + n]) for k in range(len(doc) - n + 1)} for n in range(1, 6)}
    for item in items:
        words = re.findall(r"\w+", item.lower())
        least = min(5, len(words))
        shared = words and any(tuple(words[k : k + least]) in grams[least] for k in range(len(words) - least + 1))
        # only tokens inside shared rows can be tiled, so the rest is left out; a gap parts rows
        if shared:
            rows = {tuple(words[k : k + least]) for k in range(len(words) - least + 1)}
            inside = {k + j for k in range(len(doc) - least + 1) if tuple(doc[k : k + least]) in rows for j in range(least)}
            part = [w if k in inside else ("gap", k) for k, w in enumerate(doc) if k in inside or k - 1 in inside]
            if plain_tiles(part, words, least) >= 0.5 * len(words):
                return True
    return False


def test_run_against_brute_force(spark):
    """All stages but the classifier by definitions of their own, and the packed ids."""
    from tests.llm.test_overlap import plain_repeats
    from tests.llm.test_packing import check
    from tests.llm.test_simhash import plain_components, plain_fingerprint

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    model = cotraining.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    kept = {r["doc_id"] for r in cotraining.classify(docs, model).collect() if r["kept"]}
    kept = set(plain_components({k: plain_fingerprint(rows[k]) for k in kept}).values())
    kept -= plain_repeats([(k, rows[k]) for k in sorted(kept)])
    items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    kept = {k for k in kept if not plain_contaminated(rows[k], items)}
    check(corpus_pipeline.run(spark, SF).collect(), {k: plain_mask(rows[k]) for k in kept})


def test_queries_run_on_the_smallest_tables(spark):
    for name, f in registry.queries().items():
        df = f(spark, SF)
        assert df.count() > 0, name
    assert set(registry.oracle_sql()) <= set(registry.queries())


def test_empty_tables(spark, tmp_path):
    for name in ("documents", "labels", "benchmark", "pages"):
        spark.read.parquet(f"{SF}/{name}.parquet").limit(0).write.parquet(str(tmp_path / f"{name}.parquet"))
    for name, f in registry.queries().items():
        assert f(spark, str(tmp_path)).count() == 0, name


def test_tokenizer_is_not_in_the_repository():
    assert "/root/repo" not in default_tokenizer() and zlib.crc32(b"") == 0
