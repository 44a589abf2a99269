import random

import corpus_pipeline
from canopy.llm import overlap
from tests.conftest import SF


def plain_set(text):
    words = (text or "").lower().split()
    return {tuple(words[k : k + 5]) for k in range(len(words) - 4)} if len(words) >= 5 else {tuple(words)} if words else set()


def plain_repeats(rows):
    sets = {k: plain_set(t) for k, t in rows}
    return {b for a in sets for b in sets if a < b and sets[a] and sets[b] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])}


def near_copies(seed=5):
    """Near copies of one to six changed words, a common passage and odd texts."""
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    passage = [rng.choice(words) for _ in range(30)]
    bases = [[rng.choice(words) for _ in range(n)] for n in (6, 60, 150, 400)] + [passage + [rng.choice(words) for _ in range(12)] for _ in range(20)]
    rows = []
    for k in range(200):
        text = list(rng.choice(bases))
        for _ in range(rng.randrange(7)):
            text[rng.randrange(len(text))] = rng.choice(words)
        rows.append((k, " ".join(text)))
    return rows + [(300, ""), (301, None), (302, "one two"), (303, "One  two"), (304, " ")]


def test_repeats_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(overlap, "WORTH", 100)
    rows = near_copies()
    docs = spark.createDataFrame(rows + [(None, rows[0][1])], "doc_id long, text string").repartition(5)
    kept = overlap.first_of_each(docs)
    want = plain_repeats(rows)
    assert sorted(r["doc_id"] for r in kept.where("doc_id IS NOT NULL").collect()) == sorted({k for k, _ in rows} - want)
    assert kept.where("doc_id IS NULL").count() == 1 and len(want) > 30
    assert overlap.first_of_each(docs.limit(0)).count() == 0


def test_stage_leaves_no_near_copies(spark):
    """Pairs of similarity 0.8 or more stayed when the stage only took SimHash groups."""
    rows = near_copies(6)
    for docs in (spark.createDataFrame(rows, "doc_id long, text string"), spark.read.parquet(f"{SF}/documents.parquet")):
        kept = corpus_pipeline.near_duplicates(spark, docs, SF).collect()
        assert kept and not plain_repeats([(r["doc_id"], r["text"]) for r in kept])


def test_distant_copies_of_one_group_form_no_pairs(spark, monkeypatch):
    """Texts that each changed a seventh of a common one share keys; all their pairs were candidates."""
    rng = random.Random(7)
    base = [f"w{k}" for k in range(400)]
    rows = []
    for k in range(120):
        text = list(base)
        for at in rng.sample(range(0, 400, 6), rng.randint(11, 13)):
            text[at] = f"x{k}-{at}"
        rows.append((k, " ".join(text)))
    rows += [(120 + k, f"{rows[k][1]} end") for k in range(0, 120, 10)]
    asked, similar = [], overlap.similar

    def counted(docs, pairs, parts, size):
        asked.append(pairs.count())
        return similar(docs, pairs, parts, size)

    monkeypatch.setattr(overlap, "similar", counted)
    found = overlap.similar_to_smaller(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r["doc_id"] for r in found.collect()} == plain_repeats(rows) == set(range(120, 240, 10))
    assert sum(asked) < 5 * len(rows)
