import random

import pytest

from canopy.llm import html_text, shards, url_rules
from canopy.llm.html_text import main_text
from tests.conftest import SF


def page(body, head=""):
    return f"<!DOCTYPE html><html><head><title>T</title>{head}</head><body>{body}</body></html>"


LONG = "word " * 60


def test_article_without_the_rest():
    html = page(f"<nav><a href='/'>Home</a></nav><div class='ad'>Buy now</div><article><h1>Title</h1><p>{LONG}</p><p>Short.</p><aside>See also</aside><form><input>Name</form><ul><li>one<li>two</ul></article><footer>(c)</footer>")
    assert main_text(html) == f"Title {LONG.strip()} Short. one two"


def test_references_white_space_and_inline_tags():
    assert main_text(page("<article><p>a&amp;b &lt;i&gt; &eacute;&#8364;\n\n  <b>bo</b>ld<br>next</p></article>")) == "a&b <i> é€ bold next"


def test_scripts_comments_and_open_tags():
    html = page(f"<script>var t='</p>';</script><article><!-- note --><p><b>{LONG}<p>end<style>p{{}}</style></article><div id='comments'><p>{LONG}</p></div>")
    assert main_text(html) == f"{LONG.strip()} end"


def test_pages_without_article():
    html = page(f"<div class='menu'><a>x</a><a>y</a></div><div id='content'><p>{LONG}</p><p>tail</p></div><div class='sidebar'>{LONG}</div><div class='cookie-notice'>We use cookies</div>")
    assert main_text(html) == f"{LONG.strip()} tail"
    assert main_text(f"<p>{LONG}") == LONG.strip()


def test_odd_pages(spark):
    odd = [None, "", "   ", "<", "<<<>>>", "plain text", "<div>" * 2000 + "deep", "&amp;" * 10, "<article></article>", "<a href='" + "x" * 200_000]
    rows = [(k, f"u{k}", h, "clash") for k, h in enumerate(odd)] + [(1, None, None, "c"), (None, "u", "<p>x y z", "c")]
    got = html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string, text string")).collect()
    assert len(got) == len(rows) and all(r["n_chars"] == len(r["text"]) for r in got)
    by = {r["page_id"]: r["text"] for r in got[: len(odd)]}
    assert by[0] == by[8] == "" and by[5] == "plain text" and by[6] == "deep"
    assert html_text.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_smoothing_keeps_the_level():
    import numpy as np

    assert np.allclose(html_text.smooth(np.ones(50))[10:40], 1)


def test_given_pages(spark):
    import html
    import re

    pages = spark.read.parquet(f"{SF}/pages.parquet")
    got = {r["page_id"]: r["text"] for r in html_text.extract(pages).collect()}
    for r in pages.collect():
        inner = re.search(r"<article>(.*?)(</article>|<footer>|$)", r["html"], re.S)[1]
        blocks = re.sub(r"</?(p|h1|br)>", " ", inner)
        assert got[r["page_id"]] == " ".join(html.unescape(re.sub(r"<[^>]*>", "", blocks)).split())


# url rules


def plain_parts(url):
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    cut = min([k for k in (rest.find(c) for c in "/?#") if k >= 0], default=len(rest))
    path = rest[cut:]
    end = min([k for k in (path.find(c) for c in "?#") if k >= 0], default=len(path))
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:cut]), path[:end]


def plain_verdict(url, rules):
    host, path = plain_parts(url)
    fits = [(len(h) + len(p), h + p, v) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return (host, path, *(max(fits)[1:] if fits else (None, "allow")))


def check(spark, urls, rules):
    pages = spark.createDataFrame([(k, u, "clash") for k, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_rules.judge(pages, url_rules.rule_table(spark, rules)).collect()}
    for k, u in enumerate(urls):
        assert got[k] == plain_verdict(u, rules), (u, got[k])


def test_rules_against_brute_force(spark):
    rng = random.Random(2)
    hosts = ["com", "example.com", "a.example.com", "Xexample.com", "net", "b.net", "é.net", "a..b.net", "com.", ""]
    pieces = ["/", "/en", "/en/", "/en/7", "/en/77", "/EN/7", "/é", "/en/7\n8", "/x/y/z"]
    urls = [f"http://{rng.choice(hosts)}{rng.choice(pieces)}{rng.choice(['', '?q=/en/', '#t', '7', '://x'])}" for _ in range(300)]
    urls += [None, "", "example.com/en/7", "://", "http://", "a://b://c/d", "http://com?x/en/", *urls[:20]]
    check(spark, urls, url_rules.RULES)
    deep = [("block" if rng.random() < 0.5 else "allow", rng.choice(hosts[:6]).lower(), rng.choice(pieces)[: rng.randint(0, 6)]) for _ in range(40)]
    check(spark, urls, list({(h, p): (v, h, p) for v, h, p in deep}.values()))


def test_hot_hosts_are_salted(spark):
    urls = [f"http://h{k % 3}.com/en/{k}" for k in range(3000)] + ["http://x.org/es/1"]
    check(spark, urls, url_rules.RULES)


def test_rules_and_pages_may_be_empty(spark):
    none = spark.createDataFrame([], "verdict string, host string, path string")
    pages = spark.createDataFrame([(1, "http://a.com/en/"), (1, "http://a.com/en/"), (None, None)], "page_id long, url string")
    got = url_rules.judge(pages, none)
    assert got.count() == 3 and got.where("verdict = 'allow' AND rule IS NULL").count() == 3
    assert url_rules.judge(pages.limit(0), url_rules.rule_table(spark)).count() == 0


# shards


def test_append_compact_and_read(spark, tmp_path):
    store = shards.ShardStore(spark, str(tmp_path / "store"), target=60_000)
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for k in range(4):
        assert store.append(docs.where(f"doc_id % 4 = {k}").repartition(3)) == k + 1
    before = store.manifest()["files"]
    version = store.compact()
    after = store.manifest(version)["files"]
    assert version > 4 and len(after) < len(before) == 12
    same = lambda df: df.exceptAll(docs).isEmpty() and docs.exceptAll(df).isEmpty()
    assert same(store.read()) and same(store.read(4)) and store.read(1).count() == docs.where("doc_id % 4 = 0").count()
    assert not store.plan(after) or all(len(g) <= -(-sum(f.size for f in g) // store.target) for g in store.plan(after))
    assert store.compact() == version
    assert store.expire() > 0 and same(store.read())


def test_commits_conflict(spark, tmp_path):
    store = shards.ShardStore(spark, str(tmp_path / "store"))
    store.append(spark.range(5))
    base = store.manifest()
    store.append(spark.range(3))
    with pytest.raises(shards.Conflict):
        store.commit(base["version"], base["schema"], base["files"])
    assert store.version() == 2 and store.read().count() == 8
    with pytest.raises(ValueError):
        store.append(spark.createDataFrame([("x",)], "other string"))


def test_empty_and_null_rows(spark, tmp_path):
    store = shards.ShardStore(spark, str(tmp_path / "store"))
    with pytest.raises(ValueError):
        store.read()
    schema = "doc_id long, text string"
    store.append(spark.createDataFrame([], schema))
    assert store.read().count() == 0 and store.compact() == 1
    for _ in range(5):
        store.append(spark.createDataFrame([(None, None), (1, ""), (1, "")], schema).coalesce(1))
    store.compact()
    assert store.read().count() == 15 and len(store.manifest()["files"]) < 6


def test_tiers_grow_with_size():
    store = shards.ShardStore.__new__(shards.ShardStore)
    store.target, store.ratio = 4096, 4.0
    assert [store.tier(s) for s in (0, 1, 2, 5, 20, 70, 300, 1100, 5000)] == [0, 0, 1, 2, 3, 4, 5, 6, 6]
