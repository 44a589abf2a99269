import numpy as np

from canopy.llm import html_text
from canopy.llm.html_text import main_text

LONG = "word " * 120


def test_a_teaser_article_does_not_beat_the_body():
    html = f"<body><div class='post'><p>{LONG}</p><p>{LONG}</p></div><article><p>Short teaser.</p></article></body>"
    assert main_text(html) == f"{LONG.strip()} {LONG.strip()}"


def test_a_wrapper_does_not_silence_its_article():
    html = f"<body><div class='has-sidebar'><article><h1>Title</h1><p>{LONG}</p><div class='share'>Share</div></article><div class='sidebar'>links</div></div></body>"
    assert main_text(html) == f"Title {LONG.strip()}"


def test_related_articles_stay_silent():
    html = f"<body><main><p>{LONG}</p><div class='related'><article>Teaser.</article></div><p>End.</p></main></body>"
    assert main_text(html) == f"{LONG.strip()} End."


def test_an_article_keeps_all_blocks_around_its_largest():
    html = f"<body><article><p>Intro.</p><div><p>{LONG}</p></div><p>End.</p></article><div>{'a b ' * 9}</div></body>"
    assert main_text(html) == f"Intro. {LONG.strip()} End."


def test_words_of_a_class_that_speak_of_content():
    html = "<article><p>Real.</p><div class='login-required story-content'>Members read this long line of text.</div><p class='social-science'>Science in a longer line of text.</p><div class='site-footer'>Gone.</div></article>"
    assert html_text.main_text(html) == "Real. Members read this long line of text. Science in a longer line of text."


def test_all_articles_with_content_stay():
    line = "A line of text that is long enough to count. "
    html = f"<body><nav><a href=a>a</a><a href=b>b</a></nav><article><p>{line * 6}</p></article><article><p>{line * 3}</p></article></body>"
    assert html_text.main_text(html) == " ".join([(line * 6).strip(), (line * 3).strip()])


def links(n):
    return "".join(f"<li><a href='/{k}'>Topic number {k} of many topics</a></li>" for k in range(n))


def test_the_ratio_decides(monkeypatch):
    """Without semantic tags: a long list of links has more characters than the text, which only the ratio tells apart."""
    html = f"<body><div><ul>{links(60)}</ul></div><div><p>{'Plain words of a text without any tags in it. ' * 12}</p><p>{'More of it. ' * 30}</p></div></body>"
    got = html_text.main_text(html)
    assert got.startswith("Plain words") and "Topic" not in got and got.endswith("More of it.")
    monkeypatch.setattr(html_text, "smooth", lambda ratio: np.ones(len(ratio)))
    assert "Topic" in html_text.main_text(html)
