import pytest

pytest.importorskip("approxset.llm")
from approxset.llm import html

TEXT = "Some words of the article that are long enough to stand"


@pytest.mark.parametrize("name", ["svg", "math", "iframe", "object", "canvas", "audio", "video", "noscript", "select", "template"])
def test_text_after_self_closed_or_unclosed_element(name):
    for tag in (f"<{name} class='i'/>", f"<{name} class='i'>"):
        got = html.main_text(f"<body><p>{TEXT} {tag} here</p><p>{TEXT}</p></body>", html.START)
        assert got.endswith(TEXT) and got.count(TEXT) == 2, tag
        assert got.split("\n\n")[0].split() == f"{TEXT} here".split(), tag


def test_contents_of_drawings_are_left_out():
    page = f"<body><p>{TEXT} <svg><title>Icon name</title><g><path d='x'/></g></svg> on</p><svg class='a'><p>{TEXT}</p><svg>drawn</svg><p>{TEXT} too</p>"
    assert [" ".join(b.split()) for b in html.main_text(page, html.START).split("\n\n")] == [f"{TEXT} on", TEXT, f"{TEXT} too"]


@pytest.mark.parametrize("wrapper", ["content has-sidebar", "with-header", "page-sidebar"])
def test_wrapper_of_the_article_is_no_furniture(wrapper):
    page = f"<body><div class='{wrapper}'><article><p>{TEXT}</p></article><div class='sidebar'><article>Short teaser</article></div></div></body>"
    assert html.main_text(page, html.START) == TEXT


def test_articles_in_furniture_stay_out_beside_a_free_one():
    page = f"<body><article><p>{TEXT}</p></article><div class='related'><article>{TEXT} again and again and again</article></div></body>"
    assert html.main_text(page, html.START) == TEXT
