import pytest
from geohist.llm import html

LONG = "Dense text of the page goes on here. " * 12


@pytest.mark.parametrize("mark", ["class='content no-sidebar'", "class='post has-comments'", "class='sidebar'", "id=related"])
def test_wrapper_of_most_text_is_kept(mark):
    assert LONG.strip() in html.main_text(f"<body><div class=menu><a href=1>a</a></div><div {mark}><p>{LONG}</p></div></body>")


def test_words_inside_an_article_are_kept():
    page = f"<article><p>{LONG}</p><h2 id='related-work'>Earlier work</h2><p class='share-price'>It rose.</p><section id='legal'><p>The law.</p></section><div class='share-links'>share me</div><div class='ad_box'>buy</div></article>"
    got = html.main_text(page)
    assert all(x in got for x in ("Earlier work", "It rose.", "The law.")) and "share me" not in got and "buy" not in got
