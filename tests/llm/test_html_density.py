"""Pages without telling names: only density can choose. And markup that is not well formed."""

import math

import pytest
from geohist.llm import html

P1, P2, P3 = ("The first paragraph says a good deal about the matter, at length and in full. " * 4).strip(), ("The second one goes on with more of the same, and then some. " * 5).strip(), "A short one."
LINKS = "<ul>" + "".join(f"<li><a href=/{i}>Some place number {i} of the site</a></li>" for i in range(12)) + "</ul>"
PLAIN = f"<html><body><div>{LINKS}</div><div><div><h2>A heading</h2><p>{P1}</p><p>{P3}</p><p>{P2}</p></div></div><div>{LINKS}</div><div>All rights kept.</div></body></html>"


def test_density_chooses_among_unnamed_blocks():
    assert html.main_text(PLAIN) == "\n".join(["A heading", P1, P3, P2])


def test_without_density_the_result_differs(monkeypatch):
    def flat(root):
        stack = [root]
        while stack:
            x = stack.pop()
            x.density, x.total = 1.0, 1.0
            stack.extend(k for k in x.kids if type(k) is html.Node)

    monkeypatch.setattr(html, "measure", flat)
    assert html.main_text(PLAIN) != "\n".join(["A heading", P1, P3, P2])


def test_an_article_element_does_not_decide():
    page = f"<body><article><a href=1>Teaser one of the day</a></article><article><a href=2>Teaser two of the day</a></article><div><p>{P1}</p><p>{P2}</p></div></body>"
    assert html.main_text(page) == f"{P1}\n{P2}"


def test_sections_of_one_container_stay_together():
    page = f"<body><div>{LINKS}</div><div><div><p>{P1}</p><p>{P1}</p></div><div><p>{P2}</p><p>{P2}</p></div></div></body>"
    assert html.main_text(page) == "\n".join([P1, P1, P2, P2])


def test_marked_parts_leave_by_their_density():
    page = f"<body><div class=ad>Buy this now and be glad about it.</div><div><p>{P1}</p><div class=comments><p>reader says this</p></div><p>{P2}</p></div><div class=sidebar><p>See also this and that.</p></div></body>"
    assert html.main_text(page) == f"{P1}\n{P2}"


def test_measures_of_a_small_tree():
    root = html.parse("<div><p>abcd efgh</p><p><a>ab</a>cd</p></div>")
    html.measure(root)
    div = root.kids[0]
    one, two = div.kids
    assert (div.chars, div.tags, div.link_chars, div.link_tags) == (12, 3, 2, 1)
    base = lambda c, lc: math.log(c / max(c - lc, 1) * lc + 2 / 12 * c + math.e)
    assert math.isclose(one.density, 8 * math.log(8 + 1e-9) / math.log(max(base(8, 0), 1) + 1), rel_tol=1e-6)
    assert math.isclose(two.density, 4 * math.log(2 + 1e-9) / math.log(max(base(4, 2), 1) + 1), rel_tol=1e-6)
    assert math.isclose(div.total, one.density + two.density)


@pytest.mark.parametrize(
    "page,text",
    [
        ("<p data-x=it's>First..</p><p>Don't lose this.</p><p>Third.</p>", "First..\nDon't lose this.\nThird."),
        ("<p>x<y here</p><p>more</p>", "x<y here\nmore"),
        ("<p>a < b and c > d, 1<2</p>", "a < b and c > d, 1<2"),
        ("<p title='a > b' class=\"x\">kept</p>", "kept"),
        ("<p a=b'c\"d>kept</p><p>too</p>", "kept\ntoo"),
        ("<p>one<!-- two > <p>three --> four</p><!-->five", "one four\nfive"),
        ("<p>one</p><![CDATA[<p>two</p>]]><?php echo '<p>'; ?><p>three</p>", "one\n'; ?>\nthree"),
        ("<div><span><p>in a span</p></span></div>", "in a span"),
        ("&lt;p&gt; &amp;amp; &#233;&#x4e2d;&nbsp;x", "<p> &amp; é中 x"),
        ("</", "</"),
        ("<p>open", "open"),
        ("<script>if (a<b) '</p>'</script>kept<style>x", "kept"),
        ("<p hidden>no</p><p aria-hidden=true>no</p><p>yes</p>", "yes"),
    ],
)
def test_markup(page, text):
    assert html.main_text(page) == text


def test_ties_repeats_and_clashing_columns(spark):
    page = "<body><div><p>same words here</p></div><div><p>same words here</p></div></body>"
    rows = spark.createDataFrame([(1, "u", page, "x", 5), (1, "u", page, "x", 5), (None, None, None, None, None), (2, "u", "<p>" + "long text " * 100_000, "", 0)], "page_id long, url string, html string, text string, n_chars int")
    got = html.extract(rows)
    assert got.columns == ["page_id", "url", "text", "n_chars"]
    rows = sorted((r["page_id"] or 0, r["text"][:40], r["n_chars"]) for r in got.collect())
    assert rows == [(0, "", 0), *[(1, "same words here\nsame words here", 31)] * 2, (2, "long text long text long text long text ", 999_999)]
