"""Main text of web pages by composite text density."""

from __future__ import annotations

import html as _html
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.llm.common import as_strings

# Element names of HTML by their part in parsing.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg math xmp noembed noframes".split())
BLOCK = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
CLOSES_P = BLOCK - frozenset("br td th tr tbody thead tfoot caption body html option optgroup".split())
DROPPED = frozenset("head nav footer aside form button select option input label menu dialog object embed canvas audio video".split()) | RAW
#: Words in class, id or role that name what mostly is not the article; they lessen a node's density, they cut nothing.
BOILER = frozenset(
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login sidebar sidenav widget menu menubar nav navbar navigation breadcrumb breadcrumbs pagination pager share sharing social related recommended recommendations comment comments respond replies disqus reactions footer toolbar search contentinfo complementary masthead skip hidden copyright legal disclaimer".split()
)
HEADERS = frozenset("header heading-bar topbar site-header".split())
#: Words that, put before or after a word of BOILER, still name the same part of a page: cookie-notice, ad-box, site-footer.
PARTS = frozenset("area bar block box bottom container content form inner item left link links list main outer page panel post right section site slot text top unit widget wrap wrapper".split())
#: What is left of a node's density when its class, id or role names such a part, and the share of the path's least density that a node beside it under the body must reach.
LESSENED, BESIDE = 0.01, 0.5
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())

_ATTRIBUTE = r"""[^\s/<>="'][^\s/<>=]*+(?:\s*+=\s*+(?:"[^"]*+"|'[^']*+'|[^\s"'<>][^\s<>]*+))?+"""
#: A tag up to its end; a quote opens a value only at its start, and a tag that meets another < is no tag but text.
_TAG = re.compile(rf"""</?([a-zA-Z][^\s/<>]*+)((?:[\s/="']|{_ATTRIBUTE})*+)(?:>|\Z)""")
_OPENS = re.compile(r"</?[a-zA-Z]")
_MARK = re.compile(r"""(?:^|[\s/"'])(class|id|role|hidden|aria-hidden)(?=[\s/=]|\Z)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)
_SPLIT = re.compile(r"[-_]+")


class Node:
    __slots__ = ("tag", "parent", "kids", "out", "marked", "chars", "tags", "link_chars", "link_tags", "density", "total")

    def __init__(self, tag: str, parent: Node | None):
        self.tag, self.parent, self.kids, self.out, self.marked = tag, parent, [], False, False
        self.chars = self.tags = self.link_chars = self.link_tags = 0
        self.density = self.total = 0.0


def _names(token: str, words: frozenset) -> bool:
    """Whether a whole token of class, id or role is one of the words, or a compound of them and of parts of a page only."""
    pieces = [x for x in _SPLIT.split(token) if x and not x.isdigit()]
    return token in words or not words.isdisjoint(pieces) and all(x in words or x in PARTS or x in BOILER for x in pieces)


def _unwanted(tag: str, attributes: str, inside_article: bool) -> tuple[bool, bool]:
    """Whether an element never is article text (by its name, or hidden), and whether its class, id or role names a part that mostly is not."""
    if tag in DROPPED or tag == "header" and not inside_article:
        return True, False
    if tag in ("article", "main") or not attributes:
        return False, False
    marked = False
    for name, a, b, c in _MARK.findall(attributes):
        name, value = name.lower(), (a or b or c).lower()
        if name == "hidden" or name == "aria-hidden" and value == "true":
            return True, False
        # A heading's or paragraph's id is made of its own words; it names no part of the page.
        if name == "id" and (tag in HEADINGS or tag == "p" or tag == "section" and inside_article):
            continue
        tokens = value.split()
        marked |= any(_names(t, BOILER) for t in tokens) or not inside_article and tag not in ("h1", "h2") and any(_names(t, HEADERS) for t in tokens)
    return False, marked


def _skip(text: str, at: int) -> int:
    """Where a comment, declaration or CDATA section that begins at `at` ends, or -1 if none begins there."""
    if text.startswith("<!--", at):
        if text.startswith((">", "->"), at + 4):  # an empty comment, cut short
            return text.index(">", at) + 1
        stop = text.find("-->", at + 4)
        return len(text) if stop < 0 else stop + 3
    if text.startswith("<![CDATA[", at):
        stop = text.find("]]>", at)
        return len(text) if stop < 0 else stop + 3
    if text.startswith(("<!", "<?", "</"), at) and at + 2 < len(text):
        stop = text.find(">", at)
        return len(text) if stop < 0 else stop + 1
    return -1


def parse(text: str) -> Node:
    """A tolerant tree: unknown ends are skipped, open paragraphs end where a block begins, what is not closed ends with its parent."""
    root = Node("html", None)
    here, n, at, kept = root, len(text), 0, 0  # text from `kept` on is not in the tree yet
    articles = 0

    def keep(stop: int) -> None:
        if stop > kept:
            part = text[kept:stop]
            here.kids.append(_html.unescape(part) if "&" in part else part)

    while True:
        at = text.find("<", at)
        if at < 0:
            keep(n)
            return root
        m = _TAG.match(text, at)
        if m is None:
            stop = -1 if _OPENS.match(text, at) else _skip(text, at)
            if stop < 0:
                at += 1  # a < that opens nothing is text
                continue
            keep(at)
            at = kept = stop
            continue
        keep(at)
        ends, at = text[at + 1] == "/", m.end()
        kept = at
        tag = m[1].lower()
        if ends:
            x = here
            while x is not None and x.tag != tag:
                if tag not in BLOCK and x.tag in BLOCK and x.tag != "br":
                    x = None  # an inline end does not close blocks
                    break
                x = x.parent
            if x is not None and x.parent is not None:
                y = here
                while y is not x.parent:
                    articles -= y.tag in ("article", "main")
                    y = y.parent
                here = x.parent
            continue
        if tag in ("html", "body"):
            continue
        if tag in CLOSES_P or tag in ("td", "th", "tr"):
            x = here
            while x.parent is not None and (x.tag not in BLOCK or x.tag == "p"):
                if x.tag == "p":
                    here = x.parent
                    break
                x = x.parent
        if tag in ("li", "dt", "dd", "tr", "td", "th", "option") and (here.tag == tag or {here.tag, tag} in ({"dt", "dd"}, {"td", "th"})):
            here = here.parent
        node = Node(tag, here)
        node.out, node.marked = _unwanted(tag, m[2], articles > 0)
        here.kids.append(node)
        if tag in VOID or m[2].endswith("/"):
            continue
        if tag in RAW:
            stop = re.compile(rf"</{re.escape(tag)}\b[^>]*(?:>|\Z)", re.I).search(text, at)
            at = kept = stop.end() if stop else n
            continue
        articles += tag in ("article", "main")
        here = node


def measure(root: Node) -> None:
    """Characters, tags, link characters and link tags of every node, its composite density, and the sum of the densities of the blocks below it."""
    order, stack = [], [root]
    while stack:
        x = stack.pop()
        order.append(x)
        if not x.out:
            stack.extend(k for k in x.kids if type(k) is Node)
    for x in reversed(order):
        if x.out:
            continue
        for k in x.kids:
            if type(k) is str:
                x.chars += len("".join(k.split()))
            elif not k.out:
                x.chars += k.chars
                x.tags += k.tags + 1
                x.link_chars += k.link_chars
                x.link_tags += k.link_tags + (k.tag == "a")
        if x.tag == "a":
            x.link_chars = x.chars
    whole, whole_links = max(root.chars, 1), root.link_chars
    for x in order:
        if x.out or not x.chars:
            continue
        c, t, lc, lt = x.chars, max(x.tags, 1), max(x.link_chars, 1), max(x.link_tags, 1)
        base = math.log(c / max(c - x.link_chars, 1) * x.link_chars + whole_links / whole * c + math.e)
        x.density = c / t * math.log(max(c / lc * t / lt, 1.0) + 1e-9) / math.log(max(base, 1.0) + 1.0)
        if x.marked:
            x.density *= LESSENED
    for x in reversed(order):  # an inline element stands for the blocks inside it
        x.total = sum(k.density if k.tag in BLOCK else k.total for k in x.kids if type(k) is Node and not k.out)


def _inside(x: Node, least: float) -> None:
    """Below a chosen node all text stays, but for parts named as something else whose lessened density stays under the threshold."""
    stack = [k for k in x.kids if type(k) is Node and not k.out]
    while stack:
        y = stack.pop()
        if y.marked and y.density < least:
            y.out = True
        else:
            stack.extend(k for k in y.kids if type(k) is Node and not k.out)


def choose(root: Node) -> None:
    """Marks as out whatever is not in the subtree of largest density sum, nor beside its path to the body and dense enough.

    The threshold of a level is the least density on the path from the best node up to that level; beside the path
    under the body itself, where whole other parts of a page stand, BESIDE of the least density below the body (all of it
    beside an article or main element). A heading beside the path, other than under the body, belongs to the text that it heads.
    """
    measure(root)
    best, stack = root, [root]
    while stack:  # in page order; of equal sums the one with more text, then the first
        x = stack.pop()
        if (x.total, x.chars) > (best.total, best.chars):
            best = x
        stack.extend(k for k in reversed(x.kids) if type(k) is Node and not k.out)
    if best is root:
        for k in root.kids:
            if type(k) is Node and not k.out and root.total > 0 and k.density < root.density and (k.marked or k.link_tags > 2 and k.link_chars > 0.8 * k.chars):
                k.out = True
        _inside(root, root.density)
        return
    least = best.density
    _inside(best, min(least, root.density))
    child, up = best, best.parent
    while up is not None:
        if up is root:
            threshold = least * (1 if child.tag in ("article", "main") else BESIDE)
        else:
            least = min(least, up.density / (LESSENED if up.marked else 1))
            threshold = min(least, root.density)
        for i, k in enumerate(up.kids):
            if type(k) is str:
                if up is root or len("".join(k.split())) < threshold:
                    up.kids[i] = ""
            elif k is not child and not k.out:
                if k.density < threshold and not (up is not root and k.tag in HEADINGS and not k.marked) and k.tag not in VOID:
                    k.out = True
                else:
                    _inside(k, min(least, root.density))
        child, up = up, up.parent


def text_of(root: Node) -> str:
    """Blocks in page order, one on each line; white space inside a block is one space."""
    lines: list[str] = []
    current: list[str] = []

    def end() -> None:
        line = " ".join("".join(current).split())
        if line:
            lines.append(line)
        current.clear()

    stack: list = [root]
    while stack:
        x = stack.pop()
        if x is None:
            end()
        elif type(x) is str:
            current.append(x)
        elif not x.out:
            if x.tag in BLOCK:
                end()
                stack.append(None)
            stack.extend(reversed(x.kids))
    end()
    return "\n".join(lines)


def main_text(page: str) -> str:
    if not page:
        return ""
    root = parse(page)
    choose(root)
    return text_of(root)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every page, from the whole html; null or empty html and pages without text give the empty text.

    Of parts with equal density sums the one with more text, then the first of the page is chosen. Repeated rows and ids are
    extracted each on its own; an empty table gives an empty result; other columns are not read, whatever their names.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(t.as_py()) for t in as_strings(b.column(2))]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    cols = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).alias("html"))
    return cols.mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op8_html_text(spark, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
