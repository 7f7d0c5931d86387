"""HTML extraction against pages whose text is known, and a curve by definition."""

from __future__ import annotations

import html
import random

import pytest
from tissuemap.llm import html_extract

WORDS = "storm river it's council budget night <b> & voted 7% \u00e9t\u00e9 market train \u4e2d\u6587 a of the".split()


def prose(r, least, most):
    return " ".join(r.choices(WORDS, k=r.randint(least, most)))


def inline(r, text):
    """The text as markup: references, tags and white space that do not show."""
    out = []
    for w in text.split(" "):
        w = html.escape(w, False) if r.random() < 0.7 else "".join(f"&#{ord(c)};" for c in w)
        w = r.choice([w, w, w, f"<b>{w}</b>", f"<span title=it's class=x>{w}</span>", f'<i title="a > b">{w}</i>'])
        out.append(w + r.choice(["", "", "<!-- note > -->", "<script>var x='</p>';</script>", "<style>p{}</style>"]))
    return r.choice([" ", "\n ", "&#32;", "&nbsp;"]).join(out)


def page(seed, wrap):
    """A page and the text it holds, made side by side."""
    r = random.Random(seed)
    menu = "<ul>" + "".join(f"<li><a href='/{i}'>{prose(r, 1, 2)}</a>" for i in range(8)) + "</ul>"
    blocks = [prose(r, 3, 8)] + [prose(r, 15, 60) for _ in range(r.randint(2, 9))]
    body = f"<h1>{inline(r, blocks[0])}</h1>"
    for b in blocks[1:]:
        body += r.choice(["<p>{}</p>", "<p>{}", "<div class='share-price'>{}</div>", "<blockquote>{}</blockquote>"]).format(inline(r, b))
        body += r.choice(["", "", '<div class="social-share"><p>Tell all your friends about it right now</p></div>', "<form><p>Write to us</p><input></form>", "<aside>By the way</aside>"])
    notes = "<section id=comments><article class='comment'><p>" + "I liked it. " * 60 + "</p></article></section>"
    body += r.choice(["", notes])
    head = f"<!DOCTYPE html><html><head><title>{inline(r, blocks[0])}</title></head><body>"
    top = r.choice(["<header><p>The Daily</p></header>", "<div id='site-header'>The Daily</div>", ""])
    foot = r.choice(["<footer>&copy; all</footer>", "<div class='page-footer'><p>" + "terms " * 90 + "</p></div>", ""])
    return f"{head}{top}{menu}<{wrap}>{body}</{wrap}>{menu}{foot}</body></html>", "\n\n".join(blocks)


@pytest.mark.parametrize("wrap", ["article", "main", "div", "div class='content'"])
def test_pages_made_with_their_text(wrap):
    for seed in range(150):
        given, text = page(seed, wrap.split()[0])
        assert html_extract.extract(given.replace("<div>", f"<{wrap}>", 1)) == text, seed


def slow_stretches(lengths, width, surge):
    """Point by point: within a stretch or not, from left to right."""
    out, open_at = [], None
    for i in range(len(lengths) + 1):
        total = sum(lengths[i : i + width])
        if open_at is not None and total == 0:
            out.append((open_at, i))
            open_at = None
        if open_at is None and i < len(lengths) and total >= surge and lengths[i] > 0:
            open_at = i
    return out


def test_stretches_by_definition():
    r = random.Random(4)
    for _ in range(500):
        lengths = [r.choice([0, 0, 5, 30, 90]) for _ in range(r.randint(0, 30))]
        assert html_extract.stretches(lengths) == slow_stretches(lengths, html_extract.WIDTH, html_extract.SURGE)


def test_the_curve_decides_against_a_small_article():
    story = "".join(f"<p>{'A long sentence of the story itself. ' * 12}{i}</p>" for i in range(12))
    given = f"<body><div>{story}</div><ul><li><a href=/>x</a></ul><article><p>A teaser.</p></article></body>"
    assert html_extract.extract(given).startswith("A long sentence")
    given = f"<body><article>{story}</article><div><p>{'Something else. ' * 20}</p></div></body>"
    assert "else" not in html_extract.extract(given) and html_extract.extract(given).count("\n\n") == 11


def test_names_of_elements():
    kept = ["share-price", "comment-quality", "header-image", "entry-header", "articleHeader", "admin", "tagline", "menuet"]
    gone = ["ad", "ad-slot-1", "ad_300x250", "site-header", "relatedPosts", "comment-list", "left-sidebar", "nav", "cookie-banner"]
    for name in kept + gone:
        text = f"<article><h1>T</h1><div class='{name}'>body text</div></article>"
        assert ("body text" in html_extract.extract(text)) == (name in kept), name


def test_quotes_in_attributes_and_long_pages():
    assert html_extract.extract("<article><p title=it's>First para don't</p><p>Second</p></article>") == "First para don't\n\nSecond"
    assert html_extract.extract("<p title='a > b'>x</p><p title=\"it's\">y</p>") == "x\n\ny"
    for long in ("<p>" + "word " * 400_000, "<div>" * 100_000 + "x" + "</div>" * 100_000, "<b>" * 50_000 + "x", "<" * 1_000_000, "<a b=\"" * 20_000):
        html_extract.extract(long)
