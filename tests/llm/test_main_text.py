"""Main text: hand-made pages for every way of marking clutter, and generated pages of several layouts whose text is known."""

import random
import time

import pytest

from ebbmine.llm.main_text import main_text

LONG = "word, " * 40
KEPT = LONG.strip()

PAGES = {
    "hidden": (f"<div><p>{LONG}</p><div hidden><p>secret {LONG}</p></div><p hidden>no</p><p>{LONG}</p></div>", [KEPT, KEPT]),
    "value of another attribute": (f'<div><p title="no hidden fees" data-x="class=ad display:none">fees {LONG}</p><p>{LONG}</p></div>', ["fees " + KEPT, KEPT]),
    "inline": (f'<div><p>one {LONG}<span class="ad">BUY</span><span class="share">us</span>end</p><p>{LONG}</p></div>', ["one " + LONG + "end", KEPT]),
    "content section": (f'<div><p>{LONG}</p><section class="related-work"><p>work {LONG}</p></section></div>', [KEPT, "work " + KEPT]),
    "below depth 256": ("<div>" * 300 + f'<article><p>{LONG}</p><nav>menu</nav><div class="comments"><p>me {LONG}</p></div></article>', [KEPT]),
    "long attribute": (f'<div data-x="{"a>" * 3000}"><p>{LONG}</p><p>{LONG}</p></div>', [KEPT, KEPT]),
    "names that mention clutter": (f'<div class="content has-sidebar"><article><p>A {LONG}</p></article><div class="sidebar"><p>side {LONG}</p></div></div>', ["A " + KEPT]),
    "wrap": (f'<div class="content-sidebar-wrap"><div class="post has-comments"><p>A {LONG}</p><p>{LONG}</p></div><div class="widget-area"><p>x {LONG}</p></div></div>', ["A " + KEPT, KEPT]),
    "header of the article": (f"<div class=post><header><h1>Title</h1></header><p>{LONG}</p><p>{LONG}</p></div>", ["Title", KEPT, KEPT]),
    "header of the site": (f'<div id="header"><h1>Site</h1><ul><li><a href=x>x</a></ul></div><div class="post"><h1>Title</h1><p>{LONG}</p><p>{LONG}</p></div>', ["Title", KEPT, KEPT]),
    "form around the page": (f'<form id="all"><div id="main"><h1>T</h1><p>{LONG}</p><p>{LONG}</p></div><div class="search-form"></div></form>', ["T", KEPT, KEPT]),
    "comments as articles": (f'<main><article><h1>T</h1><p>{LONG}</p></article><section id="comments"><article class="comment"><p>{LONG * 3}</p></article></section></main>', ["T", KEPT]),
    "article in a sidebar": (f'<div class="content"><p>A {LONG}</p><p>{LONG}</p></div><div class="sidebar"><article><p>teaser</p></article></div>', ["A " + KEPT, KEPT]),
    "nothing but a name": (f'<div class="notice"><p>{LONG}</p></div>', [KEPT]),
    "comments and raw text": (f'<div><!-- <p>no {LONG}</p> --><p>{LONG}<script>var a="</p><p>x"</script></p><svg><title>t</title><text>s</text></svg><!--><p>{LONG}</p></div>', [KEPT, KEPT]),
    "references": ("<div><p>a &amp;b &#233;&#x1F600; c&nbsp;d, " + LONG + f"</p><p>&amp;lt; {LONG}</p></div>", ["a &b é😀 c d, " + KEPT, "&lt; " + KEPT]),
    "links in the text": (f'<div><p>{LONG}</p><ul><li><a href=1>one</a><li><a href=2>two</a></ul><p><a href=3>{LONG}</a></p><p>{LONG}</p></div>', [KEPT, KEPT, KEPT]),
}


@pytest.mark.parametrize("name", PAGES)
def test_hand_pages(name):
    page, want = PAGES[name]
    assert main_text(f"<html><body>{page}</body></html>") == "\n\n".join(want)


def test_generated_layouts():
    rng = random.Random(6)
    side = ['<div class="sidebar"><p>{}</p></div>', "<aside><p>{}</p></aside>", '<div id="comments"><div class="comment"><p>{}</p></div></div>', '<div style="display: none"><p>{}</p></div>', "<form><p>{}</p></form>", '<div role="complementary"><p>{}</p></div>', '<div class="ad-slot">{}</div>']
    for _ in range(300):
        texts = [" ".join(f"p{k}w{j}," if j % 5 else f"P{k}w{j}." for j in range(rng.randrange(20, 60))) for k in range(rng.randrange(3, 9))]
        layout = rng.choice(["p", "div", "table", "br", "nested", "article"])
        if layout == "br":
            body = "<div id=c>" + "<br><br>".join(texts) + "</div>"
        elif layout == "table":
            body = "<table><tr><td><a href=1>Home</a></td><td>" + "".join(f"<p>{t}" for t in texts) + "</td></tr></table>"
        else:
            tag = "div" if layout == "div" else "p"
            body = "".join(f"<{tag}>{t}</{tag}>" for t in texts)
            body = {"article": f"<article>{body}</article>", "nested": "<div>" * 40 + f"<section>{body}</section>" + "</div>" * 40}.get(layout, f"<div id=c>{body}</div>")
        junk = [rng.choice(side).format("junk, " * rng.randrange(3, 60)) for _ in range(rng.randrange(0, 4))]
        at = rng.randrange(len(junk) + 1)
        page = "<!DOCTYPE html><body><nav><ul><li><a href=/>Home</a></ul></nav>" + "".join(junk[:at]) + body + "".join(junk[at:]) + "<footer>foot</footer></body>"
        assert main_text(page) == "\n\n".join(texts), (layout, page)


def test_odd_pages_take_linear_time():
    began = time.perf_counter()
    assert main_text("<div>" * 50_000 + "deep" + "</div>" * 50_000) == "deep"
    for page in ("<p><section>" + "<div>" * 20_000 + "x", "<b><i>" * 20_000 + "</b>" * 20_000, '<a href="' * 30_000, "<a href='x\">" * 30_000, '<p title="' + "y>" * 100_000, "<!--" * 50_000, "<script>" * 50_000, "</p>" * 50_000):
        assert isinstance(main_text(page), str)
    assert time.perf_counter() - began < 20
