"""Main text on layouts that the given table does not have, and pages that a parser could choke on."""

import time

import pytest

from quorumgrad.llm import html_text

BODY = "".join(f"<p>Sentence {i} of the story has some words and goes on for a while.</p>" for i in range(8))
TEXT = " ".join(f"Sentence {i} of the story has some words and goes on for a while." for i in range(8))
COMMENTS = "".join(f'<article class="comment"><header><h3>User {i}</h3></header><p>I have read all of this and I think that it is quite long, yet good.</p></article>' for i in range(30))


def extract(page):
    return html_text.extract(page, html_text.best_path(page))


@pytest.mark.parametrize(
    ("page", "text"),
    [
        (f'<body><div class="content has-sidebar"><h1>Title</h1>{BODY}</div><div class="sidebar"><p>Side words.</p></div></body>', f"Title {TEXT}"),
        (f'<body><div class="layout-with-sidebar"><main><h1>Title</h1>{BODY}</main><aside>Side words.</aside></div></body>', f"Title {TEXT}"),
        (f'<body><div class="content-sidebar-wrap"><article><h1>Title</h1>{BODY}</article><div class="sidebar-primary"><p>Side words.</p></div></div></body>', f"Title {TEXT}"),
        (f'<body><header class="site-header"><h1>Site</h1></header><article><header class="entry-header"><h1>Title</h1><p class="byline">By somebody</p></header>{BODY}<footer>Filed under x</footer></article></body>', f"Title {TEXT}"),
        (f'<body><article><h1>Title</h1>{BODY}</article><section id="comments" class="comments-area">{COMMENTS}</section></body>', f"Title {TEXT}"),
        (f'<body><div class="siteHeader">Menu</div><div id="main"><h1>Title</h1>{BODY}<div class="post-share">Share this</div><div class="newsletterBox"><form><p>Sign up now for all the news.</p></form></div></div><div class="page-footer">Legal</div></body>', f"Title {TEXT}"),
        (f'<body><div class="article"><h1>Title</h1><ul class="nav-menu"><li>Home</li></ul>{BODY}<div class="ad-slot ads">Buy now</div><div class="cookie-notice">We use cookies</div></div></body>', f"Title {TEXT}"),
        (f'<body><article><h1 title="a > b">Title</h1><p data-x=it\'s>One "word" &amp; a &lt;tag&gt;.</p>{BODY}</article></body>', f'Title One "word" & a <tag>. {TEXT}'),
        (f'<body><article><h1>Title</h1>{BODY}<p>7 < 8 and 9 > 3</p></article></body>', f"Title {TEXT} 7 < 8 and 9 > 3"),
        (f'<body><article><h1>Title</h1>{BODY}</article><a href="unclosed>more</a></body>', f"Title {TEXT}"),
    ],
)
def test_layouts(page, text):
    assert extract(page) == text


@pytest.mark.parametrize(
    "page",
    [
        "<a " * 300_000, "<a b=\"" * 200_000, "<a b='x\" " * 100_000, "<p>x" * 200_000, "</a" * 300_000, "<!a" * 300_000, "<!--" * 200_000, "<b>" * 100_000 + "<div></div>" * 50_000,
        "<" * 1_000_000, "<script>" * 100_000, "<div class='a b c'>" * 50_000 + "text", "<a =" * 200_000, "<a ='\">" * 100_000, "&" * 500_000, "<div class=" + "x-" * 300_000 + ">t</div>",
    ],
    ids=range(15),
)
def test_odd_pages_take_time_in_proportion(page):
    began = time.process_time()
    assert isinstance(extract(page), str)
    assert time.process_time() - began < 20
