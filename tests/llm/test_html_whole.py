"""Parts of an article beside its longest element, wrappers with hints, pages without telling names, odd markup."""

import re
import time

import pytest

from discourselab.llm.html_text import main_text

LONG = "word " * 199 + "end"
SIDE = '<div class="related"><p>Other things to read</p></div>'
PAGES = {
    "title and intro": (f'<article><h1>Title</h1><p>Intro.</p><div class="body"><p>{LONG}</p></div></article>', f"Title\nIntro.\n{LONG}"),
    "no article": (f'<body><div><h1>Title</h1><p>Intro.</p><div class="body"><p>{LONG}</p></div></div>{SIDE}</body>', f"Title\nIntro.\n{LONG}"),
    "list": (f"<body><p>Before.</p><ul><li>{LONG}</li></ul><p>After.</p></body>", f"Before.\n{LONG}\nAfter."),
    "table": (f"<div><p>Before.</p><table><tr><td>{LONG}</td></tr></table><p>After.</p></div>", f"Before.\n{LONG}\nAfter."),
    "quote": (f"<div><p>Before.</p><blockquote>{LONG}</blockquote><p>After.</p></div>", f"Before.\n{LONG}\nAfter."),
    "sections": (f"<article><section><p>{LONG}</p></section><section><p>{LONG[:150]}</p></section></article>", f"{LONG}\n{LONG[:150].strip()}"),
    "wrapper, article": (f'<body><div class="page no-sidebar"><article><p>{LONG}</p></article>{SIDE}</div></body>', LONG),
    "wrapper, main": (f'<body><div id="share-enabled"><main><p>{LONG}</p></main></div>{SIDE}</body>', LONG),
    "wrapper, neither": (f'<body><div class="page no-sidebar"><p>{LONG}</p></div>{SIDE}</body>', LONG),
    "nested wrappers": (f'<body><div class="has-menu"><div class="login-page"><article><p>{LONG}</p></article></div></div></body>', LONG),
    "still hidden": (f'<body><article><p>{LONG}</p><div id="comments"><article><p>{LONG}</p></article></div></article><div class="related"><article><p>Teaser.</p></article></div></body>', LONG),
    "related work": (f'<article><p>{LONG}</p><section id="related-work"><p>{LONG}</p></section><p class="related-art">See.</p><div class="related-posts"><p>Posts</p></div></article>', f"{LONG}\n{LONG}\nSee."),
    "open notice": (f'<article><p class="notice">Old.<p>{LONG}</p><ul><li class="promo">Buy<li>One<li>Two</ul><p>End.</p></article>', f"{LONG}\nOne\nTwo\nEnd."),
    "open cells": (f'<article><p>{LONG}<table><tr><td class="ad">x<td>A<td>B<tr><td>C</table><p>End.</article>', f"{LONG}\nA\nB\nC\nEnd."),
    "open head": (f"<head><title>T</title><p>{LONG}", LONG),
    "hinted all": (f'<body><div class="widget"><p>{LONG}</p></div><div><a href=x>a</a></div></body>', LONG),
    "form around": (f'<body><form><div><p>{LONG}</p><p>More.</p></div><div><a href=x>a b c d e</a></div></form></body>', f"{LONG}\nMore."),
    "menu alone": ("<body><nav><a href=x>One</a></nav><footer>Imprint</footer></body>", ""),
    "body alone": (f"<body><div><a href=x>One</a> <a href=y>Two</a></div><p>{LONG}</p><p>Short.</p><ul><li><a href=z>Three</a></ul></body>", f"{LONG}\nShort."),
    "inline hint": (f'<article><p>One <span class="share">Share</span> two. {LONG}</p></article>', f"One two. {LONG}"),
}


@pytest.mark.parametrize("name", PAGES)
def test_whole_article(name):
    page, expected = PAGES[name]
    assert main_text(page) == expected


def plain(html):
    """The page without names that tell: every sectioning element a div, no class, id or role."""
    html = re.sub(r' (?:class|id|role)="[^"]*"', "", html)
    return re.sub(r"(</?)(?:nav|article|main|footer|aside|header|section)\b", r"\1div", html)


def test_ratios_decide_without_telling_names(spark):
    pages = [r.html for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect()]
    assert all("<article>" in x and "<nav>" in x for x in pages)
    whole = [main_text(x) for x in pages]
    assert sum(main_text(plain(x)) == text for x, text in zip(pages, whole, strict=True)) >= 0.9 * len(pages)


def test_time_is_linear_in_depth():
    def seconds(n):
        begun = time.perf_counter()
        assert main_text("<div>" * n + "<p>x" + "</b>" * n) == "x"
        return time.perf_counter() - begun

    seconds(1000)
    assert seconds(40000) < 40 * seconds(4000)
