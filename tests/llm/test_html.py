"""Main text of pages: named cases, long pages, and a reference extractor for the given pages."""

from __future__ import annotations

import html
import re
import time
from pathlib import Path

import pyarrow.parquet as pq
import pytest

from kinetic.llm.html_text import main_text

LONG = "A sentence with a good many words in it that goes on for a while. " * 3


@pytest.mark.parametrize(
    ("page", "text"),
    [
        ('<p>long text of it<span class="share-count">3</span></p>', "long text of it"),
        ('<article><p>long text<span class="share-count">3</span> of it</p></article>', "long text of it"),
        ('<article><div class="post-header"><h1>T</h1></div><p>body</p></article>', "T\n\nbody"),
        (f'<div class="header">Site</div><div class="post-header"><h1>T</h1></div><p>{LONG}</p>', f"T\n\n{LONG.strip()}"),
        ('<div class="layout-sidebar-right"><article><h1>T</h1><p>body</p></article></div>', "T\n\nbody"),
        (f'<div class="layout-sidebar-right"><div class="has-menu"><h1>T</h1><p>{LONG}</p></div></div><div class="footer">me</div>', f"T\n\n{LONG.strip()}"),
        (f'<article><p>ab cd</p></article><div class="comments"><article class="comment"><p>{LONG}</p></article></div>', "ab cd"),
        ("<article><p>so <math><mi>x</mi>=1</math> holds</p></article>", "so x=1 holds"),
        ("<article><p>a<i>b<div>c</i>d</div></article>", "ab\n\ncd"),
    ],
)
def test_names_take_their_own_text_only(page, text):
    assert main_text(page) == text


@pytest.mark.parametrize("page", ["</p>" * 250_000, "<div><p>x" + "</p>" * 250_000, "<b><div>" + "<i>" * 60_000 + "</b>" * 60_000 + "x", '<div class="ad">' * 50_000 + "x", "<p>" * 100_000])
def test_long_pages_take_time_in_proportion(page):
    start = time.process_time()
    main_text(page)
    assert time.process_time() - start < 5


def reference(page: str) -> str:
    """Main text by substitutions, for pages that mark their article and close what they open."""
    body = re.search(r"(?s)<article\b[^>]*>(.*?)</article>", page)[1]
    body = re.sub(r"(?s)<!--.*?-->|<(script|style|form|aside|nav|footer)\b.*?</\1>", "", body)
    body = re.sub(r"</?(?:p|h\d|div|ul|ol|li|table|tr|td|th|section|blockquote|pre)\b[^>]*>", "\0", re.sub(r"<br ?/?>", " ", body))
    blocks = [re.sub(r"\s+", " ", html.unescape(b)).strip() for b in re.sub(r"<[^>]*>", "", body).split("\0")]
    return "\n\n".join(b for b in blocks if b)


def test_given_pages_equal_the_reference(sf):
    for page in pq.read_table(Path(sf) / "pages.parquet").column("html").to_pylist():
        assert main_text(page) == reference(page)
