"""Main text of pages that name no article, and of links inside articles."""

import time

import pytest

from adapterlab.llm import html

LONG = "A sentence of the long section, with words and stops. Another one follows it, as long as the first. " * 12


def test_text_beside_one_long_part_stays():
    for tag in ("div", "section", "blockquote", "pre"):
        page = f'<body><div class="page"><div class="post"><div>An introduction, in two clauses. It says what follows.</div><{tag}><div>{LONG}</div></{tag}><div>A last remark, at the end. That is all.</div></div></div></body>'
        got = html.main_text(page)
        assert got.startswith("An introduction, in two clauses.") and got.endswith("at the end. That is all.") and LONG.strip() in got


def test_article_right_in_body_keeps_links_and_short_blocks():
    page = f'<body><div>By A. Writer</div><p>{LONG}</p><p>See <a href="x">the paper</a> for more.</p><p>{LONG}</p><div>Last updated in May</div></body>'
    got = html.main_text(page)
    assert "See the paper for more." in got and got.startswith("By A. Writer") and got.endswith("Last updated in May")


def test_linked_headline_stays_and_menus_go():
    page = f'<body><div><ul><li><a href="a">Home</a></li><li><a href="b">News</a></li></ul><h2><a href="c">The headline</a></h2><p>{LONG}</p><p><a href="d">A linked line</a></p><p>{LONG}</p></div></body>'
    got = html.main_text(page)
    assert got.startswith("The headline") and "A linked line" in got and "Home" not in got


@pytest.mark.parametrize(
    "page",
    [
        "<p>Hello world.</p><img src=" + "a" * 1_000_000,
        "<p>Hello world.</p><img " + "a=b " * 250_000,
        "<p>Hello world.</p>" + "<a \"> \"" * 100_001,
        "<p>Hello world.</p><a href='" + "x> " * 300_000,
        "<p>Hello world.</p>" + "<" * 1_000_000,
        "<p>Hello world.</p>" + "</b " * 250_000,
        "<p>Hello world.</p><i>" + "<b>" * 150_000 + "</i>" * 150_000,
        "<p>Hello world.</p><i><div>" + "<b>x" * 100_000 + "</i>" * 100_000,
        "<p>Hello world.</p>" + "<script>" * 100_000,
        "<p>Hello world.</p><p>" + "word " * 200_000 + "</p>",
        "<p>Hello world.</p><p>" + "!" * 1_000_000 + "</p>",
        "<p>Hello world.</p><!--" + "-" * 1_000_000,
        "<p>Hello world.</p>" + "&amp" * 250_000,
        "<p>Hello world.</p>" + "<a b" + " " * 1_000_000,
    ],
    ids=range(14),
)
def test_cut_off_or_odd_markup_of_a_megabyte_is_read_once(page):
    began = time.process_time()
    assert html.main_text(page).startswith(("Hello world.", "word", "!"))
    assert time.process_time() - began < 8


def test_twice_the_markup_takes_about_twice_the_time():
    def took(n):
        began = time.process_time()
        html.main_text("<p>Hello world.</p>" + "<i><div><b c=\"'>x</i>" * n + "<img src=" + "a" * n)
        return time.process_time() - began

    took(1000)
    assert took(40_000) < 8 * max(took(10_000), 0.05)


def test_path_scores_decide(monkeypatch):
    """None of the names says what is what: only ratios of text and punctuation of the paths do."""
    teasers = "".join(f'<div class="q{i}"><span>Offer {i}</span></div>' for i in range(6))
    page = f'<body><div class="z1">{teasers}</div><div class="z2"><div class="z3"><div>{LONG}</div><div>A short remark</div><div>{LONG}</div></div></div><div class="z4"><span>Imprint</span></div></body>'
    want = f"{LONG.strip()} A short remark {LONG.strip()}"
    assert html.main_text(page) == want
    monkeypatch.setattr(html, "content_paths", lambda scores: set(scores))
    assert "Offer 3" in html.main_text(page) and "Imprint" in html.main_text(page)


def test_without_scores_furniture_would_stay(monkeypatch):
    page = f'<body><nav><ul><li><a href="a">Home</a></li></ul></nav><div class="ad">Buy it, now.</div><article><h1>Head</h1><p>{LONG}</p></article><footer>Imprint, here.</footer></body>'
    assert html.main_text(page) == f"Head {LONG.strip()}"
    monkeypatch.setattr(html, "content_paths", lambda scores: set(scores))
    assert "Home Buy it, now." in html.main_text(page)


def test_pages_of_links_or_furniture_only():
    assert html.main_text('<ul><li><a href="a">Home</a></li></ul>') == ""
    assert html.main_text("<nav>One, two.</nav><footer>Three.</footer>") == ""
    assert html.main_text("Words alone, no tag.") == "Words alone, no tag."
    assert html.main_text("a < b, and <b>c</b> > d.") == "a < b, and c > d."
