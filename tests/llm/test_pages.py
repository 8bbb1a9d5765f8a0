"""Main text of pages that are made from known blocks, and the edges."""

import random

import pytest

from claimfold.llm import html

W = html.Weights()
W.tags |= {t: -0.05 for t in ("p", "h1", "h2", "h3", "b", "br", "ul", "li", "section", "div", "span")}


def words(rng, n):
    return " ".join("".join(rng.choice("aeioutrnsl") for _ in range(rng.randint(2, 8))) for _ in range(n))


def boiler(rng):
    """A part that isn't main text."""
    links = lambda n: "".join(f'<li><a href="/{k}">{words(rng, 2)}</a></li>' for k in range(n))
    return rng.choice(
        [
            f"<nav><ul>{links(5)}</ul></nav>",
            f'<div class="site-footer">{words(rng, 6)}</div>',
            f'<div class="ad">{words(rng, 9)}</div>',
            f'<div id="cookieNotice"><p>{words(rng, 8)}</p></div>',
            f"<aside><h3>{words(rng, 2)}</h3>{words(rng, 12)}</aside>",
            f'<form action="/s"><label>{words(rng, 3)}</label><input name="q"></form>',
            f'<div class="sidebar widget"><ul>{links(3)}</ul></div>',
            f'<script>var a = "{words(rng, 4)}";</script><style>p {{ margin: 0 }}</style>',
            f'<div class="related"><ul>{links(4)}</ul></div>',
            f'<section class="comments"><div><p>{words(rng, 15)}</p></div></section>',
        ]
    )


def block(rng):
    """(markup, lines of text) of a block of the article."""
    a, b = words(rng, rng.randint(6, 25)), words(rng, rng.randint(3, 9))
    return rng.choice(
        [
            (f"<p>{a} <b>{b}</b>\n  {a}</p>", [f"{a} {b} {a}"]),
            (f'<h2 id="related-work">{b}</h2>', [b]),
            (f'<section id="discussion"><h3>{b}</h3><p>{a}</p></section>', [b, a]),
            (f'<div class="search-results-analysis"><p>{a}</p></div>', [a]),
            (f"<ul><li>{a}</li><li>{b} &amp; {b}</li></ul>", [a, f"{b} & {b}"]),
            (f'<div class="entry tags"><p>{a}</p></div>', [a]),
            (f'<p class="notice-board-study">{a}<br>{b}</p>', [a, b]),
        ]
    )


@pytest.mark.parametrize("tag", ["article", "main"])
def test_known_blocks(tag):
    rng = random.Random(6)
    for _ in range(200):
        body, lines = [], []
        for _ in range(rng.randint(3, 9)):
            markup, text = block(rng)
            body.append(markup)
            lines += text
            if rng.random() < 0.3:
                body.append(boiler(rng))
        outer = [boiler(rng) for _ in range(3)]
        page = f"<html><body>{outer[0]}{outer[1]}<{tag}>{''.join(body)}</{tag}>{outer[2]}</body></html>"
        assert html.extract(page, W) == "\n".join(lines), page


def test_names_without_an_article():
    """Where no element marks the article, whole classes alone decide."""
    text = "many words that make the text of this page long enough to be the main region of it"
    assert html.extract(f'<body><div class="entry tags"><p>{text}</p></div><div class="menu"><a href="/">a b</a></div></body>', W) == text
    assert html.extract(f'<body><div class="content"><p>{text}</p><div class="discussion"><p>some said that</p></div></div></body>', W) == text


def test_edges(spark):
    long_page = "<article>" + "<p>" + "word " * 200_000 + "</p><div class='ad'>x</div></article>"
    rows = [(1, "u", long_page, "a"), (1, "u", long_page, "a"), (2, None, None, None), (3, "u", "", "b"), (None, "u", "<article>some text here</article>", "c")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, h string")
    got = html.main_text(pages, html.fit(pages), keep=("url",)).collect()
    assert len(got) == 5 and sorted(r["n_chars"] for r in got) == [0, 0, 14, 999_999, 999_999]
    assert html.main_text(pages.where("false"), html.fit(pages.where("false"))).count() == 0
    with pytest.raises(ValueError):
        html.main_text(pages.withColumnRenamed("url", "text"), html.Weights(), keep=("text",))
