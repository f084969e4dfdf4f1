import random
import time

import pytest

from densegrid.llm import html_extract as h
from tests.llm.test_operators import page, prose

W = h.Weights()
PARAS = [prose(40, random.Random(i)) for i in range(4)]
ARTICLE = "".join(f"<p>{p}</p>" for p in PARAS)
TEXT = "\n".join(PARAS)


def test_best_region_equals_brute_force():
    rng = random.Random(3)
    for _ in range(300):
        scores = [rng.choice([-3.0, -1.0, -0.5, 0.0, 0.5, 1.0, 2.0]) for _ in range(rng.randint(0, 30))]
        sums = {(a, b): sum(scores[a:b]) for a in range(len(scores)) for b in range(a + 1, len(scores) + 1)}
        a, b = h.best_region(scores)
        assert sum(scores[a:b]) == max([0.0, *sums.values()])
        assert (a, b) == (0, 0) or sums[a, b] > 0


@pytest.mark.parametrize("raw", ["<script>for(var i=0;i<n;i++){f('</p>')}</script>", "<script>var a = '<!--';</script>", "<SCRIPT>if (a<b && c>d) x='<script>'</SCRIPT >", "<style>a>b{content:'<p>'}</style>", "<!-- <p>no</p> > -->", "<textarea><p>no</p></textarea>", "<svg><text>no</text></svg>", "<noscript><p>no</p></noscript>", "<select><option>no<option>no</select>", "<?php no ?>", "<![CDATA[no]]>", "<img alt='a > b <p>no'>"])
@pytest.mark.parametrize("place", range(3))
def test_raw_and_hidden_pieces_say_nothing(raw, place):
    parts = [f"<p>{p}</p>" for p in PARAS]
    parts.insert((0, 2, 4)[place], raw)
    assert h.main_text(page(f"<article>{''.join(parts)}</article>"), W) == TEXT


@pytest.mark.parametrize("bad", ["<p title=\"never ends>", "<p title=don't>", "</nothing>", "</>", "< ", "<p", "<script>never ends", "<!-- never ends", "<b><i><u>", "</p></p></div></div></div>"])
def test_malformed_pieces_lose_no_earlier_text(bad):
    got = h.main_text(f"<html><body><article>{ARTICLE}{bad}", W)
    assert got == TEXT or got == TEXT + "\n<"


def test_the_region_decides():
    """The region alone, without the words' own signs, is the article; everything is not."""
    html = page(f"<article>{ARTICLE}</article>")
    blocks, runs = h.scored(html, W)
    begin, end = h.best_region([r[0] for r in runs])
    text = lambda rs: [w for _, k, a, b in rs if k >= 0 for w in blocks[k][a:b] if w]
    assert text(runs[begin:end]) == TEXT.split() and len(text(runs)) > len(TEXT.split())


def test_furniture_far_away_is_left_out_whatever_its_name():
    """No name tells: the links between cost more than the stray words bring."""
    links = "".join(f"<div><a href='/{i}'>x{i}</a></div>" for i in range(30))
    assert h.main_text(f"<body><div>stray words</div>{links}<div>{ARTICLE}</div>{links}<div>more stray words</div></body>", W) == TEXT


@pytest.mark.parametrize("after", ["<section class='comments'><article class='comment'><p>{}</p></article></section>", "<div id='respond'><form><p>{}</p></form></div>", "<aside><p>{}</p></aside>", "<div class='related-posts widget'><p>{}</p></div>", "<footer><b>{}</b></footer>", "<nav><b>{}</b></nav>"])
@pytest.mark.parametrize("inside", [True, False])
def test_comments_and_the_like(after, inside):
    extra = after.format(prose(25, random.Random(9)))
    body = f"<article>{ARTICLE}{extra}</article>" if inside else f"<article>{ARTICLE}</article>{extra}"
    assert h.main_text(page(body), W) == TEXT


def test_spaces_and_references():
    assert h.main_text("<p>a <b>b</b>c&nbsp;d&lt;e<br>f<span> g </span>h</p>", W) == "a bc d<e f g h"


@pytest.mark.parametrize("piece", ["<p>word ", "<a href='x", "word < ", "<p title=\"", "<div>", "<div>word ", "<i>word</b> ", "&amp;"])
def test_long_pages_take_linear_time(piece):
    took = []
    for n in (20_000, 80_000):
        html = "<article>" + piece * n
        began = time.perf_counter()
        h.main_text(html, W)
        took.append(time.perf_counter() - began)
    assert took[1] < 30 and took[1] < 14 * took[0] + 1
