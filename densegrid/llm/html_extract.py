"""Main text of web pages as a maximum-scoring subsequence.

A page is a sequence of words and tags, each with a score that labelled pages have
taught. Tags score negative. A word scores by the elements around it, by their tags
and the names in their attributes: positive where labelled pages have article text,
negative where they have page furniture. One linear scan finds the contiguous region
of the largest sum; the text is what scores positive in it, block by block.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from densegrid.llm._text import column, of_columns

_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_MARK = re.compile(r"[\"'>]")
_ATTRIBUTE = re.compile(r"([^\s=\"'/>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_NO_DISPLAY = re.compile(r"(?:^|;)\s*display\s*:\s*none\b")
_SPLIT = re.compile(r"[^a-z]+")

# HTML element names by their role in the public standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title iframe xmp noembed noframes".split())
MUTE = frozenset("noscript template svg math canvas object audio video select".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSED_BY = {"p": frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split()), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"]), "tr": frozenset(["tr"]), "option": frozenset(["option"])}
# Names that public web pages give to furniture and to article text; the labelled pages use them.
FURNITURE = "ad ads advert advertisement adverts advertising banner sponsor sponsored promo promotion nav navbar navigation menu breadcrumb breadcrumbs sidebar aside footer header masthead cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe signup login share sharing social related recommended recommendations widget toolbar pagination pager comment comments disqus respond reply replies form search copyright legal disclaimer skip toc tags".split()
CONTENT = "article articlebody body content entry main page post story text wrapper container column row wide".split()
_MAIN = "data-main"


def labelled_pages() -> list[str]:
    """Whole pages, made by rule from the public conventions; text under a ``data-main`` element is article."""
    words = "one two three four five six seven eight nine ten eleven twelve".split()
    say = lambda n: " ".join(words[k % len(words)] for k in range(n))
    links = "<ul>" + "".join(f"<li><a href='/{w}'>{w}</a></li>" for w in words[:5]) + "</ul>"
    looks = [lambda x: f"<div {x}>{say(9)}</div>", lambda x: f"<div {x}><p>{say(30)}</p></div>", lambda x: f"<div {x}>{links}</div>", lambda x: f"<section {x}><h3>{say(2)}</h3><p>{say(20)}</p></section>", lambda x: f"<div {x}><span>{say(3)}</span><a href='/'>{say(2)}</a> <b>{say(2)}</b> <em>{say(1)}</em> <strong>{say(2)}</strong> <i>{say(1)}</i> <code>{say(1)}</code></div>", lambda x: f"<ul {x}><li>{say(3)}</li></ul>", lambda x: f"<p {x}>{say(12)}</p>", lambda x: f"<div {x}><article><p>{say(25)}</p></article></div>"]
    hidden = ["hidden", "aria-hidden='true'", "style='display:none'"]
    names = [f"{how}='{n}'" for n in FURNITURE for how in ("class", "id")] + ["role='navigation'", "role='banner'", "role='complementary'", "role='search'"] + hidden * 4
    plain = [f"<nav>{links}</nav>", f"<nav><a href='/'>{say(1)}</a><p>{say(4)}</p></nav>", f"<header><h1>{say(2)}</h1>{links}</header>", f"<header><div><a href='/'>{say(3)}</a></div><p>{say(8)}</p></header>", f"<footer>{say(12)}<a href='/x'>{say(1)}</a></footer>", f"<footer><div><p>{say(20)}</p>{links}</div></footer>", f"<aside><h2>{say(2)}</h2><p>{say(25)}</p></aside>", f"<aside>{say(4)}{links}</aside>", f"<form><p>{say(15)}</p><label>{say(2)}</label><button>{say(1)}</button></form>", f"<form><fieldset>{say(6)}</fieldset></form>", f"<div><a href='/a'>{say(1)}</a><a href='/b'>{say(1)}</a></div>", f"<ul><li><a href='/a'>{say(2)}</a></li></ul>", f"<dialog>{say(12)}<button>{say(1)}</button></dialog>", f"<menu><li>{say(3)}</li></menu>"]
    marked = f"<b>{say(1)}</b> <strong>{say(1)}</strong> <em>{say(2)}</em> <i>{say(1)}</i> <code>{say(1)}</code> <span>{say(2)}</span><br>{say(9)}"
    table = f"<table><tbody><tr><th>{say(1)}</th><td>{say(6)}</td></tr></tbody></table>"
    body = f"<p>{say(40)}</p><h2>{say(3)}</h2><p>{marked}</p><h3>{say(2)}</h3><blockquote><p>{say(12)}</p></blockquote><ul><li>{say(9)}</li></ul><ol><li>{say(5)}</li></ol><p>{say(20)} <a href='/x'>{say(2)}</a> {say(20)}</p><pre>{say(8)}</pre>{table}<dl><dt>{say(1)}</dt><dd>{say(5)}</dd></dl><figure><figcaption>{say(5)}</figcaption></figure><div>{say(30)}</div>"
    heads = [f"<h1>{say(4)}</h1>", f"<header><h1>{say(4)}</h1><p>{say(3)}</p></header>", f"<header><h2>{say(3)}</h2></header>", ""]
    frames = [("<article>", "</article>"), ("<main>", "</main>"), ("<div>", "</div>"), ("<section>", "</section>"), ("", ""), *((f"<div class='{n}'>", "</div>") for n in CONTENT), *((f"<div id='{n}'><article>", "</article></div>") for n in CONTENT)]
    pages = []
    for k, name in enumerate(names):
        begin, end = frames[k % len(frames)]
        head = heads[k % 4] if "article" in begin or "main" in begin or k % 4 in (0, 3) else ""
        out = [look(name) for look in (looks if name in hidden else [looks[(k + j) % len(looks)] for j in range(5)])]
        shell = [plain[(k + j) % len(plain)] for j in range(4)]
        before, inside, after = [shell[0], out[0]], [out[1], out[3]], [out[2], shell[1], shell[2], out[4]]
        parts = f"<div {_MAIN}>{head}{body}</div>" + "".join(inside) + f"<div {_MAIN}>{body}</div>"
        pages.append(f"<html><body>{''.join(before)}{begin}{parts}{end}{''.join(after)}</body></html>")
    return [*pages, *(f"<body>{x}<article><div {_MAIN}>{body}</div>{x}</article></body>" for x in plain[6:10]), f"<div {_MAIN}>{say(20)}</div>", *[f"<html><body><div {_MAIN}>{say(20)}<p>{say(9)}</p></div></body></html>", f"<body><div><div {_MAIN}>{body}</div></div></body>", f"<body><div><article><div {_MAIN}>{body}</div></article></div></body>"] * 20]


@lru_cache(maxsize=64)
def _end_of(name: str) -> re.Pattern:
    return re.compile(rf"</{re.escape(name)}(?=[\s/>])", re.I)


def tokens(page: str) -> Iterator[tuple[str, str, str]]:
    """(kind, name or text, attributes) of a page: text, open, close. Comments and the content of raw elements are left out.

    One pass; a quote counts only after an equals sign, one that never ends counts for nothing.
    """
    at, n, unpaired = 0, len(page), set()
    while at < n:
        begin = page.find("<", at)
        if begin != at:
            yield "text", page[at : n if begin < 0 else begin], ""
            if begin < 0:
                return
        m = _TAG.match(page, begin)
        if m is None:
            for opening, closing in (("<!--", "-->"), ("<![CDATA[", "]]>"), ("<!", ">"), ("<?", ">"), ("</", ">")):
                if page.startswith(opening, begin):
                    end = page.find(closing, begin + len(opening))
                    at = n if end < 0 else end + len(closing)
                    break
            else:
                yield "text", "<", ""
                at = begin + 1
            continue
        at = m.end()
        while True:
            mark = _MARK.search(page, at)
            if mark is None:  # the tag has no end
                return
            at = mark.end()
            if mark[0] == ">":
                break
            if mark[0] not in unpaired and page[m.end() : mark.start()][-40:].rstrip()[-1:] == "=":
                close = page.find(mark[0], at)
                if close < 0:
                    unpaired.add(mark[0])
                else:
                    at = close + 1
        name, attributes = m[2].lower(), page[m.end() : at - 1]
        if m[1]:
            yield "close", name, ""
        elif name in RAW:
            end = _end_of(name).search(page, at)
            close = page.find(">", end.end()) if end else -1
            at = n if close < 0 else close + 1
        else:
            yield "open", name, attributes


class Element:
    """An open element: its name, what it and those around it say of the words in it, and whether they are no text at all."""

    __slots__ = ("name", "says", "mute")

    def __init__(self, name: str, says, mute: bool):
        self.name, self.says, self.mute = name, says, mute


def walk(page: str, says) -> Iterator[tuple[str, str, list[Element], bool]]:
    """(kind, text or name, open elements, whether a new block begins) for text, open and close tokens, mute ones left out.

    ``says(name, attributes)`` is what an element says; it is added up inwards. Elements that the standard
    lets end without a tag end where another begins; an end tag without a beginning
    counts as a tag and closes nothing.
    """
    stack: list[Element] = []
    mute, names = 0, Counter()

    def end() -> Element:
        nonlocal mute
        e = stack.pop()
        mute -= e.mute
        names[e.name] -= 1
        return e

    for kind, name, attributes in tokens(page):
        if kind == "text":
            if not mute:
                yield kind, name, stack, False
            continue
        if kind == "close":
            while names[name]:
                if end().name == name:
                    break
            if not mute:
                yield kind, name, stack, name not in INLINE
            continue
        while stack and name in CLOSED_BY.get(stack[-1].name, ()):
            end()
        if name not in INLINE:  # an inline element left open ends with its block
            k = len(stack)
            while k and stack[k - 1].name in INLINE:
                k -= 1
            if k and name in CLOSED_BY.get(stack[k - 1].name, ()):
                while len(stack) >= k:
                    end()
        if not mute:
            yield kind, name, stack, name not in INLINE
        if name not in VOID and not attributes.rstrip().endswith("/"):
            own = says(name, attributes)
            stack.append(Element(name, stack[-1].says + own if stack else own, name in MUTE))
            mute += name in MUTE
            names[name] += 1


def features(name: str, attributes: str) -> list[str]:
    """What can be said of an element: its tag, the names it bears, whether it is hidden."""
    out = ["<" + name]
    for m in _ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if key == "hidden" and value != "until-found" or key == "aria-hidden" and value.strip() == "true" or key == "style" and _NO_DISPLAY.search(value):
            out.append("hidden")
        elif key in ("class", "id", "role"):
            out += ["." + x for x in value.split()]
        elif key == _MAIN:
            return [_MAIN]  # only a label, no element of the page
    return out


class Weights:
    """Scores of words and tags, fitted on labelled pages.

    What the elements around a word say adds up to the log odds that it is article
    text: a logistic regression over their tags and names. A tag's score is how much
    rarer, in logarithms, it is in articles than outside; never above ``LEAST``.
    """

    MOST, LEAST = 3.0, -0.05

    def __init__(self, pages: list[str] | None = None):
        rows: dict[tuple[frozenset, bool], int] = Counter()
        tags = {True: Counter(), False: Counter()}
        count = {True: 1.0, False: 1.0}
        for page in pages or labelled_pages():
            for kind, x, stack, _ in walk(page, features):
                around = frozenset(stack[-1].says if stack else ())
                label = _MAIN in around
                if kind != "text":
                    tags[label][x] += 1
                elif x.strip():
                    rows[around - {_MAIN}, label] += 1
                    count[label] += len(x.split())
        known = sorted({f for around, _ in rows for f in around})
        place = {f: i for i, f in enumerate(known)}
        x = np.zeros((len(rows), len(known) + 1))
        x[:, -1] = 1
        y, n = np.zeros(len(rows)), np.zeros(len(rows))
        for i, ((around, label), times) in enumerate(sorted(rows.items(), key=lambda r: (sorted(r[0][0]), r[0][1]))):
            x[i, [place[f] for f in around]] = 1
            y[i], n[i] = label, 1 + math.log(times)
        w, ridge = np.zeros(x.shape[1]), np.full(x.shape[1], 0.05)
        for _ in range(30):
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            step = np.linalg.solve((x.T * (n * p * (1 - p))) @ x + np.diag(ridge), x.T @ (n * (y - p)) - ridge * w)
            w += step
            if abs(step).max() < 1e-6:
                break
        self.says, self.bias = dict(zip(known, w[:-1].tolist(), strict=True)), float(w[-1])
        rare = lambda t: math.log((tags[True][t] + 0.5) / count[True]) - math.log((tags[False][t] + 0.5) / count[False])
        self.tags = {t: min(self.LEAST, rare(t)) for t in {*tags[True], *tags[False]}}
        self.other = sorted(self.tags.values())[len(self.tags) // 2] if self.tags else self.LEAST

    def tag(self, name: str) -> float:
        return self.tags.get(name, self.other)

    def named(self, name: str) -> float:
        """What a name says: its own weight, or that of its parts if all are known and of one sign; else nothing."""
        if name in self.says:
            return self.says[name]
        parts = [self.says.get("." + w) for w in _SPLIT.split(name[1:]) if w]
        if not parts or None in parts or min(parts) * max(parts) <= 0:
            return 0.0
        return min(parts) if min(parts) < 0 else max(parts)

    def element(self, name: str, attributes: str) -> float:
        return sum(self.named(f) if f[0] == "." else self.says.get(f, 0.0) for f in features(name, attributes))

    def word(self, stack: list[Element]) -> float:
        return max(-self.MOST, min(self.MOST, self.bias + (stack[-1].says if stack else 0.0)))


def scored(page: str, weights: Weights) -> tuple[list[list[str | None]], list[tuple[float, int, int, int]]]:
    """Words by block (None: white space), and runs of tokens: score of the run, its block (-1: a tag), first word, end."""
    blocks: list[list[str | None]] = [[]]
    runs: list[tuple[float, int, int, int]] = []
    for kind, x, stack, breaks in walk(page, weights.element):
        if kind != "text":
            if breaks and blocks[-1]:
                blocks.append([])
            elif x == "br" and blocks[-1] and blocks[-1][-1] is not None:
                blocks[-1].append(None)
            runs.append((weights.tag(x), -1, 0, 0))
            continue
        block, text = blocks[-1], html.unescape(x)
        words = text.split()
        if block and block[-1] is not None and text[:1].isspace():
            block.append(None)
        if words:
            first = len(block)
            block += [part for w in words for part in (w, None)][:-1]
            runs.append((weights.word(stack) * len(words), len(blocks) - 1, first, len(block)))
            if text[-1:].isspace():
                block.append(None)
    return blocks, runs


def best_region(scores: list[float]) -> tuple[int, int]:
    """First and end of the contiguous run with the largest sum, the first of equals; empty if no sum is positive."""
    best, now, start, region = 0.0, 0.0, 0, (0, 0)
    for k, score in enumerate(scores):
        if now <= 0:
            now, start = 0.0, k
        now += score
        if now > best:
            best, region = now, (start, k + 1)
    return region


def main_text(page: str | None, weights: Weights) -> str:
    """The article of a page: its blocks in order, one to a line; '' if there is none."""
    if not page:
        return ""
    blocks, runs = scored(page, weights)
    begin, end = best_region([score for score, *_ in runs])
    kept: dict[int, list[str]] = {}
    for score, block, a, b in runs[begin:end]:
        if block >= 0 and score > 0:
            held = kept.setdefault(block, [])
            if held and a and blocks[block][a - 1] is None:
                held.append(" ")
            held += [" " if w is None else w for w in blocks[block][a:b]]
    lines = (" ".join("".join(parts).split()) for _, parts in sorted(kept.items()))
    return "\n".join(x for x in lines if x)


def extract_pages(pages: DataFrame, weights: Weights | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of ``pages``; the whole html is read.

    A null or empty page gives an empty text. Null ids and urls are carried along,
    repeated rows stay repeated, other columns are ignored.
    """
    shipped = weights or Weights()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(h, shipped) for h in column(batch, "html")]
            counts = pa.array([len(t) for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), counts], ["page_id", "url", "text", "n_chars"])

    return of_columns(pages, page_id="long", url="string", html="string").mapInArrow(run, "page_id long, url string, text string, n_chars long")
