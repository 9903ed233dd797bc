"""Main text of HTML pages by a maximum-scoring subsequence.

A page is a row of text segments and tags. A segment scores its number of words, each tag scores the (negative) weight of its
name and mark; the content is the contiguous stretch with the highest sum, found by one scan. Weights are learned from
labelled pages by a perceptron: pages whose content is marked by one article or main element label themselves. About `sample` of
them are used, those with the least hashes; pages of more than `SAMPLE_CHARS` characters don't label. Tags that no labelled
page holds have a starting weight by kind.

The scan trims short blocks at the stretch's ends, so these are put back: if the stretch lies within one article or main element,
all of that; else the paragraphs, headings, list items and cells next to it, up to the next tag that opens or closes a
container, unless most of their words are links.

Words inside elements that are never content don't count and are dropped, wherever they stand. These are menus, footers, forms
and the like by element name; header elements outside articles; and elements with a class, id or role that says so. An
element that holds the article, or outside of which nothing would be left, is a wrapper and stays, whatever its class. Parts of a
class name tell by themselves ("site-nav"), but not in names of states ("has-sidebar", "with-comments"), and an article's
own header ("entry-header") is content.

Nulls and pages without words give an empty text. Rows that repeat give equal rows. An unclosed element that is never content
counts as an empty one, but for scripts, styles and the like, which run to the page's end. Of stretches with equal scores the
first and shortest is taken. Very long pages are scanned whole. Columns beside page_id, url and html, those with names used here
included, are not read. Empty tables give no rows.
"""

from __future__ import annotations

import html
import re
from bisect import bisect
from collections import Counter
from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.llm.common import arrow_map, by_bytes

#: Longest page that is learned from.
SAMPLE_CHARS = 1 << 20

#: Names of HTML elements by kind, and words of class, id and role that mark what is no content.
RAW = ("script", "style", "noscript", "template", "textarea", "iframe", "svg", "title", "object", "select")
NEVER = {"nav", "footer", "aside", "form", "button", "menu", "dialog", "head"}
OUTER = {"html", "body", "article", "main", "header", "footer", "nav", "aside", "section", "form", "div", "ul", "ol", "li", "table", "a"}
CONTAINER = {"html", "body", "article", "main", "header", "footer", "nav", "aside", "section", "form", "div"}
BLOCK = {"address", "article", "aside", "blockquote", "body", "caption", "dd", "details", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hr", "html", "li", "main", "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul"}
SPACE = {"br", "wbr", "img"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
HEADS = {"banner", "contentinfo", "header", "masthead"}
MARKS = HEADS | {"ad", "ads", "advert", "adverts", "advertisement", "breadcrumb", "breadcrumbs", "comment", "comments", "cookie", "cookies", "consent", "disqus", "footer", "menu", "nav", "navbar", "navigation", "newsletter", "notice", "popup", "promo", "related", "replies", "share", "sharing", "sidebar", "social", "sponsor", "sponsored", "subscribe", "toolbar", "widget"}
STATES = {"has", "is", "no", "not", "with", "without"}
CONTENTS = {"article", "content", "entry", "post", "story"}

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(?:" + "|".join(RAW) + r")\b(?:\"[^\"]*\"|'[^']*'|[^'\">])*>|<[!?][^>]*>|</?[a-zA-Z](?:\"[^\"]*\"|'[^']*'|[^'\">])*>", re.S | re.I)
NAME = re.compile(r"</?([a-zA-Z][a-zA-Z0-9:-]*)")
ATTRIBUTE = re.compile(r"([^\s\"'<>/=]+)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'<>]+))?")
PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
RAW_END = {name: re.compile(rf"</{name}\s*>", re.I) for name in RAW}


def mark_of(tag: str, after: int) -> str:
    """The first word of a tag's class, id or role that marks what is no content, or an empty text."""
    for name, value in ATTRIBUTE.findall(tag, after):
        if value and name.lower() in ("class", "id", "role"):
            for one in value.strip("\"'").split():
                parts = [x.lower() for x in PART.findall(one)]
                if STATES.isdisjoint(parts):
                    for x in parts:
                        if x in MARKS and not (x in HEADS and not CONTENTS.isdisjoint(parts)):
                            return x
    return ""


def tokens(page: str | None) -> list[tuple[str, str, int]]:
    """(kind, value, words): kind "t" for text; "o" and "c" for tags, whose value is name or name.mark."""
    out: list[tuple[str, str, int]] = []
    page = page or ""
    at = 0
    while True:
        m = TAG.search(page, at)
        text = page[at : m.start() if m else len(page)]
        if text:
            out.append(("t", text, len(text.split())))
        if not m:
            return out
        at, tag = m.end(), m.group()
        n = NAME.match(tag)
        if not n:
            continue  # comment or declaration
        name = n.group(1).lower()
        if tag[1] == "/":
            out.append(("c", name, 0))
            continue
        if name in RAW:
            end = RAW_END[name].search(page, at)
            at = end.end() if end else len(page)
            continue
        mark = mark_of(tag, n.end()) if "=" in tag else ""
        out.append(("o", f"{name}.{mark}" if mark else name, 0))
        if name in VOID:
            continue
        if tag.endswith("/>"):
            out.append(("c", name, 0))


def spans(found: list[tuple[str, str, int]]) -> dict[int, int]:
    """Of opened elements, where they are closed."""
    ends: dict[int, int] = {}
    opened: dict[str, list[int]] = {}
    for k, (kind, value, _) in enumerate(found):
        if kind == "o":
            opened.setdefault(value.partition(".")[0], []).append(k)
        elif kind == "c" and opened.get(value):
            ends[opened[value].pop()] = k
    return ends


def content(found: list[tuple[str, str, int]]) -> list[tuple[str, str, int]]:
    """Tokens without the elements that are never content."""
    ends = spans(found)
    articles = sorted(k for k in ends if found[k][1].partition(".")[0] in ("article", "main"))
    titles = sorted(k for k in ends if found[k][1].partition(".")[0] == "h1")
    upto = list(accumulate((ends[k] for k in articles), max))  # the furthest end of the first articles
    holds = lambda k, inner: bisect(inner, ends[k]) > bisect(inner, k)
    stays: set[int] = set()  # wrappers, by what is left outside of them

    def gone(k: int) -> bool:
        name, _, mark = found[k][1].partition(".")
        if k not in ends or k in stays or name in ("html", "body", "article", "main") or holds(k, articles):
            return False
        if name in NEVER:
            return True
        head = name == "header" or mark in HEADS
        before = bisect(articles, k)
        if head and before and upto[before - 1] > k:
            return False  # an article's own
        return head or bool(mark) and not holds(k, titles)

    while True:
        out, dropped, k, left = [], [], 0, 0
        while k < len(found):
            if found[k][0] == "o" and gone(k):
                dropped.append(k)
                out.append(("o", found[k][1], 0))
                out.append(("c", found[k][1], 0))
                k = ends[k] + 1
                continue
            out.append(found[k])
            left += found[k][2]
            k += 1
        again = [k for k in dropped if found[k][1].partition(".")[0] not in NEVER - {"form"}]
        if left or not again:
            return out
        stays.update(again)


def key(token: tuple[str, str, int]) -> str:
    return token[0] + ":" + token[1]


def start_weight(name: str) -> float:
    """Weight of a tag before anything is learned."""
    bare = name[2:]
    if "." in bare or bare in NEVER:
        return -20.0
    return -2.0 if bare in OUTER else -0.5 if bare in BLOCK else -0.1


def best(found: list[tuple[str, str, int]], weights: dict[str, float]) -> tuple[int, int]:
    """The stretch [a, b) of tokens with the highest sum; (0, 0) if none is over 0."""
    top, a, b, total, start = 0.0, 0, 0, 0.0, 0
    for k, token in enumerate(found):
        if token[0] == "t":
            total += token[2]
        else:
            name = key(token)
            total += weights[name] if name in weights else start_weight(name)
        if total > top:
            top, a, b = total, start, k + 1
        if total <= 0:
            total, start = 0.0, k + 1
    return a, b


def widened(found: list[tuple[str, str, int]], a: int, b: int) -> tuple[int, int]:
    """The stretch with what the scan has trimmed from its ends."""
    if a == b:
        return a, b
    ends = spans(found)
    for k in sorted((k for k in ends if k <= a and ends[k] >= b - 1), reverse=True):
        if found[k][1].partition(".")[0] in ("article", "main"):
            return k + 1, ends[k]

    def reach(k: int, step: int) -> int:
        """As far as a container's tag: the place behind the last words that aren't mostly links."""
        place, words, linked, inside = k, 0, 0, 0
        while 0 <= k < len(found) and not (found[k][0] != "t" and found[k][1].partition(".")[0] in CONTAINER):
            kind, value, n = found[k]
            if kind != "t" and value.partition(".")[0] == "a":
                inside = max(0, inside + (step if kind == "o" else -step))
            words, linked, k = words + n, linked + n * bool(inside), k + step
        return k if 2 * linked <= words else place

    return reach(a - 1, -1) + 1, reach(b, 1)


def labelled(found: list[tuple[str, str, int]]) -> tuple[int, int] | None:
    """The stretch of words in a page's only article, or else its only main element."""
    for name in ("article", "main"):
        a = [k for k, t in enumerate(found) if t[0] == "o" and t[1].partition(".")[0] == name]
        b = [k for k, t in enumerate(found) if t[0] == "c" and t[1] == name]
        if len(a) == len(b) == 1 and a[0] < b[0]:
            words = [k for k in range(a[0], b[0]) if found[k][2]]
            return (words[0], words[-1] + 1) if words else None
    return None


def learn(pages: list[str], rounds: int = 5, margin: float = 5.0) -> dict[str, float]:
    """Weights under which the labelled stretch of each page scores best; never above 0."""
    weights: dict[str, float] = {}
    examples = [(x, y) for x in (content(tokens(p)) for p in pages) if (y := labelled(x))]
    for _ in range(rounds):
        wrong = 0
        for found, (a, b) in examples:
            got = best(found, weights)
            if got == (a, b):
                continue
            wrong += 1
            change = Counter(key(t) for t in found[a:b] if t[0] != "t")
            change.subtract(key(t) for t in found[got[0] : got[1]] if t[0] != "t")
            for name, n in change.items():
                if n:
                    old = weights[name] if name in weights else start_weight(name)
                    weights[name] = min(-0.001, old + (min(0.2, 0.1 * n) if n > 0 else max(-margin, n)))
        if not wrong:
            break
    return weights


def extract(page: str | None, weights: dict[str, float]) -> str:
    """Text of the best stretch: blocks in order, joined by an empty line."""
    found = content(tokens(page))
    a, b = widened(found, *best(found, weights))
    blocks, held = [], []
    for kind, value, _ in found[a:b]:
        if kind == "t":
            held.append(value)
            continue
        name = value.partition(".")[0]
        if name in BLOCK:
            blocks.append("".join(held))
            held = []
        elif name in SPACE:
            held.append(" ")
    blocks.append("".join(held))
    clean = (" ".join(html.unescape(x).split()) for x in blocks)
    return "\n\n".join(x for x in clean if x)


def labelled_sample(rows: DataFrame, sample: int) -> list[str]:
    """About `sample` pages that label themselves: those whose hash is below a threshold that their number gives.

    Only these pages come to the driver, so that its share doesn't grow with the number of partitions.
    """
    marked = rows.where(F.lower("html").rlike("<(article|main)[ >]") & (F.length("html") <= SAMPLE_CHARS)).select("html", F.xxhash64("page_id", "html").alias("h"))
    n = marked.count()
    if n > sample:
        marked = marked.where(F.col("h") < -(1 << 63) + (1 << 64) * sample // n)
    return [r.html for r in sorted(marked.collect(), key=lambda r: (r.h, r.html))]


def main_text(pages: DataFrame, sample: int = 500, weights: dict[str, float] | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of each row of (page_id, url, html)."""
    rows = pages.select(pages["page_id"].alias("page_id"), pages["url"].alias("url"), pages["html"].cast("string").alias("html"))
    if weights is None:
        weights = learn(labelled_sample(rows, sample))
    sent = pages.sparkSession.sparkContext.broadcast(weights)

    def work(batches):
        for batch in batches:
            pages_ = batch.column(2).to_pylist()
            for a, b in by_bytes(pages_):
                texts = [extract(x, sent.value) for x in pages_[a:b]]
                yield {"page_id": batch.column(0).slice(a, b - a), "url": batch.column(1).slice(a, b - a), "text": texts, "n_chars": list(map(len, texts))}

    schema = T.StructType([rows.schema["page_id"], rows.schema["url"], T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])
    return arrow_map(rows, work, schema)
