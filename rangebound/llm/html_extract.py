"""Main text of web pages: the maximum-scoring contiguous region.

A page is a sequence of words and tags. Words score positive and tags negative, with weights learned from pages whose
main part is marked (`article`, else `main` or an equivalent role): a symbol's weight is the log ratio of its frequency
inside and outside that part. A symbol is a tag, or a tag with one of its class names; words in elements whose
symbol is found far more often outside score negative, and so do words outside the marked part of a page that has
one. One linear scan finds the contiguous stretch of greatest total score. Its edges are moved to those of their
blocks, and it is widened to the element around it as long as what that adds scores no worse than `slack` words, so
that a short title isn't lost.

Furniture (menus, headers and footers of the page, sidebars, notices, adverts, forms, comments of readers), known by
tag, role or class name, is left out of the text. Crossing such an element costs the stretch `cross` words,
however long it is: an advert amid the paragraphs costs neither side, and no stretch ends in one. Scripts, styles and
templates aren't words at all. All other text of the region stays.

White space inside a block becomes one space, blocks are joined by one space in page order, and character references
are decoded. Defined results: a null or empty page, or one without words, has the empty text; repeated pages are
extracted each; unclosed and stray tags are tolerated, a tag that never ends is text, and a quote that never ends is
a letter. Parsing is linear in the page. A column that is named as the result gives way to it.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_sample, table

# Element names of HTML and the words by which sites name their page furniture.
RAW = frozenset("script style noscript template textarea title iframe svg select".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
FURNITURE = frozenset("nav header footer aside form menu dialog button head".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
NAMES = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promoted nav navbar navigation menu breadcrumb breadcrumbs footer sidebar aside rail cookie cookies consent gdpr "
    "notice popup modal newsletter subscribe subscription signup login comment comments respond replies reply disqus pagination pager toolbar outbrain taboola".split()
)
#: These name furniture only outside the main part.
OUTER_NAMES = frozenset("header masthead banner".split())
BLOCKS = frozenset(
    "address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li legend main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
INLINE_NEST = frozenset("a b i em strong span u s small big sub sup code q cite abbr mark font label time var kbd samp del ins".split())
CLOSES = {"p": frozenset("p".split()), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "td", "th"]), "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"])}

_NAME = re.compile(r"/?[a-zA-Z][^\s/>]*")
_ATTR = re.compile(r"""(class|id|role|hidden|aria-hidden|style)\s*(?:=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+)))?""", re.I)
_RAW_END = {t: re.compile(rf"</{t}\s*>", re.I) for t in RAW}


def _attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): m[2] or m[3] or m[4] or "" for m in _ATTR.finditer(raw)} if raw.strip(" /") else {}


def _words(value: str) -> list[str]:
    return [w for w in re.split(r"[^a-z]+", re.sub(r"(?<=[a-z])(?=[A-Z])", "-", value).lower()) if w]


def is_furniture(tag: str, attrs: dict[str, str], in_main: bool) -> bool:
    if tag in FURNITURE and not (tag == "header" and in_main):
        return True
    if attrs:
        if attrs.get("role", "").lower() in ROLES or "hidden" in attrs or attrs.get("aria-hidden") == "true" or "display:none" in attrs.get("style", "").replace(" ", "").lower():
            return True
        if tag not in ("html", "body", "article", "main"):
            named = {*_words(attrs.get("class", "")), *_words(attrs.get("id", ""))}
            return bool(named & NAMES) or not in_main and bool(named & OUTER_NAMES)
    return False


def tokens(page: str) -> Iterator[tuple[str, str, str, int, int]]:
    """(kind, name, attributes, start, end) of each tag, "open" or "close", and of comments and declarations ("skip").
    Every character is looked at a bounded number of times."""
    at, n = 0, len(page)
    last_end = page.rfind(">")
    quoted = True  # until a quote turns out never to end
    while (at := page.find("<", at)) >= 0:
        if page.startswith("<!--", at) or page.startswith("<![CDATA[", at):
            close = "-->" if page[at + 2] == "-" else "]]>"
            end = page.find(close, at + 4)
            end = n if end < 0 else end + 3
            yield "skip", "", "", at, end
        elif page[at + 1 : at + 2] in ("!", "?"):
            end = page.find(">", at)
            end = n if end < 0 else end + 1
            yield "skip", "", "", at, end
        else:
            m = _NAME.match(page, at + 1)
            if not m or at > last_end:
                at += 1
                continue
            end = _tag_end(page, m.end()) if quoted else page.find(">", m.end())
            if end < 0 and quoted:
                quoted = False
                end = page.find(">", m.end())
            if end < 0:
                at += 1
                continue
            name, end = m[0].lower(), end + 1
            yield ("close", name[1:], "", at, end) if name[0] == "/" else ("open", name, page[m.end() : end - 1], at, end)
        at = end


_STOP = re.compile("""[>"']""")


def _tag_end(page: str, at: int) -> int:
    """Place of the > that ends a tag, beyond quoted values; -1 if there is none."""
    while m := _STOP.search(page, at):
        if m[0] == ">":
            return m.start()
        # A quote opens a value only after the sign that gives one.
        if page[at : m.start()].rstrip()[-1:] == "=" or page[m.start() - 1] == "=":
            shut = page.find(m[0], m.end())
            if shut < 0:
                return -1
            at = shut + 1
        else:
            at = m.end()
    return -1


@dataclass
class Node:
    """An event: a run of text, or a tag. up: the element it lies in; low: inside furniture; edge: opens furniture."""

    kind: str  # "text", "open", "close"
    value: str
    up: int
    low: bool
    edge: bool = False


@dataclass
class Page:
    """events in page order; parent, tag, names (of its classes), main: by element number (0 is the page itself)."""

    events: list[Node] = field(default_factory=list)
    parent: list[int] = field(default_factory=lambda: [-1])
    tag: list[str] = field(default_factory=lambda: ["#page"])
    names: list[tuple[str, ...]] = field(default_factory=lambda: [()])
    main: list[bool] = field(default_factory=lambda: [False])

    def symbols(self, k: int) -> list[str]:
        return [self.tag[k], *(f"{self.tag[k]}.{x}" for x in self.names[k])]


def parse(page: str) -> Page:
    out = Page()
    stack: list[tuple[str, int, bool, bool]] = [("#page", 0, False, False)]  # tag, number, furniture, main
    articles: list[bool] = [False]
    at = 0
    n = len(page)
    until = 0  # text up to here belongs to a raw element

    def close(k: int) -> None:
        while len(stack) > k:
            tag, number, low, _ = stack.pop()
            out.events.append(Node("close", tag, number, low))

    def text(end: int) -> None:
        if end > at:
            out.events.append(Node("text", page[at:end], stack[-1][1], stack[-1][2]))

    for kind, tag, raw, start, end in tokens(page):
        if start < until:
            continue
        text(start)
        at = end
        if kind == "skip":
            continue
        if kind == "close":
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == tag:
                    close(k)
                    break
                if tag in INLINE_NEST and stack[k][0] in BLOCKS:
                    break  # a stray end of an inline element closes no block
            continue
        if tag in RAW:
            e = _RAW_END[tag].search(page, end)
            at = until = e.end() if e else n
            continue
        if tag in BLOCKS and tag not in VOID:
            shut = CLOSES.get(tag, frozenset()) | CLOSES["p"]
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] in shut:
                    close(k)
                    break
                if stack[k][0] in BLOCKS:
                    break
        attrs = _attributes(raw)
        _, up, low, in_main = stack[-1]
        main = in_main or tag in ("article", "main") or attrs.get("role", "").lower() in ("main", "article")
        own = not low and is_furniture(tag, attrs, in_main)
        low = low or own
        if tag in VOID or raw.endswith("/") and tag not in BLOCKS:
            out.events.append(Node("open", tag, up, low))
            continue
        out.parent.append(up)
        out.tag.append(tag)
        out.names.append(tuple(dict.fromkeys(_words(attrs.get("class", ""))))[:4])
        out.main.append(main and not low)
        articles.append(not low and (tag == "article" or articles[up]))
        number = len(out.parent) - 1
        stack.append((tag, number, low, main))
        out.events.append(Node("open", tag, number, low, own))
    text(n)
    close(1)
    if any(articles):
        out.main = articles
    return out


@dataclass(frozen=True)
class Weights:
    """word: of a word; tags: of a tag, opening or closing; other: of a tag not seen in training; outside: of a word
    outside the marked main part, on a page that has one; against: symbols whose words score -word; in words: cross,
    the cost of crossing furniture, beside, that of widening around it, and slack, what widening may cost in all."""

    word: float = 1.0
    tags: dict[str, float] = field(default_factory=dict)
    other: float = -0.5
    outside: float = -1.0
    against: frozenset[str] = frozenset()
    cross: float = 3.0
    beside: float = 1.0
    slack: float = 3.0


def symbol_counts(page: str) -> tuple[Counter, Counter] | None:
    """Symbols inside and outside the marked main part: tags, words, and words by the symbols of the elements around
    them (as "@symbol"); None for a page without one."""
    p = parse(page)
    if not any(p.main):
        return None
    inside, outside = Counter(), Counter()
    around: list[frozenset[str]] = [frozenset()]
    for k in range(1, len(p.parent)):
        around.append(around[p.parent[k]] | frozenset(p.symbols(k)))
    for e in p.events:
        to = inside if p.main[e.up] and not e.low else outside
        if e.kind == "text":
            n = len(e.value.split())
            to["#word"] += n
            if not e.low:  # what furniture holds says nothing about lists and links elsewhere
                for x in around[e.up]:
                    to[f"@{x}"] += n
        elif not e.low:
            to[e.value] += 1
    return inside, outside


def fit(pages: DataFrame, html: str = "html", key: str = "page_id", sample: int = 2000, common: int = 5000) -> Weights:
    """Learns from the marked pages among `sample` pages taken by a hash of the id; of their symbols the `common` most
    frequent. A word's weight is positive and a tag's negative whatever the counts."""
    rows = bounded_sample(pages.where(F.col(html).isNotNull()), F.col(key), sample).select(F.col(html).alias("html"))

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        inside, outside = Counter(), Counter()
        for b in batches:
            for h in b["html"]:
                if got := symbol_counts(h):
                    inside.update(got[0])
                    outside.update(got[1])
        names = sorted({*inside, *outside})
        if names:
            yield pd.DataFrame({"s": names, "a": [inside[x] for x in names], "b": [outside[x] for x in names]})

    counts = rows.mapInPandas(count, "s string, a long, b long").groupBy("s").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    return learn({r["s"]: (r["a"], r["b"]) for r in counts.orderBy(F.desc(F.col("a") + F.col("b")), "s").limit(common).collect()})


def learn(counts: dict[str, tuple[int, int]]) -> Weights:
    """From (inside, outside) by symbol. A symbol is against its words if they are five times as frequent outside, by
    20 words at least."""
    if not counts:
        return Weights()
    tags = {s: c for s, c in counts.items() if s[0] not in "#@"}
    ta, tb = sum(c[0] for c in tags.values()) + 1, sum(c[1] for c in tags.values()) + 1
    wa, wb = counts.get("#word", (0, 0))
    ratio = lambda a, b, x, y: math.log((a + 0.5) / x) - math.log((b + 0.5) / y)
    word = min(4.0, max(0.3, ratio(wa, wb, wa + ta, wb + tb)))
    weigh = {s: -word * min(1.5, max(0.25, 0.75 - ratio(*c, ta, tb) / 4)) for s, c in tags.items()}
    against = frozenset(s[1:] for s, (a, b) in counts.items() if s[0] == "@" and b >= 20 and ratio(a, b, wa + 1, wb + 1) < -math.log(5) and s[1:] not in ("html", "body", "div"))
    return Weights(word, weigh, -word / 2, -word, against)


def best_stretch(scores: list[float]) -> tuple[int, int]:
    """[start, end) of the greatest sum; the first and then the longest of equals; empty if none is positive."""
    best, at = 0.0, (0, 0)
    run, start = 0.0, 0
    for i, s in enumerate(scores):
        if run < 0 or run == 0 and s > 0 and run + s == s and start != i and not any(scores[start:i]):
            run, start = 0.0, i
        run += s
        if run > best or (run == best and best > 0 and at[0] == start):
            best, at = run, (start, i + 1)
    return at


def event_scores(p: Page, w: Weights) -> list[float]:
    marked = any(p.main)
    against = [False] * len(p.parent)
    for k in range(1, len(p.parent)):
        against[k] = against[p.parent[k]] or any(x in w.against for x in p.symbols(k))
    out = []
    for e in p.events:
        if e.low:
            out.append(-w.cross * w.word if e.edge else 0.0)
        elif e.kind == "text":
            each = -w.word if against[e.up] else w.outside if marked and not p.main[e.up] else w.word
            out.append(each * len(e.value.split()))
        else:
            out.append(w.tags.get(e.value, w.other))
    return out


def region(p: Page, w: Weights) -> tuple[int, int]:
    """[start, end) of the events of the main text."""
    scores = event_scores(p, w)
    lo, hi = best_stretch(scores)
    if hi <= lo:
        return 0, 0
    # Where each element's events begin and end.
    first, last = [len(p.events)] * len(p.parent), [0] * len(p.parent)
    for i, e in enumerate(p.events):
        first[e.up], last[e.up] = min(first[e.up], i), max(last[e.up], i + 1)
    for k in range(len(p.parent) - 1, 0, -1):
        up = p.parent[k]
        first[up], last[up] = min(first[up], first[k]), max(last[up], last[k])
    run = [0.0]
    for e, x in zip(p.events, scores, strict=True):
        run.append(run[-1] + (-w.beside * w.word if e.edge else x))
    around = lambda k: next((x for x in _path(p, k) if p.tag[x] in BLOCKS), 0)
    words = [i for i in range(lo, hi) if p.events[i].kind == "text" and not p.events[i].low and p.events[i].value.strip()]
    if not words:
        return 0, 0
    k = next(x for x in _path(p, p.events[words[0]].up) if last[x] > words[-1])  # the smallest element around all words
    home = set(_path(p, k))
    for i, side in ((words[0], first), (words[-1], last)):
        block = around(p.events[i].up)
        if block not in home:  # a block around all words is widened to below, if that pays
            lo, hi = (min(lo, side[block]), hi) if side is first else (lo, max(hi, side[block]))
    while True:
        a, b = min(lo, first[k]), max(hi, last[k])
        if run[lo] - run[a] + run[b] - run[hi] < -w.slack * w.word:
            return lo, hi
        lo, hi = a, b
        if k == 0:
            return lo, hi
        k = p.parent[k]


def _path(p: Page, k: int) -> list[int]:
    """The element and those around it, innermost first."""
    out = []
    while k >= 0:
        out.append(k)
        k = p.parent[k]
    return out


def extract(page: str | None, w: Weights) -> str:
    if not page:
        return ""
    p = parse(page)
    lo, hi = region(p, w)
    blocks: list[str] = []
    now: list[str] = []
    for e in p.events[lo:hi]:
        if e.kind == "text":
            if not e.low:
                now.append(e.value)
        elif e.value in BLOCKS and now:
            blocks.append("".join(now))
            now = []
    blocks.append("".join(now))
    clean = (" ".join(entities.unescape(b).split()) for b in blocks)
    return " ".join(x for x in clean if x)


def extract_pages(pages: DataFrame, weights: Weights, html: str = "html") -> DataFrame:
    """All columns of pages but the html, with main_text."""
    keep = [c for c in pages.columns if c not in (html, "main_text")]
    pages = pages.select(*keep, html)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = b[keep].copy()
            out["main_text"] = [extract(x, weights) for x in b[html]]
            yield out

    return pages.mapInPandas(run, pages.select(*keep, F.lit("").alias("main_text")).schema)


def op6_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    out = extract_pages(pages, fit(pages))
    return out.select("page_id", "url", F.col("main_text").alias("text"), F.length("main_text").cast("long").alias("n_chars"))
