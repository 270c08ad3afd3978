"""Main text of web pages by minimum-cut labelling of text blocks.

A page becomes a row of text blocks. Every block gets two costs from a small
classifier (ancestors, class and id words, link density, length, punctuation):
what it costs to call it content, and what it costs to call it boilerplate.
These are terminal capacities, bounded by ``HARD``. Smoothness edges join
neighbours in page order, the stronger the fewer elements lie between them in
the tree, and blocks with one parent element. The minimum cut of that network
is the cheapest labelling; the blocks on the source side are the main text. So
a short block between two paragraphs goes with them, and one at their end does
not.

Defined results: a null or empty page has an empty text; unclosed or cut-off
tags are read as browsers do; a raw element without an end tag lasts to the end
of the page; a cut-off tag at the end of a page is dropped.
"""

from __future__ import annotations

import html
import re

from pyspark.sql import DataFrame

from graphweld.llm.common import map_slices

# Element names, and words of class, id and role attributes.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr button svg g text tspan path math mi mn mo ms mtext mrow mfrac msqrt mroot msup msub msubsup".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe object select option datalist xmp noembed noframes canvas audio video".split())
BOILER = frozenset("nav footer aside form menu dialog fieldset head".split())
CONTENT = frozenset("article main".split())
BOILER_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising advertorial adslot adbox adsense banner sponsor sponsored promo promotion nav navbar navigation menu menubar submenu breadcrumb breadcrumbs footer foot "
    "sidebar side aside related recommended recommendations trending popular widget widgets comment comments commentlist respond reply replies discussion disqus cookie cookies consent gdpr notice notices alert "
    "popup modal overlay newsletter subscribe subscription signup login signin register share sharing social toolbar pager pagination header masthead topbar search searchbox form disclaimer legal copyright "
    "skip tags taglist byline-links outbrain taboola hidden".split()
)
CONTENT_WORDS = frozenset("article post entry story content main body text post-content entry-content article-body maincontent".split())
BOILER_ROLES = frozenset("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar".split())

TOKEN = re.compile(r"<!--.*?(?:-->|--!>|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</?([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(>|\Z)|</[^>]*(?:>|\Z)", re.S)
RAW_END = {name: re.compile(rf"</{name}(?=[\s/>]|\Z)[^>]*(?:>|\Z)", re.I) for name in RAW}
ATTRIBUTE = re.compile(r"([^\s\"'<>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.S)
SPACE = re.compile(r"\s+")
SPLIT_WORDS = re.compile(r"[^a-z0-9]+")
SHUTS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
SELF_SHUT = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}

#: Most that ancestors can speak against a block; a quarter of it is the most that they can speak for it.
HARD = 60.0
#: Capacity between two neighbours within one element.
SMOOTH = 1.0


class Block:
    __slots__ = ("boiler", "content", "kind", "linked", "parts", "path", "size")

    def __init__(self, path, kind, boiler, content):
        self.parts, self.linked, self.size, self.path, self.kind, self.boiler, self.content = [], 0, 0, path, kind, boiler, content


def judge_attributes(name: str, attributes: str) -> tuple[float, float]:
    """(boilerplate, content) evidence of one start tag."""
    boiler = content = 0.0
    if name in BOILER:
        boiler = HARD
    elif name == "header":
        boiler = 4.0
    elif name in CONTENT:
        content = 6.0
    for key, a, b, c in ATTRIBUTE.findall(attributes) if attributes else ():
        key, value = key.lower(), (a or b or c).lower()
        if key == "role" and value in BOILER_ROLES:
            boiler += HARD
        elif key == "role" and value in ("main", "article") or key == "itemprop" and value == "articlebody":
            content += 6.0
        elif key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and "display:none" in value.replace(" ", ""):
            boiler += HARD
        elif key in ("class", "id"):
            for label in value.split():
                if label in CONTENT_WORDS:
                    content += 3.0
                elif name not in CONTENT and name not in ("body", "html") and (label in BOILER_WORDS or any(w in BOILER_WORDS for w in SPLIT_WORDS.split(label))):
                    boiler += 8.0
    return boiler, content


def blocks_of(page: str) -> list[Block]:
    """Text blocks in page order with the evidence of their ancestors."""
    # stack: name, id, boiler, content (sums over ancestors), is the element a link
    stack: list[tuple[str, int, float, float]] = [("", 0, 0.0, 0.0)]
    found: list[Block] = []
    current: Block | None = None
    links = serial = at = 0

    def add(text: str) -> None:
        nonlocal current
        if not text:
            return
        if current is None:
            if text.isspace():
                return
            name, _, boiler, content = next(x for x in reversed(stack) if x[0] not in INLINE)
            current = Block(tuple(x[1] for x in stack if x[0] not in INLINE), name, max(boiler, stack[-1][2]), content)
        current.parts.append(text)
        n = len(text) - text.count(" ")
        current.size += n
        if links:
            current.linked += n

    def close() -> None:
        nonlocal current
        if current is not None:
            found.append(current)
            current = None

    while m := TOKEN.search(page, at):
        add(page[at : m.start()])
        at = m.end()
        if m[1] is None:
            continue
        name = m[1].lower()
        if m[0].startswith("</"):
            if name == "br":
                add(" ")
                continue
            if name not in INLINE:
                close()
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == name:
                    links -= sum(1 for x in stack[k:] if x[0] == "a")
                    del stack[k:]
                    break
                if name in INLINE and stack[k][0] not in INLINE:
                    break
            continue
        if not m[3]:  # the page ends inside this tag
            continue
        if name in RAW and not m[2].endswith("/"):
            end = RAW_END[name].search(page, at)  # markup means nothing up to the end tag
            at = end.end() if end else len(page)
            close() if name not in ("script", "style", "noscript", "template") else None
            continue
        if name in VOID:
            if name == "br":
                add(" ")
            elif name not in INLINE:
                close()
            continue
        if name not in INLINE:
            close()
            if name in SHUTS_P and any(x[0] == "p" for x in stack):
                k = max(i for i, x in enumerate(stack) if x[0] == "p")
                if all(x[0] in INLINE or x[0] == "p" for x in stack[k:]):
                    links -= sum(1 for x in stack[k:] if x[0] == "a")
                    del stack[k:]
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] in SELF_SHUT.get(name, ()):
                    links -= sum(1 for x in stack[k:] if x[0] == "a")
                    del stack[k:]
                    break
                if stack[k][0] not in INLINE and stack[k][0] != "p":
                    break
        if m[2].endswith("/") and name not in INLINE and name not in BOILER:
            continue
        boiler, content = judge_attributes(name, m[2])
        serial += 1
        links += name == "a"
        top = stack[-1]
        stack.append((name, serial, top[2] + boiler, top[3] + content))
    if at < len(page):
        rest = page[at:]
        add(rest[: rest.rindex("<")] if re.search(r"<[a-zA-Z/!?][^>]*\Z", rest) else rest)
    close()
    return found


def costs(block: Block, text: str) -> tuple[float, float]:
    """(cost of calling it content, cost of calling it boilerplate)."""
    density = block.linked / max(1, block.size)
    words = text.count(" ") + 1
    stops = sum(text.count(c) for c in ".!?;:,")
    as_content = min(block.boiler, HARD) + 3.0 * density * density
    as_boiler = min(block.content, HARD / 4) + min(words, 40) * 0.05 + min(stops, 10) * 0.1
    if block.kind in ("p", "h1", "h2", "h3", "h4", "h5", "h6", "blockquote", "pre", "figcaption", "td", "dd"):
        as_boiler += 1.5
    elif block.kind == "li" and density > 0.5:
        as_content += 1.0
    elif not block.content:
        as_content += 0.8
    return as_content, as_boiler


def minimum_cut(source: list[float], sink: list[float], edges: dict[tuple[int, int], float]) -> list[bool]:
    """Which nodes stay with the source when source[i], sink[i] and symmetric edges are cut at least cost.

    Shortest augmenting paths over residual capacities (level graph and blocking flow).
    """
    n = len(source)
    s, t = n, n + 1
    to: list[int] = []
    cap: list[float] = []
    out: list[list[int]] = [[] for _ in range(n + 2)]

    def join(a: int, b: int, c: float, back: float) -> None:
        out[a].append(len(to))
        to.append(b)
        cap.append(c)
        out[b].append(len(to))
        to.append(a)
        cap.append(back)

    for i in range(n):
        straight = min(source[i], sink[i])  # saturated at once
        if source[i] > straight:
            join(s, i, source[i] - straight, 0.0)
        if sink[i] > straight:
            join(i, t, sink[i] - straight, 0.0)
    for (a, b), c in edges.items():
        join(a, b, c, c)
    while True:
        level = [-1] * (n + 2)
        level[s] = 0
        queue = [s]
        for a in queue:
            for e in out[a]:
                if cap[e] > 1e-9 and level[to[e]] < 0:
                    level[to[e]] = level[a] + 1
                    queue.append(to[e])
        if level[t] < 0:
            return [level[i] >= 0 for i in range(n)]
        ahead = [0] * (n + 2)
        path: list[int] = []
        a = s
        while True:
            if a == t:
                push = min(cap[e] for e in path)
                for e in path:
                    cap[e] -= push
                    cap[e ^ 1] += push
                cutoff = next(k for k, e in enumerate(path) if cap[e] <= 1e-9)
                del path[cutoff:]
                a = to[path[-1]] if path else s
                continue
            while ahead[a] < len(out[a]):
                e = out[a][ahead[a]]
                if cap[e] > 1e-9 and level[to[e]] == level[a] + 1:
                    break
                ahead[a] += 1
            if ahead[a] < len(out[a]):
                path.append(out[a][ahead[a]])
                a = to[path[-1]]
            elif a == s:
                break
            else:
                level[a] = -1
                e = path.pop()
                a = to[e ^ 1]


def steps_between(a: tuple[int, ...], b: tuple[int, ...]) -> int:
    """Steps from one element to another in the tree, given as paths from the root."""
    common = next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
    return len(a) + len(b) - 2 * common


def labelled(page: str | None, smooth: float = SMOOTH) -> list[tuple[str, bool]]:
    """(text, is content) of each block of the page. smooth: capacity between neighbours within one element; 0: each block alone."""
    found = []
    for b in blocks_of(page or ""):
        text = SPACE.sub(" ", html.unescape("".join(b.parts))).strip()
        if text:
            found.append((b, text))
    if not found:
        return []
    pairs = [costs(b, x) for b, x in found]
    edges: dict[tuple[int, int], float] = {}
    last: dict[int, int] = {}
    for i, (b, _) in enumerate(found):
        if i:
            edges[i - 1, i] = smooth / (1 + steps_between(found[i - 1][0].path, b.path) / 2)
        if (k := last.get(b.path[-1])) is not None and k != i - 1:
            edges[k, i] = smooth / 2
        last[b.path[-1]] = i
    keep = minimum_cut([p[1] for p in pairs], [p[0] for p in pairs], edges)
    return [(x, k) for (_, x), k in zip(found, keep, strict=True)]


def main_text(page: str | None) -> str:
    return " ".join(x for x, keep in labelled(page) if keep)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and its code points for every row; other columns are ignored."""

    def make():
        def work(part):
            texts = [main_text(x) for x in part.column("html").to_pylist()]
            return {"page_id": part.column("page_id"), "url": part.column("url"), "text": texts, "n_chars": [len(x) for x in texts]}

        return work

    kind = dict(pages.dtypes)["page_id"]
    return map_slices(pages.select("page_id", "url", "html"), "html", make, f"page_id {kind}, url string, text string, n_chars long")
