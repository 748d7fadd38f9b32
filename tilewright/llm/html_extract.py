"""Main text of web pages by tag-path ratios.

Every text node has the path of elements from the root. Per path, its text length and its punctuation
are summed over its nodes; a node's value fuses its path's ratios with a smoothing of the node values
around it in page order, and nodes above a share of the page's mean are content. What is no page text
by its element or role (menus, headers, footers, asides, forms, scripts, styles, hidden parts) is left
out before. Words of class and id (adverts, notices, comments, sharing) only weigh: a node below an
element so marked needs twice the typical content's value, and one that is marked itself among unmarked
ones of its path is measured by its own text; no mark counts on html, body, main, article or, unless a region has other
text, on an element with over half of the page's text. Marked nodes beside a region with text are none.

The content root is the innermost region (article, main) or else the smallest element that holds most
of the content's mass. Gaps between content are bridged: below the root unmarked short nodes stay
(without a region those within `REACH` nodes of content). Outside the root stay content nodes (of
other regions, if there is one) and the headings right before them.

Null, empty and blank pages give an empty text; a page without mark-up is all text. Unclosed and
misnested elements are closed where their parent ends. A page is read once from its start to its end,
however broken it is. Repeated rows give equal rows, an empty table an empty result. Only page_id, url
and html are read.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TAG = re.compile(r"<(/?)([a-zA-Z][^\s/><]*+)((?:[^<>\"']++|\"[^\"]*+\"|'[^']*+')*+)>")
NAME = re.compile(r"<(/?)([a-zA-Z][^\s/><]*+)")
ATTR = re.compile(r"""(?<![\w:-])([\w:-]++)\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s"'>]++))""")
#: After so many tags whose quotes don't close, quotes are no longer looked at.
MOST_BROKEN = 100
SPACES = re.compile(r"\s+")
PUNCTUATION = re.compile(r"[.,;:!?¡¿。，、；：！？…]")

# Elements by their role in a page.
RAW = frozenset("script style noscript template svg iframe object math".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr img br".split()
)
CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split()
)
REGION = frozenset("article main".split())
NEVER = frozenset("head nav footer aside form button select option textarea input dialog menu title canvas audio video".split())
ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert menu menubar toolbar form".split())
MARKS = frozenset(
    """ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promotion promoted banner cookie cookies consent gdpr
    notice notices notification alert popup modal overlay paywall newsletter subscribe subscription signup login sidebar sidebars widget widgets
    menu menus nav navbar navigation breadcrumb breadcrumbs masthead footer footers comment comments commentlist disqus replies reply respond
    share sharing social related recommended recommendations pagination pager toolbar skip""".split()
)
NEVER_BY_WORDS = frozenset("html body main article".split())
ITEMS = frozenset("li dt dd tr td th option".split())
HOLDERS = frozenset("ul ol dl table div article section".split())
LEAVES = frozenset("p li h1 h2 h3 td tr".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
OUTSIDE_ONLY = frozenset("header headers topbar".split())
CONTENT_SHARE, ROOT_SHARE, MARKED_WEIGHT, SMOOTH, REACH = 0.3, 0.6, 0.5, (0.25, 0.5, 0.25), 8
_END = {tag: re.compile(rf"</{tag}\b[^>]*+>", re.I) for tag in RAW}


def tokens(page: str) -> Iterator[tuple[int, int, bool, str, str]]:
    """(begin, end, closing, tag, attributes) of the mark-up of a page; the tag of comments and the like is empty.

    Elements whose content is no page text (RAW) are one token with their content.
    """
    at, last, broken = 0, page.rfind(">"), 0
    while (i := page.find("<", at)) >= 0:
        if page.startswith("<!--", i):
            end = page.find("-->", i + 4)
            at = end + 3 if end >= 0 else len(page)
            yield i, at, False, "", ""
            continue
        if i > last:
            return
        if page.startswith("<![CDATA[", i) and (end := page.find("]]>", i)) >= 0:
            at = end + 3
            yield i, at, False, "", ""
            continue
        head = NAME.match(page, i)
        if not head:
            if page[i + 1 : i + 2] in ("!", "?") or page[i + 1 : i + 2] == "/" and page[i + 2 : i + 3].isalpha():
                at = page.find(">", i) + 1
                yield i, at, False, "", ""
            else:
                at = i + 1
            continue
        found = TAG.match(page, i) if broken < MOST_BROKEN else None
        if found:
            at, attrs = found.end(), found[3]
        else:
            broken += 1
            at = page.find(">", i) + 1
            attrs = page[head.end() : at - 1]
        tag = head[2].lower()
        if tag in RAW and not head[1] and not attrs.endswith("/"):
            end = _END[tag].search(page, at)
            at = end.end() if end else len(page)
            yield i, at, False, "", ""
        else:
            yield i, at, bool(head[1]), tag, attrs


class _Element:
    __slots__ = ("tag", "parent", "off", "region", "mass", "path", "depth", "marked", "below", "chars")

    def __init__(self, tag: str, parent: "_Element | None", off: bool, region: bool, marked: bool = False):
        self.tag, self.parent, self.off, self.region, self.mass = tag, parent, off, region, 0.0
        self.marked, self.below, self.chars = marked, False, 0
        self.path, self.depth = (hash((parent.path, tag)), parent.depth + 1) if parent else (hash(tag), 0)


def _boilerplate(tag: str, attrs: str, in_region: bool) -> str:
    """`whole` if element, role or style mark boilerplate, `words` if only words of class or id do, else empty."""
    if tag in NEVER or (tag == "header" and not in_region):
        return "whole"
    if not attrs or attrs.isspace():
        return ""
    low, by_words = attrs.lower(), ""
    for name, *values in ATTR.findall(low):
        value = "".join(values)
        if name in ("class", "id") and tag not in NEVER_BY_WORDS:
            words = set(re.split(r"[^a-z0-9]+", value))
            if words & MARKS or (not in_region and words & OUTSIDE_ONLY):
                by_words = "words"
        elif name == "role" and value in ROLES or name == "aria-hidden" and value == "true":
            return "whole"
        elif name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
            return "whole"
    return "whole" if re.search(r"(?:^|\s)hidden(?:\s|=|/|$)", re.sub(r"\"[^\"]*\"|'[^']*'", "", low)) else by_words


def text_nodes(page: str) -> tuple[list[tuple[_Element, str, int]], list[_Element]]:
    """(element, raw text, block number) of each text node, in page order; and all elements, parents first."""
    root = _Element("#", None, False, False)
    stack, nodes, elements, block, at = [root], [], [root], 0, 0
    count = Counter()  # of the open elements' tags

    def add(raw: str) -> None:
        if raw and not stack[-1].off:
            nodes.append((stack[-1], raw, block))

    def push(e: _Element) -> None:
        stack.append(e)
        elements.append(e)
        count[e.tag] += 1

    def close(tag: str, but: frozenset | set, through: frozenset | None = None) -> None:
        """Close the innermost open `tag`, unless an element of `but` (or one not of `through`) is inside it."""
        if not count[tag]:
            return
        for k in range(len(stack) - 1, 0, -1):
            if stack[k].tag == tag:
                count.subtract(e.tag for e in stack[k:])
                del stack[k:]
                return
            if stack[k].tag in but or through is not None and stack[k].tag not in through:
                return

    for begin, end, closing, tag, attrs in tokens(page):
        add(page[at:begin])
        at = end
        if not tag:
            continue
        if tag in ("br", "wbr", "img"):
            if tag != "wbr":
                add(" ")
            continue
        if tag in INLINE:
            # An inline element matters only if it is boilerplate of its own.
            if not closing and (why := _boilerplate(tag, attrs, stack[-1].region)):
                push(_Element(tag, stack[-1], stack[-1].off or why == "whole", stack[-1].region, why == "words"))
            elif closing and stack[-1].tag == tag:
                count[tag] -= 1
                stack.pop()
            continue
        block += 1
        if closing:
            close(tag, frozenset())
            continue
        if tag in VOID or attrs.endswith("/") and tag not in CLOSES_P:
            continue
        if tag in CLOSES_P:
            close("p", frozenset(), INLINE)
        elif tag in ITEMS:
            close(tag, HOLDERS)
        top = stack[-1]
        why = _boilerplate(tag, attrs, top.region)
        push(_Element(tag, top, top.off or why == "whole", top.region or tag in REGION, why == "words"))
    add(page[at:])
    return nodes, elements


def _weigh_marks(nodes: list[tuple[_Element, str, int]], elements: list[_Element]) -> None:
    """Sets which elements are below a marked one; marks do not count on one that holds most of the text."""
    for e, raw, _ in nodes:
        e.chars += len(raw) - sum(map(raw.count, " \n\t"))
    for e in reversed(elements):
        if e.parent:
            e.parent.chars += e.chars

    def spread(most: float) -> None:
        for e in elements:
            e.below = e.parent is not None and (e.parent.below or e.parent.marked and e.parent.chars <= most)

    spread(math.inf)
    # Where a region has text below no marked element, however large, nothing needs to be saved.
    if not any(e.region and raw.strip() and not e.below and not e.marked for e, raw, _ in nodes):
        most = elements[0].chars / 2
        spread(most)
        for e in elements:
            e.marked = e.marked and e.chars <= most


def main_text(page: str | None) -> str:
    if not page or page.isspace():
        return ""
    nodes, elements = text_nodes(page)
    _weigh_marks(nodes, elements)
    blocks: list[list] = []
    for e, raw, k in nodes:
        if blocks and blocks[-1][2] == k and blocks[-1][0] is e:
            blocks[-1][1].append(raw)
        else:
            blocks.append([e, [raw], k])
    rows = [(e, t) for e, parts, _ in blocks if (t := SPACES.sub(" ", html.unescape("".join(parts))).strip())]
    if not rows:
        return ""
    content = _content(rows)
    if not any(content):
        return ""
    inside, by_region = _content_root(rows, content, elements)
    near, last = [False] * len(rows), -REACH - 1
    for order in (range(len(rows)), range(len(rows) - 1, -1, -1)):
        last = None
        for i in order:
            last = i if content[i] else last
            near[i] = near[i] or last is not None and abs(i - last) <= REACH
    out, kept = [], False
    for i in range(len(rows) - 1, -1, -1):
        e, t = rows[i]
        plain = not e.below and not e.marked
        kept = content[i] and (inside[i] or not by_region or e.region) or plain and (inside[i] and (by_region or near[i]) or kept and e.tag in HEADINGS)
        if kept:
            out.append(t)
    return "\n".join(reversed(out))


def _content(rows: list[tuple[_Element, str]]) -> list[float]:
    """The fused value of each row that is content, and 0 of the others."""
    own = [(len(t), len(PUNCTUATION.findall(t))) for _, t in rows]
    length, marks, count = Counter(), Counter(), Counter()
    for (e, _), (n, m) in zip(rows, own):
        length[e.path] += n
        marks[e.path] += m
        count[e.path] += 1
    worth = lambda n, m: n * math.log1p(1 + m)
    ratio = {p: worth(length[p] / count[p], marks[p] / count[p]) for p in length}
    value = [min(ratio[e.path], worth(n, m)) if e.marked else ratio[e.path] for (e, _), (n, m) in zip(rows, own)]
    smooth = [sum(w * value[min(max(i + d, 0), len(value) - 1)] for d, w in zip((-1, 0, 1), SMOOTH)) for i in range(len(value))]
    fused = [math.sqrt(v * s) for v, s in zip(value, smooth)]
    least = CONTENT_SHARE * sum(fused) / len(fused)
    plain = sorted((f, e.path) for (e, _), f in zip(rows, fused) if f >= least and not e.below and not e.marked)
    paths, middle = {p for _, p in plain}, plain[len(plain) // 2][0] if plain else least
    beside = any(e.region and not e.below and not e.marked for e, _ in rows)

    def enough(e: _Element, f: float) -> bool:
        if not (e.below or e.marked):
            return f >= least
        if beside and not e.region:
            return False
        # A marked block among blocks of its path that have no mark is one of them if it is as long as they are.
        return f >= least if not e.below and e.path in paths else MARKED_WEIGHT * f >= middle

    return [f if enough(e, f) else 0.0 for (e, _), f in zip(rows, fused)]


def _content_root(rows: list[tuple[_Element, str]], content: list[float], elements: list[_Element]) -> tuple[list[bool], bool]:
    """Which rows are below the region or element that holds the content; and whether that is a region."""
    total = 0.0
    for (e, t), f in zip(rows, content):
        total += f * len(t)
        e.mass += f * len(t)
    for e in reversed(elements):
        if e.parent:
            e.parent.mass += e.mass
    regions = [e for e in elements if e.tag in REGION]
    top = max(regions, key=lambda e: (e.mass, e.depth), default=None)
    by_region = top is not None and top.mass >= 0.3 * total
    if not by_region:
        top = max((e for e in elements if e.mass >= ROOT_SHARE * total and e.tag not in LEAVES), key=lambda e: e.depth)
    inside = {id(top)}
    for e in elements:
        if e.parent and id(e.parent) in inside:
            inside.add(id(e))
    return [id(e) in inside for e, _ in rows], by_region


def _extract(batches):
    for batch in batches:
        found = [main_text(h) for h in batch.column("html").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(found, pa.string())], ["page_id", "url", "text"])


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row."""
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return p.mapInArrow(_extract, "page_id long, url string, text string").withColumn("n_chars", F.length("text").cast("long"))
