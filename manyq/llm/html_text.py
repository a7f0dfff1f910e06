"""Main text of web pages by tag-path ratios.

A page is read into text nodes, each with its root-to-leaf tag path. For every path the length and the punctuation of
its text are summed and set against its number of nodes; the ratios are fused with the share of text outside links,
smoothed over the nodes with text in page order, and held against half of the mean of their logarithms over the page,
which one long paragraph moves little. Headings, list items and, in a marked article, paragraphs may be short: they also
stay between or beside selected blocks of their container. Two things known of HTML weigh in: paths through elements
that seldom hold the article (menus, headers, footers, side bars, notices, adverts, forms, reader comments; by element,
role, class or id) have a hundredth of their ratio, hidden ones none, and where a page marks its article, only paths
through it are scored.

Defined cases: null or empty html gives an empty text; pages cut off anywhere are read to their end; nested and unclosed
elements follow HTML's implied ends; a quote that is never closed ends with its tag. Time and memory grow with a page's
length, however deep it nests. Rows that repeat come back once each. Extra columns are not read.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from manyq.llm.common import lean_batches, table

# HTML's element kinds.
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
SHORT = HEADINGS | frozenset("li dt dd td th caption figcaption".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe object svg math head title textarea select canvas audio video noembed noframes xmp".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split()
)
BOILER = frozenset("nav footer aside form button label input select option dialog menu search fieldset legend".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
#: Words of class and id values.
MARKS = frozenset(
    "ad ads adv advert advertisement adsense sponsor sponsored sponsors promo promotion nav navbar navigation menu breadcrumb breadcrumbs sidebar aside "
    "rail widget footer foot masthead topbar header cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription "
    "signup login share sharing social related recommended recommendations comment comments disqus reply replies respond banner pagination pager "
    "toolbar skip hidden paywall alert".split()
)
CLOSES_P = BLOCK - frozenset("body html caption dd dt legend li optgroup option summary tbody td tfoot th thead tr".split()) | {"p"}
SIBLINGS = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "option": ("select",), "tr": ("table",), "td": ("tr",), "th": ("tr",)}
#: The weight of doubtful elements, and the share of the page's mean log ratio that blocks must reach.
DOUBT, SHARE = 0.01, 0.5
LISTS = frozenset("ul ol dl menu table tbody thead tfoot tr figure".split())

#: What opens markup, and what may end a tag or hide its end.
START = re.compile(r"<!--|<[!?]|<(/?)([a-zA-Z][^\s/>]*)")
INSIDE = re.compile(r"[>\"']")
ATTRIBUTE = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?(?=\s|/|$)""", re.I | re.S)
WORDS = re.compile(r"[A-Za-z]+")
PUNCTUATION = re.compile(r"[.,;:!?…。，、！？]")


class Paths:
    """Tag paths as numbers, 0 for the root: each is its parent's path and a tag. What blocks ask of a path is known when it is made, so depth costs nothing later."""

    def __init__(self):
        self.number: dict[tuple[int, str], int] = {}
        self.parent, self.tag, self.depth = [0], [""], [0]
        self.above_lists = [0]  # the nearest path, itself or above, that is no list or table
        self.short: list[tuple[str, int] | None] = [None]  # the innermost heading or list item: its tag, and what holds it or its whole list
        self.home = [0]  # what holds the innermost block element
        self.enter: list[int] = []
        self.leave: list[int] = []

    def child(self, parent: int, tag: str) -> int:
        key = (parent, tag)
        n = self.number.get(key)
        if n is None:
            n = self.number[key] = len(self.tag)
            self.parent.append(parent)
            self.tag.append(tag)
            self.depth.append(self.depth[parent] + 1)
            self.above_lists.append(self.above_lists[parent] if tag in LISTS else n)
            self.short.append((tag, self.above_lists[parent]) if tag in SHORT else self.short[parent])
            self.home.append((parent if tag in ("p", "pre", "blockquote") else n) if tag in BLOCK else self.home[parent])
        return n

    def finish(self) -> None:
        """Number the paths so that one lies below another where its number lies in the other's range."""
        size = [1] * len(self.tag)
        for n in range(len(self.tag) - 1, 0, -1):
            size[self.parent[n]] += size[n]
        self.enter, used = [0] * len(self.tag), [1] * len(self.tag)
        for n in range(1, len(self.tag)):  # a parent has a smaller number
            up = self.parent[n]
            self.enter[n] = self.enter[up] + used[up]
            used[up] += size[n]
        self.leave = [e + k for e, k in zip(self.enter, size, strict=True)]

    def below(self, a: int, b: int) -> bool:
        """Whether a is b or lies below it."""
        return self.enter[b] <= self.enter[a] < self.leave[b]


@dataclass(slots=True)
class Node:
    path: int
    block: int
    text: str
    weight: float
    linked: bool
    article: bool
    score: float = 0.0


@dataclass(slots=True)
class Open:
    tag: str
    path: int
    weight: float
    linked: bool
    article: bool
    p: int  # the place of the open paragraph that a new block ends, or -1


def _weight(tag: str, attributes: str, inside_article: bool) -> float:
    """What an element's ratio is multiplied by."""
    weight = DOUBT if tag in BOILER or tag == "header" and not inside_article else 1.0
    for m in ATTRIBUTE.finditer(attributes) if attributes else ():
        name, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if name == "hidden" or name == "aria-hidden" and value.lower() == "true":
            return 0.0
        if name == "role" and value.lower() in ROLES:
            weight = DOUBT
        if name in ("class", "id") and tag not in ("html", "body", "main", "article") and not MARKS.isdisjoint(w.lower() for w in WORDS.findall(value)):
            weight = DOUBT
    return weight


def _tag_end(page: str, at: int) -> int:
    """Where a tag ends whose name ends at `at`: past the first > outside quotes; with a quote that is never closed, past the next >; else the page's end."""
    m = INSIDE.search(page, at)
    while m and m[0] != ">":
        closing = page.find(m[0], m.end())
        if closing < 0:
            end = page.find(">", m.end())
            return end + 1 if end >= 0 else len(page)
        m = INSIDE.search(page, closing + 1)
    return m.end() if m else len(page)


def nodes_of(page: str) -> tuple[list[Node], Paths]:
    """The text nodes of a page in order, without those in raw elements (scripts, styles, the head), and their paths.

    Each character is looked at a bounded number of times, whatever is left open or unclosed.
    """
    nodes: list[Node] = []
    paths = Paths()
    stack = [Open("", 0, 1.0, False, False, -1)]
    opened: dict[str, int] = {}
    endless: set[str] = set()  # raw elements that nothing ends from here on
    block, at, n = 0, 0, len(page)

    def add(raw: str) -> None:
        if raw and not raw.isspace() or nodes and raw:
            top = stack[-1]
            nodes.append(Node(top.path, block, html.unescape(raw), top.weight, top.linked, top.article))

    def close(until: int) -> None:
        for x in stack[until:]:
            opened[x.tag] -= 1
        del stack[until:]

    while at < n:
        m = START.search(page, at)
        if not m:
            add(page[at:])
            break
        add(page[at : m.start()])
        if not m[2]:
            mark = "-->" if m[0] == "<!--" else ">"
            end = page.find(mark, m.end())
            at = end + len(mark) if end >= 0 else n
            continue
        tag = m[2].lower()
        at = _tag_end(page, m.end())
        inside = page[m.end() : at - 1 if page[at - 1] == ">" else at]
        if m[1]:
            block += tag in BLOCK
            if opened.get(tag):
                i = len(stack) - 1
                while stack[i].tag != tag:
                    i -= 1
                close(i)
            continue
        if tag in RAW:
            end = None if tag in endless else re.compile(rf"</{re.escape(tag)}(?=[\s/>]|\Z)[^>]*(?:>|\Z)", re.I).search(page, at)
            if end is None:
                endless.add(tag)
            if tag != "head" or end:
                at = end.end() if end else n
            block += tag in ("head", "title")
            continue
        if tag == "br":
            add(" ")
            continue
        block += tag in BLOCK
        if tag in VOID or inside.endswith("/") and tag not in BLOCK:
            continue
        if tag in CLOSES_P:
            if stack[-1].p >= 0:
                close(stack[-1].p)
        elif tag in SIBLINGS:
            same = ("td", "th") if tag in ("td", "th") else ("dt", "dd") if tag in ("dt", "dd") else (tag,)
            for i in range(len(stack) - 1, 0, -1) if any(opened.get(t) for t in same) else ():
                if stack[i].tag in SIBLINGS[tag]:
                    break
                if stack[i].tag in same:
                    close(i)
                    break
        top = stack[-1]
        article = top.article or tag in ("article", "main") or bool(inside) and "main" in inside and re.search(r"role\s*=\s*[\"']?main\b", inside) is not None
        weight = min(top.weight, _weight(tag, inside, article and (top.article or tag not in ("article", "main"))))
        p = len(stack) if tag == "p" else -1 if tag in BLOCK else top.p
        opened[tag] = opened.get(tag, 0) + 1
        stack.append(Open(tag, paths.child(top.path, tag), weight, top.linked or tag == "a", article, p))
    paths.finish()
    return nodes, paths


def score(nodes: list[Node]) -> float:
    """Give every node the smoothed and fused ratio of its path; return the page's threshold."""
    sums: dict[tuple[int, float], list[float]] = {}  # doubtful nodes apart, lest they have the article's ratio
    for x in nodes:
        own = sums.setdefault((x.path, x.weight), [0, 0, 0, 0])
        size = len(x.text.strip())
        own[0] += size
        own[1] += len(PUNCTUATION.findall(x.text))
        own[2] += size > 0
        own[3] += size if x.linked else 0
    ratio = {p: (1 - link / max(1, size)) * (size / max(1, n)) * (1 + punct / max(1, n)) for p, (size, punct, n, link) in sums.items()}
    # White space between elements has no ratio of its own and would only halve its neighbours'.
    live = [x for x in nodes if x.text.strip()]
    plain = [x.weight * ratio[x.path, x.weight] for x in live]
    for i, x in enumerate(live):
        near = [(0.5, plain[i])] + [(0.25, plain[j]) for j in (i - 1, i + 1) if 0 <= j < len(live)]
        x.score = sum(w * v for w, v in near) / sum(w for w, _ in near) if x.weight == 1 else plain[i]  # no lift for doubtful ones
    logs = [math.log1p(x.score) for x in live if not x.linked and x.weight]
    return math.expm1(SHARE * sum(logs) / len(logs)) if logs else 0.0


def main_text(page: str | None) -> str:
    """The article: its blocks in page order, white space inside a block as one blank, joined by newlines."""
    nodes, paths = nodes_of(page or "")
    if any(x.article and x.weight == 1 and x.text.strip() for x in nodes):
        nodes = [x for x in nodes if x.article]
    least = max(score(nodes), 1e-9)
    groups: dict[int, list[Node]] = {}
    for x in nodes:
        groups.setdefault(x.block, []).append(x)
    blocks = [own for _, own in sorted(groups.items()) if any(x.text.strip() for x in own)]
    chosen = [max(x.score for x in own) >= least for own in blocks]
    # Of every block, the paths that hold the nearest selected ones before and after it.
    before, after = [None] * len(blocks), [None] * len(blocks)
    for order, near in ((range(len(blocks)), before), (range(len(blocks) - 1, -1, -1), after)):
        last = None
        for i in order:
            near[i] = last
            if chosen[i]:
                best = max(blocks[i], key=lambda x: x.score)
                kind = paths.short[best.path]
                last = kind[1] if kind else paths.home[best.path]
    out = []
    for i, own in enumerate(blocks):
        if not chosen[i] and not _kept_short(own, paths, before[i], after[i]):
            continue
        if text := " ".join("".join(x.text for x in own if x.score >= least or x.weight == 1).split()):
            out.append(text)
    return "\n".join(out)


def _kept_short(own: list[Node], paths: Paths, before: int | None, after: int | None) -> bool:
    """Whether an unselected block is a heading, list item or paragraph that belongs to selected blocks."""
    first = next(x for x in own if x.text.strip())
    if first.article and first.weight == 1 and not first.linked and paths.tag[first.path] == "p":
        # A paragraph beside selected blocks, in the same element of a marked article.
        return paths.parent[first.path] in (before, after)
    kind = paths.short[first.path]
    if not kind or min(x.weight for x in own) < 1 or all(x.linked for x in own if x.text.strip()):
        return False
    tag, home = kind
    inside = [near is not None and (paths.below(home, near) or paths.below(near, home)) for near in (before, after)]
    if all(inside) or tag in HEADINGS and inside[1]:
        return True
    # At an end of the selected blocks: only where their container is no more than the article.
    return any(inside) and (first.article or paths.depth[home] > 2)


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) for every page."""
    lean_batches(pages.sparkSession)
    kind = pages.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(h) for h in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, f"page_id {kind}, url string, text string, n_chars long")


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
