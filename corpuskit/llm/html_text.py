"""Main text of web pages by two passes of block rules (operator 9).

A page is read once, from left to right, as a row of tags and text. Elements that are never
article text by their kind (menus, footers, forms, scripts, ...) are left out with all they
hold; what remains is cut into blocks at block-level tags. Pass one judges each block by
itself from its length, the share of its characters inside links and the share of stop
words. The names that an author gave to the containers around it are one more sign: where
they all say comment, advert or the like the block is bad, where they hint at it only a
long block of running text passes, and where one of them says article they say nothing.
Pass two lets the short and doubtful blocks inherit the label of the nearest decided block
on each side. Inside an ``article`` or ``main`` element a doubtful block is taken as text
unless its decided neighbours are not; outside it needs text on both sides, a heading below
only.

Defined cases: a null or empty page has an empty text; pages may lack any closing tag or
quote; equal pages get equal texts; only the id, address and page columns are read; an
empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.common import small
from corpuskit.llm.quality import STOP_WORDS


@dataclass(frozen=True)
class BlockRules:
    long_words: int = 25
    short_words: int = 10
    max_links: float = 0.5
    stop_high: float = 0.20
    stop_low: float = 0.08


#: Elements whose content is no markup, and elements left out with what they hold.
RAW = {"script", "style", "noscript", "template", "svg", "iframe", "object", "select", "textarea", "button", "math", "canvas", "audio", "video", "title"}
LEFT_OUT = {"nav", "footer", "aside", "form", "menu", "dialog", "fieldset", "head"}
CONTAINERS = {
    "html", "body", "main", "article", "section", "div", "nav", "header", "footer", "aside", "form", "ul", "ol", "dl", "table",
    "figure", "details", "dialog", "menu", "fieldset", "blockquote", "head",
}
BLOCKS = CONTAINERS | {
    "p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "dt", "dd", "tr", "td", "th", "thead", "tbody", "tfoot", "caption", "pre", "hr",
    "figcaption", "address", "summary", "legend", "option", "center", "hgroup", "search",
}
#: Roles that are left out, and parts of names that speak against article text, for it, or for neither.
ROLES = {"navigation", "banner", "complementary", "contentinfo", "search", "form", "menu", "menubar", "dialog", "alert", "toolbar"}
AGAINST = set(
    "nav navbar navigation menu sidebar footer masthead ad ads advert adverts advertisement adsense sponsor sponsored promo promos promotion cookie cookies consent gdpr "
    "notice notices alert alerts popup modal overlay newsletter subscribe subscription signup comment comments commentlist disqus respond reply replies related "
    "recommended breadcrumb breadcrumbs pagination pager teaser teasers trending paywall".split()
)
DOUBTFUL = set("share sharing social login search legal copyright disclaimer widget widgets toolbar skip banner header".split())
IN_FAVOUR = set("article post story entry content main body text page prose".split())
NEUTRAL = set("site top bottom left right side box block section wrapper wrap container area slot unit bar list items item links link buttons button inner outer row col column form thread posts articles stories id".split())
_NEGATED = {"has", "with", "without", "no", "is", "not"}
_OPEN = re.compile(r"<(?:(!--)|([!?])|(/?)([a-zA-Z][a-zA-Z0-9:-]*))")
_ATTRIBUTES = re.compile(r"""(?:[^>"'=]+|=\s*(?:"[^"]*"|'[^']*')?|["'])*""")
_NAMED = re.compile(r"""(?:^|\s)(class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|/|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none|visibility\s*:\s*hidden""", re.I)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|[0-9]+")
_STOPS = frozenset(STOP_WORDS)


@dataclass
class Block:
    inside: bool
    heading: bool
    text: str = ""
    links: float = 0.0
    hint: int = 0  # what the names around it say: 0 nothing, 1 doubtful, 2 against
    label: str = ""
    parts: list[str] = field(default_factory=list)


def _hint(names: list[str]) -> int:
    """What the names of one container say; one that speaks for the article outweighs the others."""
    worst = 0
    for name in names:
        parts = [x.lower() for x in _PARTS.findall(name)]
        if not parts or parts[0] in _NEGATED:
            continue
        against = [x for x in parts if x in AGAINST]
        if len(parts) == 1 and parts[0] in IN_FAVOUR:
            return 0
        known = all(x in AGAINST or x in DOUBTFUL or x in NEUTRAL or x in IN_FAVOUR or x.isdigit() for x in parts)
        if against and known:
            worst = 2
        elif known and any(x in DOUBTFUL for x in parts):
            worst = max(worst, 1)
    return worst


def _judged_element(tag: str, attributes: str, in_article: bool) -> tuple[bool, int]:
    """Whether the element is left out, and the hint of its names."""
    if tag in LEFT_OUT or (tag == "header" and not in_article):
        return True, 0
    if tag in ("html", "body", "main") or not attributes:
        return False, 0
    if _HIDDEN.search(attributes):
        return True, 0
    names: list[str] = []
    for m in _NAMED.finditer(attributes):
        value = m[2].strip("\"'")
        if m[1].lower() == "role" and value.strip().lower() in ROLES:
            return True, 0
        names += value.split()
    return False, _hint(names)


def tags(html: str) -> Iterator[tuple[int, int, str, bool, str]]:
    """``start, end, tag, closing, attributes`` of each tag; comments and raw elements come whole, with an empty tag.

    Every character is looked at a bounded number of times: a quote that never closes is
    an ordinary character, and after the first tag that its quotes carry to the end of the
    page a tag ends at the next bracket.
    """
    at, quoted, last = 0, True, html.rfind(">")
    while (m := _OPEN.search(html, at)) is not None:
        start = m.start()
        if m[1]:
            end = html.find("-->", m.end())
            at = len(html) if end < 0 else end + 3
            yield start, at, "", False, ""
            continue
        if start > last:
            return  # no tag ends any more
        if m[2]:
            at = html.find(">", m.end()) + 1
            yield start, at, "", False, ""
            continue
        tag, closing = m[4].lower(), bool(m[3])
        end = _ATTRIBUTES.match(html, m.end()).end() if quoted else html.find(">", m.end())
        if end >= len(html):
            quoted, end = False, html.find(">", m.end())
        attributes, at = html[m.end() : end], end + 1
        if tag in RAW and not closing:
            shut = re.compile(rf"</{tag}\s*>", re.I).search(html, at)
            at = shut.end() if shut else len(html)
            yield start, at, "", False, ""
            continue
        yield start, at, tag, closing, attributes


def blocks_of(html: str) -> list[Block]:
    """Blocks with text outside the elements that are left out, in page order."""
    out: list[Block] = []
    open_: list[tuple[str, bool, bool, int]] = []  # container, left out, inside article or main, hint
    none = ("", False, False, 0)
    count: Counter = Counter()  # how many of each container are open
    parts: list[str] = []
    links = hint = 0
    heading = skipped = linked = False

    def end_block() -> None:
        nonlocal parts, links
        if parts:
            text = " ".join(unescape("".join(parts)).split())
            if text:
                out.append(Block(bool(open_) and open_[-1][2], heading, text, min(1.0, links / len(text)), max(hint, open_[-1][3] if open_ else 0)))
        parts, links = [], 0

    def shut() -> None:
        count[open_.pop()[0]] -= 1

    at = 0
    for start, end, tag, closing, attributes in tags(html):
        if not skipped and start > at:
            piece = html[at:start]
            parts.append(piece)
            if linked:
                links += len(unescape(piece).strip())
        at = end
        if tag == "a":
            linked = not closing
        elif tag == "br":
            if not skipped:
                parts.append(" ")
        elif tag in BLOCKS:
            end_block()
            linked = False
            heading = not closing and len(tag) == 2 and tag[0] == "h" and tag[1].isdigit()
            if open_ and open_[-1][0] not in CONTAINERS:
                shut()  # a single block that was left out ends where the next one begins
            _, bad, within, above = open_[-1] if open_ else none
            hint = 0
            if tag in CONTAINERS:
                if not closing:
                    if tag == "body" and count["head"]:  # also ends an unclosed head
                        open_ = [x for x in open_ if x[0] != "head"]
                        count["head"] = 0
                        _, bad, within, above = open_[-1] if open_ else none
                    left_out, own = _judged_element(tag, attributes, within)
                    open_.append((tag, bad or left_out, within or tag in ("article", "main"), 0 if tag == "main" else max(above, own)))
                    count[tag] += 1
                elif count[tag]:
                    while open_[-1][0] != tag:
                        shut()
                    shut()
            elif not closing and attributes and not bad:
                left_out, hint = _judged_element(tag, attributes, within)
                if left_out:
                    open_.append((tag, True, within, above))
                    count[tag] += 1
            skipped = bool(open_) and open_[-1][1]
    if not skipped and at < len(html):
        parts.append(html[at:])
    end_block()
    return out


def _judge(block: Block, rules: BlockRules) -> str:
    """Pass one: good, bad, near (doubtful) or short."""
    if block.links > rules.max_links or block.hint == 2:
        return "bad"
    words = block.text.split()
    if len(words) < rules.short_words:
        return "bad" if block.links > 0.3 or block.hint else "short"
    share = sum(w.strip(".,;:!?\"'()*#%$&|").lower() in _STOPS for w in words) / len(words)
    if len(words) >= rules.long_words and (share >= rules.stop_low or block.inside):
        return "good"
    if block.hint:
        return "bad"
    if share >= rules.stop_high:
        return "good"
    if share >= rules.stop_low or block.inside:
        return "near"
    return "bad"


def classify(blocks: list[Block], rules: BlockRules) -> None:
    """Both passes; afterwards each label is good or bad."""
    first = [_judge(b, rules) for b in blocks]
    decided = {"good", "bad"}
    before, last = [], None
    for label in first:
        before.append(last)
        last = label if label in decided else last
    after, last = [], None
    for label in reversed(first):
        after.append(last)
        last = label if label in decided else last
    after.reverse()
    for b, label, left, right in zip(blocks, first, before, after, strict=True):
        if label in decided:
            b.label = label
        elif b.inside:
            b.label = "bad" if left == right == "bad" else "good"
        elif b.heading:
            b.label = "good" if right == "good" else "bad"
        elif label == "near":
            b.label = "good" if "good" in (left, right) else "bad"
        else:
            b.label = "good" if left == right == "good" else "bad"


def main_text(html: str | None, rules: BlockRules | None = None) -> str:
    if not html:
        return ""
    blocks = blocks_of(html)
    classify(blocks, rules or BlockRules())
    return "\n".join(b.text for b in blocks if b.label == "good")


def extract_pages(df: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", rules: BlockRules | None = None) -> DataFrame:
    """``page_id, url, text, n_chars`` for each row of ``df``."""
    rules = rules or BlockRules()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            texts = [main_text(h, rules) for h in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())],
                ["page_id", "url", "text", "n_chars"],
            )

    pages = df.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return pages.mapInArrow(run, "page_id long, url string, text string, n_chars long")
