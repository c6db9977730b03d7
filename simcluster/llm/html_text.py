"""Main text of web pages by two passes of block rules.

The page is cut into blocks at block-level tags. The first pass labels each block by itself: blocks inside
menus, headers, footers, sidebars, notices, adverts, forms and reader comments are out; elsewhere link
density, length and the density of stop words decide, or leave short and middling blocks open. The second
pass gives each open block the label of its nearest decided neighbours. An article or main element is one more
hint: it lifts the label of blocks inside by one step, from out to open and from open to in, and one neighbour that is in
is enough for an open block inside.

On a page none of whose long blocks holds stop words of the languages that the list covers, the language is taken as
unknown, and length and link density decide alone.

A narrow pass over pages; each page is handled in time linear in its length.

Defined cases: null or empty html gives empty text; unclosed or stray tags never fail; `br br` parts blocks,
a single `br` counts as white space; unclosed scripts, styles and comments reach to the end of the page.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Tag names by role.
BLOCK_TAGS = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW_TAGS = frozenset("script style noscript template iframe object svg math textarea title select button canvas audio video".split())
OUT_TAGS = frozenset("nav footer aside form menu dialog head fieldset".split())
CLOSED_BY_NEXT = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
# Words in class, id or role that mark parts that are no article text.
OUT_WORDS = frozenset("ad ads adbox adv advert advertisement adverts advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies discussion disqus footer gdpr header masthead menu menubar modal nav navbar navigation navigational newsletter notice notices overlay pager pagination popup promo promoted promotion replies reply respond sidebar sponsor sponsored subscribe subscription toolbar topbar widget contentinfo complementary alert".split())
# Frequent function words of English, French, German and Spanish.
STOP_WORDS = frozenset("the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which one you were all her she there would their we him been has when who will no more if out so said what up its about than into them can only other time new some could these two may then do le la les des de du un une et en est que qui dans pour pas sur au aux avec ce il elle par plus ne se son sont mais nous vous ou der die das und ist ein eine nicht von zu den mit im auf für sich dem des auch als an es er sie wir ich wird bei aus nach einen einer el los las y que del se por con para una su al lo como más pero sus ya este sí porque esta entre cuando muy sin sobre también me hasta hay donde".split())

_TAG = re.compile(r"<(?:(!--)|(/?)([a-zA-Z][^\s/>]*)|([!?]))")
_END_OR_VALUE = re.compile(r"[>=]")
_VALUE_END = re.compile(r"[\s>]")
_SPACES = re.compile(r"\s*")
_ATTR = re.compile(r"""(?:^|\s)(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_NOT_NAME = re.compile(r"[^a-z0-9]+")
_CAMEL = re.compile(r"([a-z])([A-Z])")
_WS = re.compile(r"\s+")


def _tag_end(page: str, at: int) -> int:
    """Index after the > that ends a tag; only quotes that open a value, and are closed inside the page, hide a >."""
    while m := _END_OR_VALUE.search(page, at):
        if m[0] == ">":
            return m.end()
        at = _SPACES.match(page, m.end()).end()
        if page[at : at + 1] in ('"', "'"):
            close = page.find(page[at], at + 1)
            if close < 0:
                end = page.find(">", at)
                return end + 1 if end >= 0 else len(page)
            at = close + 1
        elif end := _VALUE_END.search(page, at):
            at = end.start()
        else:
            break
    return len(page)


def _marked_out(tag: str, attrs: str, inside: bool) -> bool:
    if tag in OUT_TAGS or tag == "header" and not inside:
        return True
    if not attrs or tag in ("html", "body", "article", "main") and "omment" not in attrs:
        return False
    names = " ".join(x for m in _ATTR.finditer(attrs) for x in m.groups() if x)
    return any(x in OUT_WORDS for x in _NOT_NAME.split(_CAMEL.sub(r"\1 \2", names).lower()))


class _Block:
    __slots__ = ("text", "linked", "out", "inside", "heading")

    def __init__(self, text: str, linked: int, out: bool, inside: bool, heading: bool):
        self.text, self.linked, self.out, self.inside, self.heading = text, linked, out, inside, heading


def blocks_of(page: str) -> list[_Block]:
    found: list[_Block] = []
    parts: list[str] = []
    linked = 0
    stack: list[tuple[str, bool, bool]] = []  # tag, whether it marks its content out, whether it is an article
    opened: Counter = Counter()
    outs = insides = links = headings = 0
    at, n, breaks = 0, len(page), 0

    def flush() -> None:
        nonlocal linked
        text = _WS.sub(" ", entities.unescape("".join(parts))).strip()
        if text:
            found.append(_Block(text, linked, outs > 0, insides > 0, headings > 0))
        parts.clear()
        linked = 0

    def pop() -> str:
        nonlocal outs, insides, headings
        tag, out, inside = stack.pop()
        opened[tag] -= 1
        outs -= out
        insides -= inside
        headings -= tag in ("h1", "h2", "h3", "h4", "h5", "h6")
        return tag

    while at < n:
        m = _TAG.search(page, at)
        upto = m.start() if m else n
        if upto > at:
            piece = page[at:upto]
            parts.append(piece)
            if links:
                linked += len(piece)
            if not piece.isspace():
                breaks = 0
        if not m:
            break
        if m[1]:
            end = page.find("-->", m.end())
            at = n if end < 0 else end + 3
            continue
        if m[4]:
            end = page.find(">", m.end())
            at = n if end < 0 else end + 1
            continue
        tag, closing = m[3].lower(), bool(m[2])
        at = _tag_end(page, m.end())
        if tag == "br":
            parts.append(" ")
            breaks += 1
            if breaks == 2:
                flush()
            continue
        if tag in RAW_TAGS:
            if not closing and not page[m.end() : at].rstrip(">").endswith("/"):
                end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])", re.I).search(page, at)
                at = _tag_end(page, end.end()) if end else n
            parts.append(" ")
            continue
        if tag == "a":
            links = 0 if closing else 1
            continue
        if tag not in BLOCK_TAGS and (closing or tag in VOID_TAGS or not _ATTR.search(page[m.end() : at])):
            if closing and opened[tag]:
                while stack[-1][0] != tag and stack[-1][0] not in BLOCK_TAGS:
                    pop()
                if stack[-1][0] == tag:
                    if stack[-1][1]:
                        flush()
                    pop()
            elif tag == "body":
                flush()
            continue
        block = tag in BLOCK_TAGS
        if block:
            flush()
            breaks = 0
        if tag in VOID_TAGS:
            continue
        if closing:
            if opened[tag]:
                while pop() != tag:
                    pass
            continue
        if tag in ("body", "article", "main") and opened["head"]:
            while pop() != "head":
                pass
        if tag in CLOSED_BY_NEXT and stack and stack[-1][0] in CLOSED_BY_NEXT[tag]:
            pop()
        out = _marked_out(tag, page[m.end() : at - 1], insides > 0)
        if out and not block:
            flush()
        inside = tag in ("article", "main") and not out
        stack.append((tag, out, inside))
        opened[tag] += 1
        outs += out
        insides += inside
        headings += tag in ("h1", "h2", "h3", "h4", "h5", "h6")
    flush()
    return found


def _stop_density(text: str) -> float:
    words = text.lower().split()
    return sum(w.strip(".,;:!?\"'()%*#&$") in STOP_WORDS for w in words) / max(1, len(words))


def _by_rules(block: _Block, known: bool = True) -> bool | None:
    """In, out or open by link density, length and density of stop words; the latter counts in known languages only."""
    if block.out:
        return False
    density = block.linked / max(1, len(block.text))
    if density > 0.4:
        return False
    if len(block.text) < 70:
        return False if block.linked else None
    if not known:
        return True if len(block.text) > 140 or block.linked == 0 else None
    stops = _stop_density(block.text)
    if stops >= 0.25:
        return True if len(block.text) > 140 or block.linked == 0 else None
    return None if stops >= 0.12 else False


def _first_pass(block: _Block, ruled: bool | None) -> bool | None:
    """The rules' label, one step better inside an article or main element."""
    if block.out or not block.inside:
        return ruled
    return None if ruled is False else True


def main_text(page: str | None) -> str:
    if not page:
        return ""
    blocks = blocks_of(page)
    long = [b for b in blocks if not b.out and len(b.text) >= 70]
    known = not long or any(_stop_density(b.text) >= 0.12 for b in long)
    ruled = [_by_rules(b, known) for b in blocks]
    first = [_first_pass(b, x) for b, x in zip(blocks, ruled, strict=True)]
    before, last, dist = [], None, 0
    for x in first:  # (label, distance) of the decided block before each one
        dist += 1
        if x is not None:
            last, dist = x, 0
        before.append((last, dist))
    labels: list[bool] = [False] * len(first)
    last, dist = None, 0
    for i in range(len(first) - 1, -1, -1):
        dist += 1
        if first[i] is not None:
            last, dist = first[i], 0
            labels[i] = first[i]
            continue
        (left, near), (right, far) = before[i], (last, dist)
        if left is None and right is None:
            labels[i] = False
        elif left is None or right is None:
            labels[i] = bool(right if left is None else left)
        else:
            labels[i] = left if left == right else True if blocks[i].inside else (bool(right) if blocks[i].heading else left if near < far else right if far < near else True)
    if not any(labels):
        labels = [x is None for x in ruled]
    return "\n".join(b.text for b, keep in zip(blocks, labels, strict=True) if keep)


def extract_main_text(pages: DataFrame, html_col: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """The kept columns, text and n_chars (code points) of every page."""

    @F.pandas_udf("string")
    def extract(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for pages in batches:
            yield pd.Series([main_text(x if isinstance(x, str) else None) for x in pages], dtype="object")

    return pages.select(*keep, extract.asNondeterministic()(F.col(html_col)).alias("text")).withColumn("n_chars", F.length("text").cast("long"))
