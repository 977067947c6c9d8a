"""Main text of HTML pages by two passes over their blocks.

A tolerant tokeniser cuts a page into blocks at block-level tags and drops what the markup itself names as no text of the article (scripts, menus,
footers, forms, adverts, comments and the like). Pass one then judges every other block by its own text: mostly links is bad; enough common
words for its length is good; a block too short to tell, or of a middling share of common words, is ambiguous, as is a
heading. A block of hardly any common words is bad outside an article element and ambiguous within one, where lists, tables and code stand.
Pass two lets each ambiguous block inherit the label of its nearest decided neighbours in its section (an article element's
blocks, or those between two): the label both sides share, else that of the nearer one, a tie goes to the one before; a
heading follows the block after it. Where a section has no decided block, its ambiguous ones are good in an article element and bad elsewhere.

Null and empty pages give an empty text. Blocks keep page order, so repeated blocks stay; whole pages are read. Extra columns
are kept; a column named like the output column is replaced.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from privmatrix.llm import textscan

#: Common words of the languages at hand.
COMMON_WORDS = frozenset(
    "the of and to in is that it for was on are with as be at by this from or an have not you he she they we had his her but which "
    "der die das und ist nicht ein eine mit von zu den sich auf für als auch im dem es des aus bei nach wird sind oder wie "
    "el la de que y en un los se del las por con una para su al lo como más es son este esta pero "
    "le et les des du une est pour qui dans par plus pas sur au ce il elle ne se son avec ou".split()
)
#: Tag names.
RAW = frozenset("script style noscript template textarea iframe svg math object select canvas audio video head".split())
OUTSIDE = frozenset("nav footer aside form button fieldset dialog menu".split())
INSIDE = frozenset("article main".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img input ins kbd label mark q ruby rp rt s samp small span strike strong sub sup time tt u var wbr".split())
#: Parts of class names and ids that mark what is not main text.
OUTSIDE_NAMES = frozenset("ad ads advert adverts advertisement advertising banner sponsor sponsored promo promotion cookie cookies consent notice popup modal overlay sidebar menu nav navbar navigation breadcrumb breadcrumbs footer masthead comment comments reply replies respond disqus related share sharing social newsletter subscribe signup login search widget copyright pagination pager toolbar".split())

STOP_HIGH, STOP_LOW = 0.3, 0.15
SHORT, LONG = 70, 200
LINK_DENSITY = 0.5

_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*>|(</?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>"'<]++|"[^"<]*+"|'[^'<]*+')*+|[^>]*)>""", re.DOTALL)
_NAMES = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.IGNORECASE)
_SPACE = re.compile(r"\s+")

GOOD, BAD, OPEN = 1, 0, -1


class Block:
    __slots__ = ("heading", "inside", "link_chars", "outside", "parts", "text")

    def __init__(self, outside: bool, inside: bool, heading: bool):
        self.parts: list[str] = []
        self.link_chars, self.outside, self.inside, self.heading, self.text = 0, outside, inside, heading, ""


def blocks(html: str) -> list[Block]:
    """The page's non-empty blocks in order."""
    out: list[Block] = []
    stack: list[tuple[str, bool, bool]] = []  # tag, outside, inside: as they hold within it
    block, links, at, n = Block(False, False, False), 0, 0, len(html)

    def close(heading: bool = False) -> Block:
        nonlocal block
        if block.parts:
            block.text = _SPACE.sub(" ", "".join(block.parts)).strip()
            if block.text:
                out.append(block)
        _, outside, inside = stack[-1] if stack else ("", False, False)
        block = Block(outside, inside, heading)
        return block

    def put(text: str) -> None:
        if text:
            text = unescape(text)
            block.parts.append(text)
            if links:
                block.link_chars += len(_SPACE.sub(" ", text).strip())

    while at < n:
        m = _TOKEN.search(html, at)
        if not m:
            put(html[at:])
            break
        put(html[at : m.start()])
        at = m.end()
        if not m[2]:
            continue
        tag, ends = m[2].lower(), m[1] == "</"
        if tag in RAW and not ends:
            if not m[3].endswith("/"):
                stop = re.compile(rf"</{tag}\b[^>]*>|<body\b" if tag == "head" else rf"</{tag}\b[^>]*>", re.IGNORECASE).search(html, at)
                at = n if not stop else stop.start() if stop[0][1] != "/" else stop.end()
            continue
        if tag == "a":
            links = 0 if ends else 1
        if tag == "br" or tag == "hr":
            block.parts.append(" ")
        if tag in INLINE:
            continue
        if ends:
            if any(x[0] == tag for x in stack):
                while stack.pop()[0] != tag:
                    pass
            close()
        else:
            if tag not in VOID and not m[3].endswith("/"):
                _, outside, inside = stack[-1] if stack else ("", False, False)
                names = {w for x in _NAMES.findall(m[3]) for w in re.split(r"[^a-z]+", "".join(x).lower())} if m[3] else set()
                if tag in INSIDE or (not inside and names & {"main", "article"} and tag not in ("html", "body")):
                    inside = True
                elif tag not in ("html", "body") and (tag in OUTSIDE or (tag == "header" and not inside) or names & OUTSIDE_NAMES):
                    outside = True
                if tag in ("p", "li", "td", "th", "tr", "dt", "dd", "option") and stack and stack[-1][0] == tag:
                    stack.pop()
                stack.append((tag, outside, inside))
            links = 0
            close(len(tag) == 2 and tag[0] == "h" and tag[1].isdigit())
    close()
    return out


def common_share(text: str) -> float:
    """Share of a text's words that are common ones."""
    words = text.lower().split()
    return sum(w.strip(".,;:!?()\"'") in COMMON_WORDS for w in words) / len(words)


def judged(b: Block) -> tuple[int, str]:
    """(GOOD, BAD or OPEN, the rule that says so) of a block by itself."""
    n = len(b.text)
    if b.outside:
        return BAD, "named"
    if b.link_chars / n > LINK_DENSITY:
        return (OPEN if b.inside else BAD), "links"
    if "©" in b.text and not b.inside:
        return BAD, "notice"
    if b.heading or n < SHORT:
        return OPEN, "short"
    common = common_share(b.text)
    if common >= STOP_HIGH or (common >= STOP_LOW and n >= LONG):
        return GOOD, "common words"
    if common >= STOP_LOW or b.inside:
        return OPEN, "few common words"
    return BAD, "no common words"


def first_pass(found: list[Block]) -> list[int]:
    """GOOD, BAD or OPEN for each block."""
    return [judged(b)[0] for b in found]


def second_pass(labels: list[int], found: list[Block]) -> list[int]:
    """OPEN labels replaced by those of the nearest decided blocks of the section; what the markup names as no text parts no section and decides nothing."""
    out, own = list(labels), [i for i, b in enumerate(found) if not b.outside]
    sections: list[list[int]] = []
    for i in own:
        if not sections or found[sections[-1][-1]].inside != found[i].inside:
            sections.append([])
        sections[-1].append(i)
    for section in sections:
        last = GOOD if found[section[0]].inside else BAD
        before: list[tuple[int, int] | None] = []
        after: list[tuple[int, int] | None] = []
        for run, order in ((before, section), (after, section[::-1])):
            seen = None
            for place, i in enumerate(order):
                if labels[i] != OPEN:
                    seen = place
                run.append(None if seen is None else (place - seen, labels[order[seen]]))
        for i, x, y in zip(section, before, after[::-1]):
            if labels[i] == OPEN:
                near = [z for z in ((y, x) if found[i].heading else (x, y)) if z]
                out[i] = last if not near else near[0][1] if found[i].heading else min(near, key=lambda z: z[0])[1]
    return out


def extract(html: str | None) -> str:
    """The main text: good blocks joined by empty lines."""
    if not html:
        return ""
    found = blocks(html)
    return "\n\n".join(b.text for b, label in zip(found, second_pass(first_pass(found), found)) if label == GOOD)


def main_text(df: DataFrame, html_col: str = "html", out: str = "text") -> DataFrame:
    """``df`` with ``out``: the main text of each page."""
    kept = [c for c in df.columns if c != out]
    schema = T.StructType([df.schema[c] for c in kept] + [T.StructField(out, T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, len(whole), 500):
                batch = whole.slice(a, 500)
                pages = batch.column(batch.schema.get_field_index(html_col))
                text = pa.array([extract(x.as_py()) for x in pages], pa.string())
                yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(c)) for c in kept] + [text], [*kept, out])

    return textscan.mapped(df, run, schema)
