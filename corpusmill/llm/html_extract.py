"""Main text of web pages by two-pass block rules.

A tag scanner cuts a page into blocks and notes for each its words, link characters and place: whether it lies in an article region, and how
its classes, ids or roles mark it. Elements that never hold main text (navigation, footers, forms, scripts and so on) leave with the scanner. The first pass
decides blocks by link density, length and stop-word density, with lower bars in an article region and higher ones under a mark; the second gives the blocks
that it left open the label of their nearest decided neighbours in the same region. Region and marks are evidence, not verdicts: a region without any
decided block keeps its open ones, a paragraph of prose in an article stays under a word like "related" or "notice", and on pages without a region the
bars alone decide.
Defined results: null or empty html gives an empty text; a quote that never closes ends its tag at the next ">"; rows are handled one by one (repeated
ids repeat); extra columns are ignored. Scanning takes time in proportion to the page, however malformed it is.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Stop words of the four languages of the tables.
STOP_WORDS = frozenset(
    "the of and to a in is it that was for on are as with by be this at from or an not but which have has had they you we he she "
    "der die das und ist ein eine von zu den dem mit auf für im nicht als auch es an werden aus er sie nach bei einer um am sind "
    "le la les de des et un une en que qui dans du est pour par sur au avec ne se pas plus ce il elle sont "
    "el los las y del se con por una su para lo al como más o pero sus este ya entre cuando muy sin".split()
)
#: Elements by what they do.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noscript iframe noembed noframes template".split())
SKIP = frozenset("nav footer aside form button select option dialog menu svg math canvas audio video object figure-nav fieldset label input head".split()) | RAW
BLOCK = frozenset("address article blockquote body caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
REGION = frozenset(("article", "main"))
CLOSES_P = BLOCK - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption"}
#: Words in class, id or role that name other content outright, and those that a part of an article may carry too.
STRONG = frozenset(
    "ad ads advert adverts advertisement advertisements advertising sponsor sponsored nav navbar navigation menubar breadcrumb breadcrumbs sidebar comment comments commentlist "
    "disqus cookie cookies consent gdpr newsletter subscribe subscription pagination pager complementary contentinfo".split()
)
WEAK = frozenset("banner promo menu side footer foot header masthead topbar discussion replies reply respond notice notices notification signup login popup modal overlay share sharing social related recommended recommendations widget toolbar skip search".split())

_ATTR = re.compile(r"""\b(class|id|role|hidden|aria-hidden|style)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I)
_NAME = re.compile(r"(/?)([A-Za-z][A-Za-z0-9:-]*)")
_STOP = re.compile(r"[\"'>]")
_WORD = re.compile(r"\w+")


@dataclass
class Block:
    text: str
    linked: int
    inside: bool
    heading: bool
    item: bool
    mark: int
    label: str = field(default="")


@dataclass
class Open:
    """An open element; mark is 2 under a word that names other content, 1 under one that may, 0 else."""

    name: str
    skipped: bool
    inside: bool
    mark: int


def _mark(name: str, attributes: str, inside: bool) -> int:
    """3 if an element never holds main text, else how it is marked."""
    if name in SKIP or name == "header" and not inside:
        return 3
    if "=" not in attributes and "hidden" not in attributes or name in ("body", "html", "main", "article"):
        return 0
    mark = 0
    for key, value in _ATTR.findall(attributes):
        key, value = key.lower(), value.strip("\"'").lower()
        if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none", value):
            return 3
        if key in ("class", "id", "role"):
            words = set(re.split(r"[^a-z]+", value))
            mark = max(mark, 2 if words & STRONG else 1 if words & WEAK else 0)
    return mark


def tags_of(page: str):
    """(start, end, name, attributes, closing) of each tag; comments and declarations have no name."""
    at, end = page.find("<"), len(page)
    last = {q: page.rfind(q) for q in "\"'>"}
    while 0 <= at:
        if page.startswith("<!--", at):
            shut = page.find("-->", at + 4)
            yield at, (to := shut + 3 if shut >= 0 else end), "", "", False
        elif page.startswith("<![CDATA[", at):
            yield at, (to := at + 9), "", "", False
        elif page[at + 1 : at + 2] in ("!", "?"):
            shut = page.find(">", at)
            yield at, (to := shut + 1 if shut >= 0 else end), "", "", False
        elif m := _NAME.match(page, at + 1):
            to = m.end()
            while to <= last[">"] and (stop := _STOP.search(page, to)):
                to = stop.end()
                if stop[0] == ">":
                    break
                if to > last[stop[0]]:  # it never closes: the tag ends at the next ">"
                    to = page.find(">", m.end()) + 1
                    break
                to = page.find(stop[0], to) + 1
            if to > m.end() and page[to - 1] == ">":
                yield at, to, m[2].lower(), page[m.end() : to - 1], bool(m[1])
            elif (shut := page.find(">", m.end()) if m.end() <= last[">"] else -1) >= 0:
                yield at, (to := shut + 1), m[2].lower(), page[m.end() : shut], bool(m[1])
            else:
                return  # no ">" is left, so there is no further tag
        else:
            to = at + 1
        at = page.find("<", to)


def blocks_of(page: str) -> list[Block]:
    out: list[Block] = []
    stack: list[Open] = []
    count: Counter[str] = Counter()
    paragraphs: list[int] = []  # where p elements lie in the stack, and other block elements
    others: list[int] = []
    parts: list[str] = []
    linked = links = 0
    heading = item = started = False
    mark = 0

    def close(inside: bool) -> None:
        nonlocal linked, mark, started
        text = " ".join("".join(parts).split())
        parts.clear()
        if text:
            out.append(Block(text, min(linked, len(text)), inside, heading, item, mark))
        linked, mark, started = 0, 0, False

    def cut(depth: int) -> None:
        nonlocal links
        for gone in stack[depth:]:
            count[gone.name] -= 1
            links -= gone.name == "a" and not gone.skipped
        del stack[depth:]
        for places in (paragraphs, others):
            while places and places[-1] >= depth:
                places.pop()

    at, raw = 0, -1
    for start, to, name, attributes, closing in (*tags_of(page), (len(page), len(page), "", "", False)):
        if start < raw:  # inside a script or another element of raw text
            at = max(at, min(to, raw))
            continue
        skipped, inside = (stack[-1].skipped, stack[-1].inside) if stack else (False, False)
        if not skipped and (text := page[max(at, raw) : start]):
            text = entities.unescape(text)
            if not started and text.strip():
                started, mark = True, stack[-1].mark if stack else 0
            parts.append(text)
            linked += len(text.strip()) * bool(links)
        at = to
        if not name:
            continue
        if closing:
            if name == "p" and not count["p"]:
                close(inside)
            if count[name]:
                depth = len(stack) - 1
                while stack[depth].name != name:
                    depth -= 1
                for gone in reversed(stack[depth:]):
                    if gone.name in BLOCK and not gone.skipped:
                        close(gone.inside)
                cut(depth)
            continue
        if name in ("br", "wbr"):
            parts.append(" " if name == "br" and not skipped else "")
            continue
        if name in BLOCK and not skipped:
            close(inside)
        if name in CLOSES_P and not skipped and paragraphs and (not others or others[-1] < paragraphs[-1]):
            cut(paragraphs[-1])
        if name == "li" and stack and stack[-1].name == "li":
            cut(len(stack) - 1)
        if name in VOID or attributes.endswith("/") and name not in BLOCK and name not in RAW:
            continue
        own = _mark(name, attributes, inside)
        if name in RAW:
            shut = re.compile(rf"</{name}\b[^>]*>", re.I).search(page, to)
            raw = at = shut.end() if shut else len(page)
            continue
        above = stack[-1].mark if stack else 0
        stack.append(Open(name, skipped or own == 3, inside or name in REGION, max(above, own if own < 3 else 0)))
        count[name] += 1
        if name in BLOCK:
            (paragraphs if name == "p" else others).append(len(stack) - 1)
        if not stack[-1].skipped:
            heading, item = name in ("h1", "h2", "h3", "h4", "h5", "h6") or name not in BLOCK and heading, name in ("li", "dd", "dt") or name not in BLOCK and item
            links += name == "a"
    close(stack[-1].inside if stack else False)
    return out


#: What a block's first label can be.
GOOD, BAD, NEAR, SHORT = "good", "bad", "near", "short"


def first_label(b: Block, short: int, long: int, low: float, high: float, most_links: float) -> str:
    """Decided by link density, length and stop-word density, or left to the neighbours: near for running text, short for the rest."""
    words = [w.lower() for w in _WORD.findall(b.text)]
    density = sum(w in STOP_WORDS for w in words) / len(words) if words else 0.0
    links = b.linked / len(b.text)
    if b.mark == 2 or links > (0.9 if b.inside else most_links) and (b.item or not b.inside):
        return BAD
    if b.mark == 1 and not (b.inside and links <= most_links and len(b.text) >= short and density >= low / 2):
        return BAD
    if len(b.text) < short or links > most_links:
        return BAD if b.linked and not b.inside else SHORT
    if density >= (low / 2 if b.inside else high) or b.inside and len(b.text) >= long:
        return GOOD
    if density >= low or len(b.text) >= long:
        return GOOD if density >= low and len(b.text) >= long else NEAR
    return SHORT if b.heading else NEAR


def classify(blocks: list[Block], short: int = 70, long: int = 200, low: float = 0.30, high: float = 0.32, most_links: float = 0.4) -> list[str]:
    """Two passes; labels become good or bad. Returns the labels of the first pass."""
    region = any(b.inside for b in blocks)
    for b in blocks:
        b.label = first_label(b, short, long, low, high, most_links)
        if region and not b.inside and b.label != GOOD:
            b.label = BAD  # beside an article only whole prose has a claim
    firsts = [b.label for b in blocks]
    before: list[str] = []
    seen = {True: "", False: ""}
    for b in blocks:
        before.append(seen[b.inside])
        seen[b.inside] = b.label if b.label in (GOOD, BAD) else seen[b.inside]
    seen = {True: "", False: ""}
    for b, first, left in zip(reversed(blocks), reversed(firsts), reversed(before)):
        right = seen[b.inside]
        if first == NEAR or first == SHORT and b.inside:
            b.label = GOOD if GOOD in (left, right) or b.inside and not (left or right) or b.inside and b.mark == 0 and b.linked == 0 else BAD
        elif first == SHORT:
            b.label = GOOD if right == GOOD and (b.heading or left == GOOD) else BAD
        seen[b.inside] = first if first in (GOOD, BAD) else seen[b.inside]
    return firsts


def main_text(page: str | None) -> str:
    blocks = blocks_of(page or "")
    classify(blocks)
    return "\n\n".join(b.text for b in blocks if b.label == "good")


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: its main text (blocks in page order, joined by an empty line) and the text's code points."""
    arrow = pa.schema([(id_col, pa.int64()), (url_col, pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])
    picked = pages.select(F.col(id_col), F.col(url_col).cast("string"), F.col(html_col).cast("string").alias("__html"))

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = [main_text(h) for h in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), part.column(1).cast(pa.string()), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], schema=arrow)

    return picked.mapInArrow(run, f"`{id_col}` long, `{url_col}` string, text string, n_chars long")
