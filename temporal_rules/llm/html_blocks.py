"""Main text of web pages by two passes of block rules.

A page is cut at block-level tags.  The first pass decides a block by itself: what stands in
menus, footers, forms, adverts, comments and the like is boilerplate; length, density of
links and density of stop words decide others, as far as they can.  The second pass gives
undecided blocks (short ones, or of middling density) the label of the nearest decided
neighbour; a heading asks what follows it.  A page's own mark of its article is a prior: the
same rules run on both sides of it, and only what they leave undecided goes with the mark.
"""

from __future__ import annotations

import html
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import reach_workers

# Function words of the languages expected, tags, and names of page furniture.
STOP_WORDS = frozenset(
    """
    a an and are as at be been but by for from had has have he her his i in is it its my no not of on or our she so that the their there they this to was we were what when which who will with you your
    au aux avec ce ces cette dans de des du elle en est et eux il ils je la le les leur lui mais ne nous on ou par pas pour que qui sa se ses son sur un une vous
    aber als am an auch auf aus bei bin bis da das dass dem den der des die durch ein eine einem einen einer er es für haben hat ich ihr im in ist ja kann mit nach nicht noch nur oder sein sich sie sind so über um und uns von vor war was wenn wer wie wird wir zu zum zur
    al como con del desde donde el ella en entre era es esta este esto fue ha hay la las lo los más me mi muy no nos o para pero por que se ser si sin sobre su sus también tiene un una y ya
    """.split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var br img wbr".split())
FURNITURE = frozenset("nav footer aside form menu dialog button fieldset".split())
MARKED = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|cookies?|consent|gdpr|comments?|commentlist|disqus|sidebar|widget|menu|nav|navbar|navigation|breadcrumbs?|footer|masthead|share|sharing|social|related|recommended|newsletter|subscribe|subscription|signup|login|popup|modal|notice|toolbar|pagination|pager)(?:[\s_-]|$)",
    re.I,
)
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert menu menubar".split())
TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<(script|style|noscript|template|svg|textarea|select|iframe|object|canvas|head(?=[\s>]))\b[^>]*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)|<[!?][^>]*(?:>|\Z)",
    re.S | re.I,
)
ATTRIBUTE = re.compile(r"(class|id|role|aria-hidden|style|itemprop|hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.I)
SIGN = re.compile(r"^\W+|\W+$")


def closed(page: str) -> str:
    """The page without tags that would hide its rest: self-closed graphics, a head or another such element that is never closed."""
    low = page.lower()
    if "<svg" in low:
        page = re.sub(r"<svg\b[^>]*/>", " ", page, flags=re.I)
        low = page.lower()
    for name in ("head", "svg", "select", "object", "canvas"):
        if f"<{name}" not in low:
            continue
        last = low.rfind(f"</{name}")
        tail = re.sub(rf"<{name}(?=[\s>])[^>]*>", " ", page[last + 1 :], flags=re.I)
        if len(tail) != len(page) - last - 1:
            if name == "head":
                tail = re.sub(r"<title\b[^>]*>.*?</title\s*>", " ", tail, flags=re.I | re.S)
            page = page[: last + 1] + tail
            low = page.lower()
    return page


class Block:
    __slots__ = ("text", "linked", "furniture", "article", "heading", "label")

    def __init__(self, text: str, linked: int, furniture: bool, article: bool, heading: bool):
        self.text, self.linked, self.furniture, self.article, self.heading = text, linked, furniture, article, heading
        self.label: bool | None = None


def _state(tag: str, attributes: str, furniture: bool, article: bool) -> tuple[bool, bool]:
    """Whether an element's content is page furniture and whether it is the article."""
    found = {m[1].lower(): m[2] or m[3] or m[4] or "" for m in ATTRIBUTE.finditer(attributes)} if attributes.strip() else {}
    role = found.get("role", "").lower()
    if tag in ("article", "main") or role in ("main", "article") or "articlebody" in found.get("itemprop", "").lower():
        names = f"{found.get('class', '')} {found.get('id', '')}"
        return furniture or bool(re.search(r"comment", names, re.I)), tag == "article" or article or "MAIN"
    if furniture or tag in ("html", "body"):
        return furniture, article
    if tag in FURNITURE or tag == "header" and not article or role in ROLES:
        return True, article
    if "hidden" in found or found.get("aria-hidden", "").lower() == "true" or re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", found.get("style", ""), re.I):
        return True, article
    return bool(MARKED.search(found.get("class", "")) or MARKED.search(found.get("id", ""))), article


def blocks_of(page: str) -> list[Block]:
    out: list[Block] = []
    stack: list[tuple[str, bool, object]] = []
    furniture, article = False, False
    pieces: list[str] = []
    linked, in_link, heading, at = 0, False, False, 0

    def close() -> None:
        nonlocal linked, pieces
        if pieces:
            text = " ".join("".join(pieces).split())
            if text:
                out.append(Block(text, linked, furniture, article, heading))
            pieces = []
        linked = 0

    def add(raw: str) -> None:
        nonlocal linked
        text = html.unescape(raw) if "&" in raw else raw
        pieces.append(text)
        if in_link:
            linked += len(text.strip())

    for m in TOKEN.finditer(closed(page)):
        if m.start() > at:
            add(page[at : m.start()])
        at = m.end()
        if m[0].startswith("<![CDATA["):
            add(m[0][9:-3])
            continue
        tag = (m[3] or m[6] or "").lower()
        if not tag:
            if m[1]:
                close()
            continue
        ending, attributes = bool(m[2] or m[5]), m[4] or m[7] or ""
        if tag == "a":
            in_link = not ending
            continue
        if tag == "br":
            pieces.append(" ")
            continue
        if tag in INLINE:
            if not ending and tag not in VOID and attributes.strip():
                now = _state(tag, attributes, furniture, article)
                if now[0] != furniture:
                    close()
                    stack.append((tag, furniture, article))
                    furniture, article = now
            elif ending and any(t == tag for t, _, _ in stack):
                close()
                while True:
                    t, furniture, article = stack.pop()
                    if t == tag:
                        break
            continue
        close()
        in_link = False
        if tag in VOID:
            continue
        if ending:
            if any(t == tag for t, _, _ in stack):
                while True:
                    t, furniture, article = stack.pop()
                    if t == tag:
                        break
            heading = any(re.fullmatch(r"h[1-6]", t) for t, _, _ in stack)
            continue
        if stack and stack[-1][0] == "p":
            _, furniture, article = stack.pop()
        if stack and stack[-1][0] == tag and tag in ("li", "td", "th", "tr", "dd", "dt", "option"):
            _, furniture, article = stack.pop()
        stack.append((tag, furniture, article))
        furniture, article = _state(tag, attributes, furniture, article)
        heading = any(re.fullmatch(r"h[1-6]", t) for t, _, _ in stack)
    if at < len(page):
        add(page[at:])
    close()
    return out


def stop_words(text: str) -> tuple[int, int]:
    """Stop words and words of a block."""
    words = [SIGN.sub("", w) for w in text.lower().split()]
    return sum(w in STOP_WORDS for w in words), len(words)


def decide(block: Block, share: float, marked: bool, fluent: bool, short: int, long: int, low: float, high: float, links: float) -> bool | None:
    """First pass: True keeps, False drops, None is for the neighbours.

    Inside a page's own article (``marked``) a short block may hold a link and shorter prose is kept; stop
    words missing there say something only where the article as a whole has them (``fluent``).
    """
    if block.furniture:
        return False
    if block.linked / len(block.text) > links or "©" in block.text and len(block.text) < long:
        return False
    if len(block.text) < short:
        return False if block.linked and not marked else None
    if share >= high:
        return True if marked or len(block.text) >= long else None
    return None if share >= low or not block.linked or marked and not fluent else False


def by_neighbours(blocks: list[Block]) -> None:
    """Second pass where nothing is marked: the label of the nearest decided block; a heading asks what follows."""
    first = [b.label for b in blocks]
    known = [i for i, x in enumerate(first) if x is not None]
    for i, b in enumerate(blocks):
        if b.label is None:
            if not known:
                b.label = True
                continue
            j = int(np.searchsorted(known, i))
            before, after = (known[j - 1] if j else None), (known[j] if j < len(known) else None)
            if b.heading and after is not None:
                b.label = first[after]
            elif before is None or after is not None and after - i < i - before:
                b.label = first[after]
            else:
                b.label = first[before]


def by_sides(blocks: list[Block], prior: bool) -> None:
    """Second pass beside a mark: an undecided block goes against the prior only where the decided blocks on
    both its sides do; a heading inside goes with what it heads."""
    first = [b.label for b in blocks]
    before: list[bool] = []
    last = prior
    for x in first:
        last = last if x is None else x
        before.append(last)
    last = prior
    for i in range(len(blocks) - 1, -1, -1):
        last = last if first[i] is None else first[i]
        if first[i] is None:
            blocks[i].label = before[i] if before[i] == last else prior
    if prior:
        kept = seen = False
        for i in range(len(blocks) - 1, -1, -1):
            b = blocks[i]
            if not b.heading:
                if i + 1 < len(blocks) and blocks[i + 1].heading:
                    kept = seen = False
                kept, seen = kept or bool(b.label), True
            elif first[i] is None:
                b.label = kept or not seen


def main_text(page: str | None, short: int = 70, long: int = 160, low: float = 0.1, high: float = 0.2, links: float = 0.33) -> str:
    """The kept blocks of a page in page order, joined by an empty line; "" for null, empty and textless pages."""
    if not page:
        return ""
    every = blocks_of(page)
    blocks = [b for b in every if not b.furniture]
    if any(b.article is True for b in blocks):  # an <article>; a bare <main> around it says less
        for b in blocks:
            b.article = b.article is True
    counts = [stop_words(b.text) for b in blocks]
    for b, (stops, n) in zip(blocks, counts):
        b.label = decide(b, stops / n, False, True, short, long, low, high, links)
    inside = [b for b in blocks if b.article]
    outside = [b for b in blocks if not b.article]
    # A mark around teasers (links, and nothing that the rules keep) is none where they keep text outside.
    teasers = any(b.linked / len(b.text) > links for b in inside) and not any(b.label for b in inside) and any(b.label for b in outside)
    if not inside or teasers:
        by_neighbours(blocks)
    else:
        stops, n = (sum(x) for x in zip(*(c for b, c in zip(blocks, counts) if b.article)))
        for b, (s, m) in zip(blocks, counts):
            if b.article:
                b.label = decide(b, s / m, True, stops >= low * n, short, long, low, high, links)
        by_sides(inside, True)
        by_sides(outside, False)
    return "\n\n".join(b.text for b in blocks if b.label)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row.

    Null or empty html gives empty text; other columns are ignored; null ids and urls stay;
    repeated rows are extracted each; an empty table gives no rows.
    """
    reach_workers(pages.sparkSession)

    def run(batches):
        for batch in batches:
            texts = [main_text(h) for h in batch.column(2).to_pylist()]
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string, n_chars long")
