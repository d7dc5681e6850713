"""Main text of HTML pages by tag-path ratios.

A page is a sequence of blocks, each with the path of block elements from the root to it. Per path the text
length, punctuation and linked text of its blocks are summed into ratios; these are smoothed over the
blocks in page order, fused into one value and compared with a threshold. Blocks of the selected paths, and blocks
under the element that holds most selected text, are content. An article or main element decides nothing by itself: where
such elements hold most of the selected text, paths outside them count OUTSIDE of their value, and blocks in the one around the holder
need only HEADING of the threshold. What HTML or usual class names mark
as menu, header, footer, sidebar, notice, advert, form or reader comment never is.

Defined results: null and empty pages have no text; broken markup is read as browsers do in outline (an open
paragraph ends at the next block, unclosed elements end with the page, a cut tag is dropped); white space
in a block becomes one space; blocks are joined by a line feed; nothing is capped; repeated rows get equal results.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: Elements by role.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr input picture source".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea xmp iframe noembed noframes".split())
NEVER = frozenset("head script style title noscript template iframe object embed svg math canvas audio video nav footer aside form button select option textarea menu dialog datalist map fieldset xmp noembed noframes".split())
NEVER_ROLE = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert form menu menubar toolbar".split())
NEVER_WORD = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense adslot banner banners sponsor sponsored sponsors promo promos promotion promoted "
    "sidebar sidebars aside menu menus nav navbar navigation navigations breadcrumb breadcrumbs topbar toolbar tabs pagination pager "
    "cookie cookies consent gdpr notice notices notification notifications alert alerts popup popups modal overlay disclaimer "
    "footer footers foot masthead header pageheader newsletter subscribe subscription signup login share sharing social "
    "related recommended recommendations trending popular widget widgets comment comments comentarios commentaires kommentare disqus respond reply replies reviews skip skiplink".split()
)
#: Headers of the page go, headings inside the article stay.
ARTICLE = frozenset(("article", "main"))
#: An element of these ends an open paragraph.
CLOSERS = {"li": ("li", ("ul", "ol", "menu")), "dt": ("dt dd", ("dl",)), "dd": ("dt dd", ("dl",)), "tr": ("tr td th", ("table",)), "td": ("td th", ("tr", "table")), "th": ("td th", ("tr", "table")), "option": ("option", ("select",))}

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(>|\Z)", re.S)
ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
NAME = re.compile(r"[a-z]+")
PUNCTUATION = re.compile(r"[.,;:!?…。，、؛؟¿¡]")

SMOOTHING = (0.25, 0.5, 0.25)
THRESHOLD = 0.25
#: What article and main elements that hold most selected text change.
OUTSIDE, HEADING = 0.2, 0.1


class Block:
    __slots__ = ("path", "parts", "linked", "container")

    def __init__(self, path: tuple[str, ...], container: tuple[int, ...]):
        self.path, self.container, self.parts, self.linked = path, container, [], 0


def _never(tag: str, attributes: str, in_article: bool) -> bool:
    if tag in NEVER or tag == "header" and not in_article:
        return True
    if not attributes.strip():
        return False
    for m in ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
            return True
        if name == "role" and value.strip() in NEVER_ROLE:
            return True
        if name in ("class", "id") and tag not in ("html", "body") and tag not in ARTICLE:
            words = NAME.findall(value)
            if not NEVER_WORD.isdisjoint(words):
                return True
    return False


def blocks_of(page: str) -> list[Block]:
    """Blocks with text that may be content, in page order."""
    found: list[Block] = []
    stack: list[tuple[str, bool, int]] = []  # tag, whether never content, number of the element
    never = links = number = 0
    current: Block | None = None
    at, end = 0, len(page)

    def text(raw: str) -> None:
        nonlocal current
        if never or not raw:
            return
        if current is None:
            if not raw.strip():
                return
            inner = [(t, n) for t, _, n in stack if t not in INLINE]
            current = Block(tuple(t for t, _ in inner), tuple(n for _, n in inner))
            found.append(current)
        said = entities.unescape(raw) if "&" in raw else raw
        current.parts.append(said)
        if links:
            current.linked += len(said)

    def pop() -> None:
        nonlocal never, links
        tag, bad, _ = stack.pop()
        never -= bad
        links -= tag == "a"

    while at < end:
        m = TOKEN.search(page, at)
        if m is None:
            text(_before_cut(page[at:]))
            break
        text(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            if m[0].startswith("<![CDATA["):
                text(m[0][9:].removesuffix("]]>"))
            continue
        if not m[4]:  # the page ends inside a tag
            break
        tag, closing = m[2].lower(), bool(m[1])
        if tag not in INLINE:
            current = None
        elif tag == "br" and current is not None:
            current.parts.append(" ")
        if closing:
            if any(t == tag for t, _, _ in stack):
                if tag in INLINE and _blocked(stack, tag):
                    continue
                while stack[-1][0] != tag:
                    pop()
                pop()
            continue
        if tag not in INLINE:
            _close_before(tag, stack, pop)
        if tag in VOID or m[3].endswith("/") and tag not in ("a", "p", "div", "span", "script", "style"):
            continue
        number += 1
        bad = _never(tag, m[3], any(t in ARTICLE for t, _, _ in stack))
        stack.append((tag, bad, number))
        never += bad
        links += tag == "a"
        if tag in RAW:
            close = re.compile(rf"</{tag}(?=[\s/>]|\Z)", re.I).search(page, at)
            at = close.start() if close else end
    return [b for b in found if "".join(b.parts).strip()]


def _before_cut(rest: str) -> str:
    """Text up to a tag that the page's end cuts."""
    cut = re.search(r"<[a-zA-Z/!?]?[^<]*\Z", rest)
    return rest[: cut.start()] if cut and re.match(r"<(?:[a-zA-Z/!?]|\Z)", cut[0]) else rest


def _blocked(stack: list, tag: str) -> bool:
    """Whether a block was opened after the last open inline element of this tag."""
    for t, _, _ in reversed(stack):
        if t == tag:
            return False
        if t not in INLINE:
            return True
    return False


def _close_before(tag: str, stack: list, pop) -> None:
    """End what the start of a block ends: an open paragraph, and items of the same list or row."""
    names = [t for t, _, _ in stack]
    if "p" in names:
        last = len(names) - 1 - names[::-1].index("p")
        if all(t in INLINE for t in names[last + 1 :]):
            while len(stack) > last:
                pop()
    if tag in CLOSERS:
        own, borders = CLOSERS[tag]
        own_set = own.split()
        for i in range(len(stack) - 1, -1, -1):
            if stack[i][0] in borders:
                break
            if stack[i][0] in own_set:
                while len(stack) > i:
                    pop()
                break


def content_blocks(blocks: list[Block]) -> list[bool]:
    """Which blocks are content, by the fused and smoothed ratios of their paths."""
    if not blocks:
        return []
    sums: dict[tuple, np.ndarray] = {}
    said = ["".join(b.parts) for b in blocks]
    for b, t in zip(blocks, said):
        plain = len(" ".join(t.split()))
        sums.setdefault(b.path, np.zeros(4))
        sums[b.path] += (plain, len(PUNCTUATION.findall(t)), min(b.linked, plain), 1)
    ratio = {p: ((v[0] - v[2]) / v[3], v[1] / v[3]) for p, v in sums.items()}
    each = np.array([ratio[b.path] for b in blocks])
    if len(blocks) > 2:
        padded = np.vstack([each[:1], each, each[-1:]])
        each = sum(w * padded[k : k + len(blocks)] for k, w in enumerate(SMOOTHING))
    fused = each[:, 0] * (1 + each[:, 1])
    by_path: dict[tuple, list[float]] = {}
    for b, f in zip(blocks, fused):
        by_path.setdefault(b.path, []).append(f)
    value = {p: float(np.mean(v)) for p, v in by_path.items()}
    least = THRESHOLD * max(value.values())
    select = lambda: {p for p, v in value.items() if v >= least and ratio[p][0] > 0}
    free = [len(t) - b.linked for b, t in zip(blocks, said)]
    selected = select()
    inside = sum(n for b, n in zip(blocks, free) if b.path in selected and not ARTICLE.isdisjoint(b.path))
    prior = 2 * inside > sum(n for b, n in zip(blocks, free) if b.path in selected)
    if prior:
        value = {p: v if not ARTICLE.isdisjoint(p) else OUTSIDE * v for p, v in value.items()}
        least = THRESHOLD * max(value.values())
        selected = select()
    weight: dict[int, float] = {}
    for b, n in zip(blocks, free):
        if b.path in selected and b.container:
            holder = b.container[-2] if len(b.container) > 1 else b.container[-1]
            weight[holder] = weight.get(holder, 0) + n
    holder = max(weight, key=lambda n: (weight[n], -n)) if weight else -1
    around = _article_around(holder, blocks) if prior else -1
    chosen = lambda b: b.path in selected or holder in b.container or around in b.container and value[b.path] >= HEADING * least
    return [chosen(b) and not _link_list(b, t) for b, t in zip(blocks, said)]


def _article_around(holder: int, blocks: list[Block]) -> int:
    """The innermost article or main element that is or holds an element; -1 if there is none."""
    for b in blocks:
        if holder in b.container:
            for tag, n in reversed(list(zip(b.path, b.container))[: b.container.index(holder) + 1]):
                if tag in ARTICLE:
                    return n
            return -1
    return -1


def _link_list(block: Block, said: str) -> bool:
    """A list item or cell that is one link: part of a menu."""
    return bool({"li", "td"} & set(block.path)) and block.linked >= 0.9 * len(said.strip())


def main_text(page: str | None) -> str:
    blocks = blocks_of(page or "")
    lines = (" ".join("".join(b.parts).split()) for b, keep in zip(blocks, content_blocks(blocks)) if keep)
    return "\n".join(x for x in lines if x)


def extract_pages(pages: DataFrame) -> DataFrame:
    """Per row of pages (page_id, url, html): page_id, url, text, n_chars."""
    kind = pages.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = [main_text(p) for p in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, f"page_id {kind}, url string, text string, n_chars long")
