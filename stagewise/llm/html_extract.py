"""Main text of web pages by two passes of block rules.

Pass one cuts a page into blocks at block-level tags, drops elements that are never main
text, and classifies each block by its length, link density and stop-word density.  Containers that only their
names give away count as boilerplate as long as the page has text outside of them.  In pass
two an ambiguous or short block takes the label of the nearest decided neighbours on
both sides.  Inside an article or main element the rules lean to keeping a block, outside of it
to dropping it; pages without either are judged by the rules alone.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

# Frequent function words of the languages served.
STOP_WORDS = frozenset(
    """the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which one you were
    all her she there would their we him been has when who will no more if out so up said what its about than into them can only
    der die das und in den von zu mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird
    bei einer um am sind noch wie einem über einen so zum war haben nur oder aber vor zur bis mehr durch man sein wurde
    le la les de des et en un une du que qui dans pour est par au sur pas plus ne se ce il sont avec son aux ou mais sa ses leur
    comme nous vous elle on été cette être même
    el los las y del una por con no para su al lo como más o pero sus este ya entre cuando todo esta ser son dos también fue había
    era muy años hasta desde está mi porque""".split()
)
BLOCK_TAGS = frozenset(
    """address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6
    head header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul""".split()
)
DROPPED_TAGS = frozenset(
    "head nav header footer aside form script style noscript template iframe svg math select button textarea object dialog menu title canvas audio video".split()
)
RAW_TAGS = frozenset("script style textarea title noscript iframe template".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Words of class, id and role values of containers that are beside the text (LAYOUT) or never text (NEVER).
LAYOUT = frozenset("nav navbar navigation menu breadcrumb breadcrumbs header masthead footer foot sidebar side aside widget search pagination pager toolbar complementary contentinfo".split())
NEVER = frozenset(
    """ad ads adsense banner promo cookie cookies consent notice alert popup modal overlay comment comments commentlist respond replies reply disqus discussion
    share sharing social related recommended subscribe newsletter signup login hidden disclaimer copyright""".split()
)
#: Words that may stand beside those in one name: ``left-sidebar`` is a sidebar, ``with-sidebar`` is not.
NEUTRAL = frozenset("site page main top bottom left right box container wrapper wrap list block section bar area inner outer item items body panel module group col column content div li ul the thread global primary secondary".split())
_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?>=\s*+(?:\"[^\"]*\"|'[^']*'|[^\s>\"'][^\s>]*+)?+|[^=>]++)*+)>")
_MARKUP = re.compile(r"<(?=[a-zA-Z/!?])")
_ATTRIBUTE = re.compile(r"(?:^|[\s/\"'])(class|id|role|hidden|aria-hidden|style)(?=[\s=/]|$)\s*(?:=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?", re.I)
_UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_WORD = re.compile(r"[^\W\d_]+")
_ENDS = {t: re.compile(rf"</{t}(?=[\s/>])[^>]*>", re.I) for t in RAW_TAGS}
#: Elements that an opening one of the same kind ends, and those beyond which it does not reach.
_ENDED_BY_KIN = frozenset("p li dd dt tr td th option".split())
_BOUNDS = frozenset("ul ol dl table div article section main nav body td th".split())
GOOD, BAD, SHORT, NEAR = "good", "bad", "short", "near"


def _name_kind(value: str) -> int:
    """0: a name like any other, 1: one of LAYOUT, 2: one of NEVER; all its words must be known."""
    worst = 0
    for token in value.lower().split():
        kind = 0
        for word in re.split(r"[-_]+", token):
            if word in NEVER or word.startswith(("advert", "sponsor")):
                kind = 2
            elif word in LAYOUT:
                kind = max(kind, 1)
            elif word not in NEUTRAL and not word.isdigit():
                kind = 0
                break
        worst = max(worst, kind)
    return worst


def _container(attributes: str) -> tuple[bool, int]:
    """(whether the element is not shown, the kind of its names)."""
    if "=" not in attributes and "hidden" not in attributes.lower():
        return False, 0
    unseen, kind = False, 0
    for name, value in _ATTRIBUTE.findall(attributes):
        name, value = name.lower(), value.strip("\"'")
        if name == "hidden" or name == "aria-hidden" and value.lower() == "true" or name == "style" and _UNSEEN.search(value):
            unseen = True
        elif name in ("class", "id", "role"):
            kind = max(kind, _name_kind(value))
    return unseen, kind


class Box:
    """A container whose name says that it is not main text; ``main``: it holds an article or main element."""

    __slots__ = ("kind", "main")

    def __init__(self, kind: int):
        self.kind, self.main = kind, False


class Block:
    __slots__ = ("parts", "linked", "main", "heading", "boxes", "text")

    def __init__(self, main: bool, heading: bool, boxes: tuple[Box, ...]):
        self.parts: list[str] = []
        self.linked = 0
        self.main = main
        self.heading = heading
        self.boxes = boxes
        self.text = ""


def blocks_of(page: str) -> list[Block]:
    """The blocks of a page that hold shown text outside of elements that are never main text."""
    out: list[Block] = []
    boxes: list[Box] = []
    now = Block(False, False, ())
    # open elements: (tag, whether it drops its content, whether it is article or main, its box), and where those of each tag are
    stack: list[tuple[str, bool, bool, Box | None]] = []
    opens: dict[str, list[int]] = {}
    solid: list[int] = [-1]  # places of open block elements
    bounds: list[int] = [-1]
    dropping = mains = links = 0
    at, end = 0, len(page)

    def text(piece: str) -> None:
        if not dropping and piece:
            piece = html.unescape(piece) if "&" in piece else piece
            now.parts.append(piece)
            if links:
                now.linked += len(piece.strip())

    def close(n: int) -> None:
        nonlocal dropping, mains, links
        while len(stack) > n:
            tag, dropped, main, box = stack.pop()
            opens[tag].pop()
            if solid[-1] == len(stack):
                solid.pop()
            if bounds[-1] == len(stack):
                bounds.pop()
            if box is not None:
                boxes.pop()
            dropping -= dropped
            mains -= main
            links -= tag == "a"

    def turn(tag: str = "") -> None:
        nonlocal now
        if now.parts:
            out.append(now)
        now = Block(mains > 0, tag in ("h1", "h2", "h3", "h4", "h5", "h6"), tuple(boxes))

    while at < end:
        found = _MARKUP.search(page, at)
        if not found:
            text(page[at:])
            break
        begin = found.start()
        text(page[at:begin])
        m = _TAG.match(page, begin)
        if not m:
            follow = page[begin + 1 : begin + 3]
            if follow[:1].isalpha() or follow[:1] == "/" and follow[1:].isalpha():
                break  # a tag that never ends is markup up to the end
            if page.startswith("<!--", begin):
                stop = page.find("-->", begin + 2)
                at = end if stop < 0 else stop + 3
            else:
                stop = page.find(">", begin)
                at = end if stop < 0 else stop + 1
            continue
        at = m.end()
        tag = m[2].lower()
        block = tag in BLOCK_TAGS
        where = opens.setdefault(tag, [])
        if m[1]:
            # inline elements end inside their block only
            if where and (block or tag in DROPPED_TAGS or solid[-1] <= where[-1]):
                close(where[-1])
            if block:
                turn()
            continue
        if tag in RAW_TAGS and not m[3].endswith("/"):
            ended = _ENDS[tag].search(page, at)
            at = ended.end() if ended else end
            if block:
                turn()
            continue
        if tag == "br":
            text(" ")
            continue
        if block:
            if tag in _ENDED_BY_KIN and where and where[-1] > bounds[-1]:
                close(where[-1])
            paragraphs = opens.get("p")
            if paragraphs and paragraphs[-1] > bounds[-1]:
                close(paragraphs[-1])
        if tag in VOID_TAGS:
            if block:
                turn()
            continue
        main = tag in ("article", "main")
        dropped, box = tag in DROPPED_TAGS, None
        if not dropped and tag not in ("html", "body", "main"):
            dropped, kind = _container(m[3])
            if not dropped and (kind == 2 or kind == 1 and not main):
                box = Box(kind)
        if not m[3].endswith("/") or block:
            if main and box is None:
                for x in boxes:
                    x.main = True
            if box is not None:
                boxes.append(box)
            where.append(len(stack))
            if block:
                solid.append(len(stack))
            if tag in _BOUNDS:
                bounds.append(len(stack))
            stack.append((tag, dropped, main and not dropped, box))
            dropping += dropped
            mains += main and not dropped
            links += tag == "a"
        if block:
            turn(tag)
    turn()
    found_blocks = []
    for b in out:
        b.text = " ".join("".join(b.parts).split())
        if b.text:
            found_blocks.append(b)
    return found_blocks


def classify(block: Block) -> str:
    """First pass: the label of a block from its length, link density and stop-word density."""
    text = block.text
    if block.linked / len(text) > 0.33:
        return BAD
    words = _WORD.findall(text.lower())
    if len(text) < 70 or block.heading:
        return SHORT
    density = sum(w in STOP_WORDS for w in words) / max(1, len(words))
    if density >= 0.2:
        return GOOD if len(text) > 140 else NEAR
    if density >= 0.1:
        return NEAR
    return NEAR if block.main else BAD  # an article may hold tables or lists without function words


def _candidates(blocks: list[Block]) -> list[Block]:
    """Blocks to judge.  What is outside of an article or main element is not the text where there is one.

    Containers by name are left out, unless they are around the only article, or around all long texts of the page.
    """
    free = [b for b in blocks if not b.boxes]
    inside = [b for b in free if b.main] or [b for b in blocks if b.main and all(x.main and x.kind == 1 for x in b.boxes)]
    if inside:
        return inside
    if not any(classify(b) == GOOD for b in free):
        inside = [b for b in blocks if b.main and all(x.main for x in b.boxes)]
        if inside:
            return inside
        beside = [b for b in blocks if all(x.kind == 1 for x in b.boxes)]
        if any(classify(b) == GOOD for b in beside):
            return beside
    return free


def main_text(page: str | None) -> str:
    """The main text of one page; empty for null, empty or all-boilerplate pages.

    Short blocks take the label of the nearest decided block, and between two as near that of the rejected one;
    a heading goes with good text that follows, an ambiguous block with any good neighbour.  Where a page has no decided block of running text, ambiguous blocks without links are its text, or else the short ones not next to rejected ones.
    """
    blocks = _candidates(blocks_of(page)) if page else []
    inside = bool(blocks) and all(b.main for b in blocks)
    labels = [classify(b) for b in blocks]
    if inside and BAD not in labels:
        return " ".join(b.text for b in blocks)
    if not inside and GOOD not in labels:
        near = [b.text for b, x in zip(blocks, labels) if x == NEAR and not b.linked]
        return " ".join(near or _alone(blocks, labels))
    before, after = _decided(labels), _decided(labels[::-1])[::-1]
    kept = []
    for block, x, (back, left), (ahead, right) in zip(blocks, labels, before, after):
        if x == NEAR:
            x = GOOD if GOOD in (left, right) or inside and None in (left, right) else BAD
        elif x == SHORT:
            if left == right:
                x = left
            elif block.heading and right == GOOD or inside and not block.linked and GOOD in (left, right):
                x = GOOD
            elif None in (left, right):
                x = left or right
            else:
                x = left if back < ahead or back == ahead and left == BAD else right
        if x == GOOD:
            kept.append(block.text)
    return " ".join(kept)


def _decided(labels: list[str]) -> list[tuple[int, str | None]]:
    """For each block: how many blocks before it the last decided one lies, and its label; none: (0, None)."""
    out, last, label = [], 0, None
    for k, x in enumerate(labels):
        out.append((k - last if label else 0, label))
        if x in (GOOD, BAD):
            last, label = k, x
    return out


def _alone(blocks: list[Block], labels: list[str]) -> list[str]:
    """Short blocks without links of a page that has no other text, but for those next to a rejected one."""
    around = [None, *labels, None]
    return [b.text for k, (b, x) in enumerate(zip(blocks, labels)) if x == SHORT and not b.linked and BAD not in (around[k], around[k + 2])]


def _run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(0, batch.num_rows, 256):
            part = batch.slice(k, 256)
            texts = [main_text(x) for x in part.column("html").to_pylist()]
            cols = [part.column("page_id"), part.column("url"), pa.array(texts, type=pa.string()), pa.array([len(x) for x in texts], type=pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, names=["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame) -> DataFrame:
    """pages(page_id, url, html, ...) -> (page_id, url, text, n_chars), one row per input row.

    White space inside a block becomes one space; blocks are joined in page order by one
    space; ``n_chars`` counts code points.  Null or empty html gives an empty text.  Other columns are not read.
    """
    kinds = dict(pages.dtypes)
    schema = f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long"
    return pages.select("page_id", "url", "html").mapInArrow(_run, schema)
