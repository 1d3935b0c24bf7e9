"""Web pages to regions without a browser: a cell-metric layout of the html tree.

Metrics: 8 px a code point, 20 px a line, a page 1024 px wide, a banner 0..100.  The
template is ``page_id mod 3``: bar at the left (0..200, content 220..1024), at the right (content 0..804,
bar 824..1024), or at the top (item k at 160(k-1)..160k, y 100..120; content 0..1024 from y 120).
List items go into the bar, other leaf blocks into the content, one below the other;
inline elements lie at the origin of their block; containers bound what they hold.  Integers only.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..model import REGIONS
from ..session import shipped
from .tables import load

CHAR_W, LINE_H, WIDTH, BANNER, TOP_ITEM = 8, 20, 1024, 100, 160
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
INLINE = frozenset("a abbr b cite code em i kbd mark q s small span strong sub sup u".split())
LEAF = frozenset("li h1 h2 h3 h4 h5 h6 p div footer td th dt dd pre".split())
RAW = ("script", "style")
#: An opening tag ends open elements of these names, up to the next container.
ENDS = {"li": {"li"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}}
#: Entities that are decoded, in this order; anything else stays as it is.
ENTITIES = (("&copy;", "©"), ("&middot;", "·"), ("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&#39;", "'"), ("&amp;", "&"))
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(?P<raw>script|style)\b[^>]*>.*?(?:</(?P=raw)\s*>|\Z)|<(?P<end>/?)(?P<name>[a-zA-Z][a-zA-Z0-9]*)[^>]*>|<[!?][^>]*>", re.S | re.I)


@dataclass
class Node:
    tag: str
    path: str
    depth: int
    parent: Node | None
    ord: int = 0
    kids: int = 0
    runs: list[int] = field(default_factory=list)  # runs of text directly inside
    text_start: int | None = None
    text_end: int | None = None
    box: tuple[int, int, int, int] | None = None


def decode(text: str) -> str:
    for a, b in ENTITIES:
        text = text.replace(a, b)
    return " ".join(re.split(r"[ \t\n\r\f]+", text)).strip(" ")


def build_tree(html: str) -> tuple[list[Node], list[str]]:
    """Element nodes in document order (body is ``1``) and the runs of text."""
    body = re.search(r"<body\b[^>]*>", html, re.I)
    at = body.end() if body else 0
    root = Node("body", "1", 1, None, 1)
    nodes, runs, stack = [root], [], [root]

    def text(raw: str) -> None:
        said = decode(raw)
        if said:
            stack[-1].runs.append(len(runs))
            runs.append(said)

    for m in _TOKEN.finditer(html, at):
        text(html[at : m.start()])
        at = m.end()
        if m["name"] is None:
            continue
        name = m["name"].lower()
        if m["end"]:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == name:
                    del stack[i:]
                    break
            if name in ("body", "html"):
                at = len(html)
                break
            continue
        if name in VOID or name in ("html", "head", "body"):
            continue
        shut = ENDS.get(name, set()) | (set() if name in INLINE else {"p"})
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in shut:
                del stack[i:]
                break
            if stack[i].tag not in INLINE and stack[i].tag != "p":
                break
        up = stack[-1]
        up.kids += 1
        node = Node(name, f"{up.path}.{up.kids}", up.depth + 1, up, len(nodes) + 1)
        nodes.append(node)
        stack.append(node)
    text(html[at:])
    return nodes, runs


def place(nodes: list[Node], runs: list[str], template: int) -> None:
    """Text offsets and boxes."""
    offset, starts = 0, []
    for r in runs:
        starts.append(offset)
        offset += len(r) + 1
    for n in nodes:
        for r in n.runs:
            up: Node | None = n
            while up is not None:
                a, b = starts[r], starts[r] + len(runs[r])
                up.text_start = a if up.text_start is None else min(up.text_start, a)
                up.text_end = b if up.text_end is None else max(up.text_end, b)
                up = up.parent
    last = 0
    for n in nodes:  # nodes without text stand where the text before them ends
        if n.text_start is None:
            n.text_start = n.text_end = last
        last = max(last, n.text_start)
    bar = {0: (0, 200), 1: (824, 1024), 2: (0, WIDTH)}[template]
    content = {0: (220, 1024), 1: (0, 804), 2: (0, WIDTH)}[template]
    y_bar, y_content, item = BANNER, BANNER + (LINE_H if template == 2 else 0), 0
    held: dict[int, list[tuple[int, int, int, int]]] = {}
    for n in nodes:
        size = n.text_end - n.text_start
        inside = n.parent
        while inside is not None and inside.box is None:
            inside = inside.parent
        if inside is not None and inside.tag in LEAF:
            x, y, x_h, y_h = inside.box
            n.box = (x, y, x + min(CHAR_W * size, x_h - x), y_h)
        elif n.tag in LEAF:
            if n.tag == "li" and template == 2:
                n.box = (TOP_ITEM * item, BANNER, TOP_ITEM * (item + 1), BANNER + LINE_H)
                item += 1
            else:
                x, x_h = bar if n.tag == "li" else content
                height = LINE_H * max(1, -(-CHAR_W * size // (x_h - x)))
                y = y_bar if n.tag == "li" else y_content
                n.box = (x, y, x_h, y + height)
                if n.tag == "li":
                    y_bar += height
                else:
                    y_content += height
        if n.box is not None:
            up = n.parent
            while up is not None:
                held.setdefault(up.ord, []).append(n.box)
                up = up.parent
    for n in nodes:
        if n.box is None:
            own = held.get(n.ord)
            n.box = (min(b[0] for b in own), min(b[1] for b in own), max(b[2] for b in own), max(b[3] for b in own)) if own else (0, BANNER, 0, BANNER)


def draw(page_id: int | None, html: str | None) -> list[tuple]:
    """Rows of the relation of regions for one page."""
    template = (page_id or 0) % 3
    nodes, runs = build_tree(html or "")
    place(nodes, runs, template)
    chains: dict[tuple[int, int], list[Node]] = {}
    for n in nodes:
        if n.text_end > n.text_start:
            chains.setdefault((n.text_start, n.text_end), []).append(n)
    out = []
    for n in nodes:
        chain = chains.get((n.text_start, n.text_end), [n]) if n.text_end > n.text_start else [n]
        own = "\n".join(runs[r] for r in n.runs) if n.runs else None
        out.append((page_id, n.path, *n.box, n.text_start, n.text_end, own, n.tag, max(chain, key=lambda x: x.depth).path, min(chain, key=lambda x: x.depth).path, n.depth, n.ord, template))
    return out


def render_pages(pages: DataFrame) -> DataFrame:
    """REGIONS of ``page_id, html``: one pass over the html, no shuffle."""
    names = REGIONS.names
    types = [pa.string() if f.dataType.simpleString() == "string" else pa.int64() for f in REGIONS]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [r for page, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) for r in draw(page, html)]
            for lo in range(0, len(rows), 50_000):
                cols = zip(*rows[lo : lo + 50_000], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    return shipped(pages).select("page_id", "html").mapInArrow(run, REGIONS)


def regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return render_pages(load(spark, sf_dir, "pages"))
