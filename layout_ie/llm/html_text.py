"""Main text of web pages by two-pass block rules.

A page is cut into blocks of text between block-level tags.  Pass one labels a
block by its link density, its length and its stop-word density, and by where it stands: inside an article
little is needed, in the open page much, inside a menu, form, notice and the like nothing helps.  Runs of blocks that
are all link are menus wherever they stand.  Blocks
that are short or in between stay ambiguous.  Pass two gives each ambiguous block
the label of its nearest decided neighbours of the same region; the nearer one
wins, and a tie goes to the text.  Inside an article ambiguous blocks without a
decided neighbour are text, elsewhere they are not.

Stop words count only where the page is in a language whose words are listed, which its long blocks tell; other
languages go by length and links.  A character of a script without blanks counts as three.

A class marks an element by a whole token or a token's first or last part, unless a part tells a state; it
does not count for the first article or main inside it, nor where a page would be left without a text.  An article that
holds next to nothing beside a long open page is not taken for the article.

Defined results: a null or empty html gives an empty text; unclosed tags end
with their parent, an unclosed comment, script or style runs to the end;
repeated pages are extracted each; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shipped

#: Fixed word lists: frequent function words of four languages.
STOP_WORDS = frozenset(
    # English
    "the of and to in a is that for it was on as with be by at this are or an from not which but have has had were their they his her its you we will would can "
    # German
    "der die das und in zu den von mit im ist des sich auf für dem ein eine nicht als auch es an er so dass aus bei nach wird "
    # French
    "le la les de des du et un une est que qui dans en pour par sur au aux pas ne se ce il elle avec plus son sa ses "
    # Spanish
    "el los las y del una no con su para al lo como más pero sus o si porque esta entre".split()
)
#: Elements whose text never counts.
RAW = ("script", "style", "noscript", "template", "svg", "math", "iframe", "object", "select", "textarea", "title")
ASIDE = frozenset(("nav", "footer", "aside", "form", "button", "dialog", "menu", "fieldset"))
MAIN = frozenset(("article", "main"))
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Words of class, id or role that mark what is not the article.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments commentlist cookie cookies consent copyright disclaimer disqus footer gdpr login masthead menu menubar modal nav navbar navigation newsletter notice notices notification pager pagination popup promo promotion related reply respond share sharing sidebar signup skip social sponsor sponsored subscribe toolbar widget widgets complementary contentinfo search".split()
)
HEADER = frozenset(("header", "masthead"))
#: Parts of a class that tell the state of a whole page or element, as in has-sidebar or post-share-enabled.
STATES = frozenset("has have no not with without is are show shows hide hides enable enabled disable disabled open opened closed active inactive on off layout supports allow allowed".split())
#: Opening one of the keys ends an open element of the values.
IMPLIED = {
    "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"},
    "tbody": {"thead", "tbody", "tfoot"}, "tfoot": {"thead", "tbody"}, "option": {"option"},
}

LINK_BAD, LINK_MAIN_BAD = 0.34, 0.9
SHORT, LONG = 70, 200
STOP_LOW, STOP_HIGH = 0.2, 0.3
#: Share of stop words in the long blocks of a page from which its language counts as listed.
LISTED = 0.1
#: Blocks in a row that are all link: a menu.
MENU = 3
#: Scripts that are written without blanks: from the radicals to the compatibility ideographs, and Thai to Khmer.
_DENSE = re.compile("[\u2e80-\ud7a3\uf900-\ufaff\u0e00-\u0eff\u1000-\u109f\u1780-\u17ff]")

_TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<(?:svg|math)\b(?:[^\"'>]++|\"[^\"]*\"|'[^']*')*+(?<=/)>|<(?P<raw>" + "|".join(RAW) + r")\b(?:[^\"'>]++|\"[^\"]*\"|'[^']*')*+>.*?(?:</(?P=raw)\s*+[^>]*>|\Z)"
    r"|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<rest>(?:[^\"'>]++|\"[^\"]*\"|'[^']*')*+)>|<(?P<loose_end>/?)(?P<loose_name>[a-zA-Z][^\s/>]*)(?P<loose_rest>[^>]*)>|<[!?/][^>]*>",
    re.S | re.I,
)
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|/|$)|display\s*:\s*none", re.I)
_NAME_PARTS = re.compile(r"[a-z]+")


@dataclass
class Block:
    text: str
    link_chars: int
    region: str  # "main", "aside" (by kind), "marked" (by class) or "page"
    label: str = ""


def _words(value: str) -> set[str]:
    """What may mark an element: each token of a class as a whole, its first and its last part; nothing of a state."""
    out: set[str] = set()
    for token in re.sub(r"([a-z])([A-Z])", r"\1-\2", value).lower().split():
        parts = _NAME_PARTS.findall(token)
        if parts and not STATES & set(parts):
            out |= {token, parts[0], parts[-1]}
    return out


def _marked(name: str, rest: str, inside_main: bool) -> tuple[bool, bool]:
    """Whether the element is marked by what it is, or hidden; and whether by its class, id or role."""
    if name in ASIDE or (name == "header" and not inside_main):
        return True, False
    if not rest or name in ("html", "body") or name in MAIN:
        return False, False
    if _HIDDEN.search(rest):
        return True, False
    for _, value in _ATTRIBUTE.findall(rest):
        words = _words(value.strip("\"'"))
        if words & MARKS or (not inside_main and words & HEADER):
            return False, True
    return False, False


def blocks(html: str) -> list[Block]:
    """Blocks of visible text in page order."""
    out: list[Block] = []
    stack: list[tuple[str, int, int, int, int]] = []  # name, and how often main, aside, marked, link are open
    main = aside = marked = link = 0
    found_main = False
    parts: list[str] = []
    linked = 0
    at = 0

    def flush() -> None:
        nonlocal parts, linked
        if parts:
            text = " ".join("".join(parts).split())
            if text:
                out.append(Block(text, linked, "aside" if aside else "marked" if marked else "main" if main else "page"))
        parts, linked = [], 0

    def say(text: str) -> None:
        nonlocal linked
        if text:
            text = unescape(text)
            parts.append(text)
            if link:
                linked += len(text.strip())

    def pop(to: int) -> None:
        nonlocal main, aside, marked, link
        if any(x[0] in BLOCK for x in stack[to:]):
            flush()
        _, main, aside, marked, link = stack[to]
        del stack[to:]

    for m in _TAG.finditer(html):
        say(html[at : m.start()])
        at = m.end()
        name = m["name"] or m["loose_name"]
        if m["raw"] and name is None:
            parts.append(" ")
            continue
        if name is None:
            continue
        name = name.lower()
        if m["end"] or m["loose_end"]:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == name:
                    pop(i)
                    break
                if stack[i][0] in MAIN and name not in ("body", "html"):
                    break
            else:
                if name in BLOCK:
                    flush()
            continue
        if name in VOID:
            flush() if name == "hr" else parts.append(" ")
            continue
        shut = IMPLIED.get(name, set())
        if name in BLOCK:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == "p" or stack[i][0] in shut:
                    pop(i)
                    break
                if stack[i][0] in ("ul", "ol", "dl", "table", "div", "section", "article", "main", "body"):
                    break
            flush()
        if (m["rest"] or m["loose_rest"] or "").endswith("/") and name not in BLOCK and name != "a":
            continue
        stack.append((name, main, aside, marked, link))
        rest = m["rest"] or m["loose_rest"] or ""
        by_kind, by_class = _marked(name, rest, bool(main))
        aside += by_kind
        marked += by_class
        if name in MAIN or "articlebody" in rest.lower() or 'role="main"' in rest.lower():
            main += 1
            if not aside and (not marked or not found_main):
                # The class of what holds the article does not count; cards beside a found one stay marked.
                marked, found_main = 0, True
        link += name == "a"
    say(html[at:])
    flush()
    return out


def link_density(b: Block) -> float:
    return b.link_chars / max(1, len(b.text))


def size_of(b: Block) -> int:
    return len(b.text) + 2 * len(_DENSE.findall(b.text))


def _stops(b: Block) -> tuple[int, int]:
    words = b.text.lower().split()
    return sum(w.strip(".,;:!?\"'()") in STOP_WORDS for w in words), len(words)


def listed_language(found: list[Block]) -> bool:
    """Whether the long blocks of the page, links left out, are in a language whose stop words are listed."""
    counts = [_stops(b) for b in found if size_of(b) >= SHORT and link_density(b) <= LINK_BAD]
    return sum(c for c, _ in counts) >= LISTED * max(1, sum(n for _, n in counts))


def menus(found: list[Block]) -> set[int]:
    """Places of the blocks that stand in runs of ``MENU`` or more blocks that are all link."""
    out: set[int] = set()
    run: list[int] = []
    for i, b in enumerate([*found, Block("", 0, "")]):
        if b.text and link_density(b) > LINK_MAIN_BAD and (not run or found[run[-1]].region == b.region):
            run.append(i)
            continue
        out |= set(run) if len(run) >= MENU else set()
        run = [i] if b.text and link_density(b) > LINK_MAIN_BAD else []
    return out


def main_counts(found: list[Block]) -> bool:
    """Whether what is tagged as the article holds the page's text: not if it is less than a short block beside much open text."""
    inside = sum(size_of(b) for b in found if b.region == "main")
    prose = sum(size_of(b) for b in found if b.region == "page" and size_of(b) >= LONG and link_density(b) <= LINK_BAD)
    return inside > 0 and (inside >= SHORT or prose < 3 * LONG)


def first_labels(found: list[Block]) -> None:
    """Pass one: good, bad, or ambiguous (empty)."""
    has_main, listed, menu = main_counts(found), listed_language(found), menus(found)
    for i, b in enumerate(found):
        density, size = link_density(b), size_of(b)
        hits, n = _stops(b)
        stop = hits / max(1, n) if listed else 1.0
        if b.region in ("aside", "marked") or i in menu or (has_main and b.region == "page"):
            b.label = "bad"
        elif b.region == "main" and has_main:
            b.label = "bad" if density > LINK_MAIN_BAD and size > SHORT else "good" if size >= SHORT and stop >= STOP_LOW else ""
        elif density > LINK_BAD:
            b.label = "bad"
        elif size < SHORT:
            b.label = ""
        elif stop >= STOP_HIGH and size >= LONG:
            b.label = "good"
        else:
            b.label = "" if stop >= STOP_LOW else "bad"


def second_labels(found: list[Block]) -> None:
    """Pass two: ambiguous blocks inherit from the nearest decided neighbours of their region."""
    n = len(found)
    near: list[list[tuple[int, str] | None]] = [[None, None] for _ in range(n)]
    for side, order in ((0, range(n)), (1, range(n - 1, -1, -1))):
        last: dict[str, tuple[int, str]] = {}
        for i in order:
            b = found[i]
            if b.label:
                last[b.region] = (i, b.label)
            else:
                near[i][side] = last.get(b.region)
    for i, b in enumerate(found):
        if not b.label:
            sides = [(abs(i - s[0]), s[1] != "good", s[1]) for s in near[i] if s]
            b.label = min(sides)[2] if sides else "good" if b.region == "main" else "bad"


def label(found: list[Block]) -> None:
    if not main_counts(found):
        for b in found:
            b.region = "page" if b.region == "main" else b.region
    first_labels(found)
    second_labels(found)
    if not any(b.label == "good" for b in found) and any(b.region == "marked" for b in found):
        # A class alone is no reason to leave a page without its text.
        for b in found:
            b.region, b.label = "page" if b.region == "marked" else b.region, ""
        first_labels(found)
        second_labels(found)


def main_text(html: str | None) -> str:
    """Text blocks of the article, one a line."""
    found = blocks(html or "")
    label(found)
    return "\n".join(b.text for b in found if b.label == "good")


def extract(pages: DataFrame, html: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """``keep``, ``text`` and its length ``n_chars`` of every page."""
    rows = pages.select(*keep, F.col(html).alias("_html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py()) for x in batch.column(len(keep))]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*keep, "text", "n_chars"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema), "text string, n_chars long"])
    return shipped(rows).mapInArrow(run, schema)
