"""Main text of web pages by line-block distribution.

Markup is stripped into lines, one per block element. A line's mass is the length of its
text outside links. Sums of masses over sliding windows of ``WINDOW`` lines rise over the
threshold at a surge point and fall below it at a dive point; the text between a surge and
its dive is kept, and short plain lines at both ends of it (menus that carry no markup) are
trimmed. The threshold is ``SURGE`` characters, or less on pages whose fullest window is small.

Markup helps in three ways. Elements that are never article text by their tag, role or an
unmistakable class name (nav, footer, form, script, comments, ads) are stripped like markup.
Lines of ``article`` or ``main``, where they hold a good part of the page's mass, count
as full windows of their own, and the other lines as none. Blocks whose class or id says
nothing but a word like "related" or "share" form a distribution of their own: they are
kept only between its surge and dive points, which link lists and one-line boxes
never reach. A class name with any other word in it ("related-work") says nothing.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame

#: Elements that start a new line; that never hold text; that never close;
#: whose content is not text; that are never part of an article.
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure "
    "footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol optgroup option p pre section "
    "summary table tbody td tfoot th thead title tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template svg math iframe object canvas textarea xmp noembed noframes title".split())
BOILERPLATE = frozenset(
    "head nav footer aside form menu dialog button select label input fieldset audio video map".split()
)
ROLES = frozenset(
    "navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar note".split()
)
#: Words of class names and ids: those that name boilerplate, those that may, and those that say nothing
#: beside one of them.
NAMED = frozenset(
    "ad ads adv advert adverts advertisement advertisements advertising adsense adslot sponsor sponsors sponsored cookie cookies "
    "consent gdpr popup modal newsletter subscribe nav navbar navigation menu menus submenu breadcrumb breadcrumbs sidebar "
    "sidebars footer masthead comment comments commentlist disqus respond replies pagination pager paywall".split()
)
DOUBTFUL = frozenset(
    "notice notices notification alert alerts promo promos promotion banner banners overlay widget widgets header toolbar share "
    "sharing social related recommended recommendations reply signup login copyright legal teaser teasers".split()
)
NEUTRAL = frozenset(
    "site page main global top bottom left right primary secondary bar box list block container wrapper wrap area section links "
    "link item items panel inner outer slot unit post posts entry article articles blog content text group row col module".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
HOLD = frozenset(("main", "body", "html"))
#: Elements whose end tag may be missing: the next of the same group ends them, as any block ends p.
OPEN = {"p": "p", "li": "li", "dt": "dt dd", "dd": "dt dd", "tr": "tr td th", "td": "td th", "th": "td th", "option": "option"}
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)>", re.S)
ATTRIBUTE = re.compile(r"([a-zA-Z_:][\w:.-]*)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'=<>`]+)))?")
SPACE = re.compile(r"\s+")
PARTS = re.compile(r"[-_0-9]+|(?<=[a-z])(?=[A-Z])")
#: Lines of one window of the distribution; the mass at which it surges, as a share of the
#: fullest window at most; the mass for doubtful blocks; share of the page's mass that ``article``
#: or ``main`` must hold to count; plain lines shorter than this are trimmed at the ends of a run.
WINDOW = 3
SURGE, SHARE = 80, 0.25
DOUBT = 240
MARKED = 1 / 3
SHORT = 25
CLEAN, MAYBE, NEVER = 0, 1, 2


class Line(NamedTuple):
    text: str
    linked: int
    kind: int
    main: bool
    heading: bool


def named(value: str) -> int:
    """What the words of a class or id attribute say of its element: CLEAN, MAYBE or NEVER text."""
    worst = CLEAN
    for token in value.split():
        words = [w.lower() for w in PARTS.split(token) if w]
        if any(w not in NAMED and w not in DOUBTFUL and w not in NEUTRAL for w in words):
            continue
        if any(w in NAMED for w in words):
            return NEVER
        if any(w in DOUBTFUL for w in words):
            worst = MAYBE
    return worst


def boilerplate(tag: str, attributes: str, in_main: bool) -> int:
    """CLEAN, MAYBE or NEVER, from an element's tag and attributes."""
    if tag in BOILERPLATE or tag == "header" and not in_main:
        return NEVER
    if not attributes or tag in HOLD or tag == "article" and not in_main or "=" not in attributes and "hidden" not in attributes:
        return CLEAN
    worst = CLEAN
    for name, a, b, c in ATTRIBUTE.findall(attributes):
        name, value = name.lower(), a or b or c
        if name in ("class", "id"):
            worst = max(worst, named(value))
        elif name == "role" and value.lower() in ROLES or name == "hidden" or name == "aria-hidden" and value == "true":
            return NEVER
        elif name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            return NEVER
    return worst


def lines(page: str) -> Iterator[Line]:
    """The page's blocks in order; inline markup vanishes and br is white space."""
    stack: list[tuple[str, int, bool, bool]] = []  # tag, kind, main, heading: of the element or above it
    parts: list[str] = []
    linked = anchors = 0
    kind, main, heading = CLEAN, False, False
    at, end = 0, len(page)

    def flush() -> Iterator[Line]:
        nonlocal parts, linked
        text = SPACE.sub(" ", html.unescape("".join(parts))).strip()
        if text:
            yield Line(text, min(linked, len(text)), kind, main, heading)
        parts, linked = [], 0

    while at < end:
        m = TOKEN.search(page, at)
        if m is None:
            parts.append(page[at:])
            break
        if m.start() > at:
            parts.append(page[at : m.start()])
            if anchors:
                linked += m.start() - at
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            if tag == "a":
                anchors = max(0, anchors - 1)
            if tag in BLOCKS:
                yield from flush()
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == tag:
                    del stack[i:]
                    break
                if stack[i][0] in ("article", "main", "body") and tag not in BLOCKS:
                    break  # a stray end tag of inline markup closes nothing above
            _, kind, main, heading = stack[-1] if stack else ("", CLEAN, False, False)
            continue
        if tag in RAW:
            close = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            if not m[3].endswith("/"):
                at = close.end() if close else end
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag == "a":
            anchors += 1
        if tag in BLOCKS:
            yield from flush()
            ended = ("p", *OPEN.get(tag, "").split())
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] in ended:
                    del stack[i:]
                elif stack[i][0] in BLOCKS and stack[i][0] not in OPEN:
                    break
            _, kind, main, heading = stack[-1] if stack else ("", CLEAN, False, False)
        if tag not in VOID and not m[3].endswith("/"):
            kind = max(kind, boilerplate(tag, m[3], main))
            main = main or tag in ("article", "main")
            heading = heading or tag in HEADINGS
            stack.append((tag, kind, main, heading))
    yield from flush()


def runs(masses: list[float], threshold: float, window: int = WINDOW) -> list[tuple[int, int]]:
    """Half-open line ranges between a surge and its dive.

    The block value of a line is the sum of masses over the window of lines from it. A run
    surges at a line whose value reaches the threshold and dives after the last line of its
    last such window; both ends are then moved to lines that have mass. Without any
    mass there is no run.
    """
    n, out = len(masses), []
    value = sum(masses[:window])
    for i in range(n):
        if value >= threshold and value > 0:
            last = min(n, i + window)
            if out and out[-1][1] > i:
                out[-1][1] = last
            else:
                out.append([i, last])
        value += (masses[i + window] if i + window < n else 0) - masses[i]
    trimmed = []
    for a, b in out:
        while a < b and not masses[a]:
            a += 1
        while b > a and not masses[b - 1]:
            b -= 1
        if a < b:
            trimmed.append((a, b))
    return trimmed


def edge(line: Line) -> bool:
    """Whether a line at the end of a run is too slight to be text: short, no heading and no sentence."""
    return len(line.text) < SHORT and not line.heading and line.text[-1] not in ".!?:;…。！？\"'”’»)"


def kept_lines(found: list[Line]) -> list[int]:
    """Indices of the lines of the main text, in page order."""
    own = [len(x.text) - x.linked if x.kind == CLEAN else 0 for x in found]
    in_main = sum(m for m, x in zip(own, found, strict=True) if x.main)
    marked = any(x.main and x.kind == CLEAN for x in found) and in_main >= MARKED * sum(own)
    if marked:
        masses = [SURGE if x.main and x.kind == CLEAN else 0 for x in found]
        threshold = SURGE
    else:
        masses = own
        fullest = max((sum(masses[i : i + WINDOW]) for i in range(len(masses))), default=0)
        threshold = min(SURGE, SHARE * fullest)
    keep = set()
    for a, b in runs(masses, threshold):
        if not marked:
            while a < b and edge(found[a]) and len(found[a].text) < SHARE * fullest:
                a += 1
            while b > a and edge(found[b - 1]) and len(found[b - 1].text) < SHARE * fullest:
                b -= 1
        # lines of links inside a run belong to it; stripped, doubtful and outer ones do not
        keep.update(i for i in range(a, b) if found[i].kind == CLEAN and (found[i].main or not marked))
    doubtful = [len(x.text) - x.linked if x.kind == MAYBE and (x.main or not marked) else 0 for x in found]
    for a, b in runs(doubtful, DOUBT):
        keep.update(i for i in range(a, b) if doubtful[i])
    return sorted(keep)


def main_text(page: str | None) -> str:
    """The blocks of the main text, joined by an empty line; empty where a page has none."""
    if not page:
        return ""
    found = list(lines(page))
    return "\n\n".join(found[i].text for i in kept_lines(found))


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page; a null or empty html gives empty text.

    Repeated rows give repeated results, an empty table an empty one; other columns are ignored.
    Pages are read whole, one at a time, whatever their length.
    """
    schema = "page_id long, url string, text string, n_chars long"

    def run(batches):
        for batch in batches:
            texts = [main_text(h.as_py()) for h in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                names=["page_id", "url", "text", "n_chars"],
            )

    return pages.select("page_id", "url", "html").mapInArrow(run, schema)
