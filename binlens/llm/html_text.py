"""Main text of raw web pages by two-pass block rules.

A page is cut into blocks at block-level tags.  Pass one decides a block by link density, by structure (inside a menu,
header, footer, form, advert, comment section, ... or beside the page's article it is boilerplate), and by length and
stop-word density: long running text is main text.  What is short or poor in stop words stays open, inside an article
too.  Pass two gives each open block the label of its nearest decided neighbours: if they differ, the nearer one's, and
on a tie the one before, or for a heading the one after.  All steps are linear in the page.
"""

from __future__ import annotations

import html
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import narrow

SCHEMA = "page_id long, url string, text string, n_chars long"

#: Stop words, fixed values.
STOP = frozenset(
    "the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which you were her all she there would their "
    "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei einer um am sind noch wie "
    "de la le et les des en un du une que est pour qui dans a par plus pas au sur ne se ce il sont avec son cette ou "
    "que el y los del se las por un para con no una su al lo como más pero sus le ya o este sí porque esta entre cuando".split()
)
BLOCK_TAGS = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 "
    "h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul".split())
RAW_TAGS = frozenset("script style noscript template iframe object svg math textarea canvas".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CHROME_TAGS = frozenset("head nav header footer aside form menu dialog button select title".split())
CONTENT_TAGS = frozenset("article main".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
CHROME_WORDS = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo banner nav navbar navigation menu sidebar footer header masthead "
        "breadcrumb breadcrumbs cookie cookies consent notice "
    "gdpr popup modal overlay newsletter subscribe signup login social share sharing related recommended comments comment respond disqus reply "
        "replies copyright legal widget toolbar pagination pager skip".split()
)
#: First parts of class names that say something about the page, not what the element is.
MODIFIERS = frozenset("has no with without is not show hide open enable enabled disable disabled".split())
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^<>]*+>|<(/?)([a-zA-Z][^\s/><]*+)((?:[^<>\"']|\"[^\"]*+\"|'[^']*+')*+)>", re.S)
_ATTR = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
_PART = re.compile(r"[^a-z0-9]+")
_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
_WHOLE = frozenset("html body article main".split())


class Block:
    __slots__ = ("parts", "linked", "chrome", "content", "heading")

    def __init__(self, chrome: bool, content: bool, heading: bool = False):
        self.parts: list[str] = []
        self.linked, self.heading = 0, heading
        self.chrome, self.content = chrome, content


def _names_chrome(name: str, content: bool) -> bool:
    """Whether a class or id says that its element is boilerplate: by its whole, its first or its last part
    ("cookie-notice", "site-footer"), but not as a remark ("has-sidebar"); headings of an article aren't."""
    parts = [p for p in _PART.split(name) if p]
    if not parts or parts[0] in MODIFIERS:
        return False
    hits = {p for p in (parts[0], parts[-1]) if p in CHROME_WORDS}
    return bool(hits - {"header", "masthead"} if content else hits)


def _is_chrome(tag: str, attrs: str, content: bool) -> bool:
    if tag in CHROME_TAGS and not (content and tag == "header"):
        return True
    if not attrs:
        return False
    if tag not in _WHOLE:
        for kind, a, b, c in _ATTR.findall(attrs):
            value = (a or b or c).lower()
            if kind.lower() == "role":
                if value.strip() in _ROLES:
                    return True
            elif any(_names_chrome(name, content) for name in value.split()):
                return True
    return "hidden" in attrs.lower().split()


def blocks(page: str) -> list[tuple[str, float, bool, bool, bool]]:
    """(text, link density, in chrome, in a content element, heading) of each non-empty block in page order."""
    out: list[Block] = []
    current = Block(False, False)
    stack: list[tuple[str, bool, bool]] = []  # open elements: tag, chrome, content
    opened: Counter[str] = Counter()  # how many of each tag are on the stack
    chrome = content = False
    links, at, end = 0, 0, len(page)

    def shut() -> str:
        tag = stack.pop()[0]
        opened[tag] -= 1
        return tag

    def turn() -> None:
        nonlocal current
        if current.parts:
            out.append(current)
        current = Block(chrome, content, bool(stack) and stack[-1][0] in HEADINGS)

    def say(text: str) -> None:
        if text:
            current.parts.append(text)
            if links:
                current.linked += len("".join(text.split()))

    while at < end:
        m = _TOKEN.search(page, at)
        if not m:
            say(page[at:])
            break
        say(page[at : m.start()])
        at = m.end()
        tag = m[2].lower() if m[2] else ""
        if not tag:
            continue
        if m[1]:
            if tag == "a":
                links = max(0, links - 1)
            if opened[tag]:
                while shut() != tag:
                    pass
                was = (chrome, content)
                chrome, content = (stack[-1][1], stack[-1][2]) if stack else (False, False)
                if tag in BLOCK_TAGS or was != (chrome, content):
                    turn()
            elif tag in BLOCK_TAGS:
                turn()
            continue
        attrs = m[3] or ""
        if tag in RAW_TAGS and not attrs.rstrip().endswith("/"):
            close = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
            at = close.end() if close else end
            continue
        if tag in VOID_TAGS:
            if tag == "br":
                say(" ")
            elif tag in BLOCK_TAGS:
                turn()
            continue
        if tag == "a":
            links += 1
        bad = _is_chrome(tag, attrs, content)
        if tag in BLOCK_TAGS or bad or tag in CONTENT_TAGS:
            if tag == "p" and opened["p"]:  # a paragraph ends an open one
                while stack and stack[-1][0] not in BLOCK_TAGS:
                    shut()
                if stack and stack[-1][0] == "p":
                    shut()
                chrome, content = (stack[-1][1], stack[-1][2]) if stack else (False, False)
                links = 0
            stack.append((tag, chrome or bad, content or tag in CONTENT_TAGS))
            chrome, content = stack[-1][1], stack[-1][2]
            turn()
        else:
            stack.append((tag, chrome, content))
        opened[tag] += 1
    turn()
    made = []
    for b in out:
        text = " ".join(html.unescape("".join(b.parts)).split())
        if text:
            size = len(text.replace(" ", ""))
            made.append((text, min(1.0, b.linked / size) if size else 0.0, b.chrome, b.content, b.heading))
    return made


def decide(found: list[tuple[str, float, bool, bool, bool]], most_links: float = 0.4, short: int = 70, dense: float = 0.2) -> list[tuple[bool, str]]:
    """Whether each block is main text, and what said so: "links", "structure", "text" (pass one), "neighbours" (pass
    two) or "alone" (no decided block to go by: main text if in an article)."""
    inside = any(content and not chrome for _, _, chrome, content, _ in found)
    first: list[tuple[bool, str] | None] = []
    for text, links, chrome, content, _ in found:
        if links > most_links:
            first.append((False, "links"))
        elif chrome or (inside and not content):
            first.append((False, "structure"))
        elif len(text) >= short and _stop_share(text) >= dense:
            first.append((True, "text"))
        else:
            first.append(None)
    # chrome and links between the parts of an article don't speak for it
    speaks = [[x is not None for x in first], [x is not None and x[1] == "text" for x in first]]
    before, after = ([_nearest(mask, back) for mask in speaks] for back in (False, True))
    out = []
    for k, x in enumerate(first):
        if x is None:
            content, heading = found[k][3:]
            i, j = before[content][k], after[content][k]
            if i is None and j is None:
                x = (content, "alone")
            elif i is None or (j is not None and j - k < k - i + heading):
                x = (first[j][0], "neighbours")
            else:
                x = (first[i][0], "neighbours")
        out.append(x)
    return out


def _stop_share(text: str) -> float:
    tokens = text.lower().split()
    return sum(t.strip(".,;:!?\"'()") in STOP for t in tokens) / len(tokens)


def _nearest(mask: list[bool], back: bool) -> list[int | None]:
    """For each place the nearest marked one before it (or, from the back, after it), by one sweep."""
    out: list[int | None] = [None] * len(mask)
    last = None
    for k in range(len(mask) - 1, -1, -1) if back else range(len(mask)):
        out[k] = last
        if mask[k]:
            last = k
    return out


def main_text(page: str | None) -> str:
    found = blocks(page or "")
    return "\n".join(text for (text, *_), keep in zip(found, (x for x, _ in decide(found))) if keep)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page.  Null and empty pages have empty text; repeated rows repeat; other
    columns are not read; an empty table gives no rows."""

    def run(batches):
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                texts = [main_text(t) for t in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts],
                    pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return narrow(rows, run, SCHEMA)
