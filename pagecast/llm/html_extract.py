"""Main text of web pages by two passes of block rules.

A page is cut into blocks at its block-level tags. The first pass looks at each
block by itself: the share of stop words, the length and the share of link text
make it good, bad, nearly good or short. The second pass settles the undecided
ones from the nearest decided neighbours on both sides. The page's own markup
takes part as evidence that needs no context: text inside menus, headers,
footers, sidebars, forms, adverts, notices and comment sections is bad, text in
an article or main element counts as near good text, and headings follow the
text below them. Nothing is cut to a length.
"""

from __future__ import annotations

import html as htmllib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from pagecast.cluster import ship
from pagecast.llm.words import strings

#: Fixed word lists: function words of the languages in view.
STOP_WORDS = frozenset(
    """
    a an and are as at be but by for from had has have he her his i if in is it its not of on or she so that the their
    there they this to was we were which will with would you
    aber als am an auch auf aus bei das dass dem den der des die durch ein eine einem einen einer eines er es für hat
    ich im in ist mit nach nicht noch nur oder sich sie sind so um und von war werden wie wird zu zum zur über
    au aux avec ce ces cette dans de des du elle en est et il ils je la le les leur mais ne nous on ou où par pas plus
    pour qu que qui sa se ses son sont sur un une vous à être
    al como con cuando de del desde el ella en entre era es esta este están fue ha hay la las lo los más muy no nos o
    para pero por que se ser si sin sobre son su sus también un una uno y ya él
    """.split()
)
_BLOCK = frozenset(
    """
    address article aside blockquote body caption center col colgroup dd details dialog dir div dl dt fieldset figcaption
    figure footer form frame h1 h2 h3 h4 h5 h6 head header hgroup hr html iframe legend li main menu nav noscript ol
    optgroup option p pre search section select summary table tbody td template tfoot th thead title tr ul
    """.split()
)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is never text of the page.
_RAW = frozenset("script style noscript template svg math iframe object textarea title select".split())
_BOILER = frozenset("nav header footer aside form button menu dialog fieldset".split())
_HEADING = frozenset("h1 h2 h3 h4 h5 h6".split())
_CORE = frozenset("article main".split())
#: Elements that an opening tag of the same kind, or of a block, closes.
_CLOSED_BY_SELF = frozenset("p li dt dd td th tr option".split())
_BOILER_NAME = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisements?|advertising|sponsor(?:ed)?|promo(?:tion)?s?|banner|cookies?|consent|gdpr|notices?|popup|modal|overlay"
    r"|nav(?:bar|igation)?|menu|breadcrumbs?|header|masthead|footer|foot|side-?bars?|widgets?|related|recommend(?:ed|ations)?|share|sharing|social"
    r"|comments?|commentlist|comment-list|respond|replies|disqus|newsletter|subscribe|subscription|signup|login|search|pagination|pager|toolbar|skip-link|legal|copyright|disclaimer)(?=$|[\s_-])",
    re.IGNORECASE,
)
_BOILER_ROLE = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar toolbar".split())
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)(?:>|\Z)", re.DOTALL)
_ATTRIBUTE = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.IGNORECASE)
_SPACE = re.compile(r"\s+")

GOOD, BAD, SHORT, NEAR = "good", "bad", "short", "near good"
LENGTH_LOW, LENGTH_HIGH = 70, 140
STOP_LOW, STOP_HIGH = 0.10, 0.20
LINKS_HIGH = 0.5


def _boilerplate(name: str, attributes: str) -> bool:
    if name in _BOILER:
        return True
    if not attributes or name in ("html", "body", "main", "article"):
        return False
    for key, value in _ATTRIBUTE.findall(attributes):
        key, value = key.lower(), value.strip("\"'")
        if key in ("class", "id") and _BOILER_NAME.search(value):
            return True
        if key == "role" and value.lower() in _BOILER_ROLE:
            return True
        if key == "hidden" or key == "aria-hidden" and value.lower() == "true":
            return True
        if key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.IGNORECASE):
            return True
    return False


class _Page:
    """Blocks of one page: (text, link characters, tag, in boilerplate, in core)."""

    def __init__(self, source: str):
        self.blocks: list[tuple[str, int, str, bool, bool]] = []
        self.open: list[tuple[str, bool]] = []
        self.parts: list[str] = []
        self.link_chars = self.in_link = self.bad = self.core = 0
        self.tag = ""
        at = 0
        for token in _TOKEN.finditer(source):
            begin = token.start()
            if begin < at:
                continue
            self._text(source[at:begin])
            at = token.end()
            name = (token[2] or "").lower()
            if not name:
                continue
            if token[1]:
                self._close(name)
            elif name in _RAW:
                end = re.compile(rf"</{re.escape(name)}\s*>", re.IGNORECASE).search(source, at)
                at = end.end() if end else len(source)
                if name in _BLOCK:
                    self._end_block()
            else:
                self._start(name, token[3] or "")
        self._text(source[at:])
        self._end_block()

    def _text(self, raw: str) -> None:
        if raw:
            self.parts.append(raw)
            if self.in_link:
                self.link_chars += len(raw.strip())

    def _end_block(self) -> None:
        if self.parts:
            text = _SPACE.sub(" ", htmllib.unescape("".join(self.parts))).strip()
            if text:
                self.blocks.append((text, self.link_chars, self.tag, self.bad > 0, self.core > 0))
        self.parts, self.link_chars = [], 0

    def _start(self, name: str, attributes: str) -> None:
        if name == "br":
            self.parts.append(" ")
            return
        if name in _BLOCK:
            self._end_block()
            if any(n == "p" for n, _ in self.open[-4:]):
                self._close("p")
            if name in _CLOSED_BY_SELF and self.open and self.open[-1][0] == name:
                self._close(name)
            self.tag = name
        if name in _VOID or attributes.rstrip().endswith("/"):
            return
        boiler = _boilerplate(name, attributes)
        self.open.append((name, boiler))
        self.bad += boiler
        self.core += name in _CORE
        self.in_link += name == "a"

    def _close(self, name: str) -> None:
        if name in _BLOCK:
            self._end_block()
        if not any(n == name for n, _ in self.open):
            return
        # an inline end tag does not close the block around it
        if name not in _BLOCK:
            for k in range(len(self.open) - 1, -1, -1):
                if self.open[k][0] == name:
                    self._forget(self.open.pop(k))
                    return
                if self.open[k][0] in _BLOCK:
                    break
        while self.open:
            top = self.open.pop()
            self._forget(top)
            if top[0] == name:
                return

    def _forget(self, element: tuple[str, bool]) -> None:
        name, boiler = element
        self.bad -= boiler
        self.core -= name in _CORE
        self.in_link -= name == "a"


def first_pass(text: str, link_chars: int, tag: str, boiler: bool, core: bool) -> str:
    """The class of a block by itself."""
    if boiler:
        return BAD
    if link_chars > LINKS_HIGH * len(text):
        return BAD
    words = text.lower().split()
    stops = sum(w.strip(".,;:!?\"'()*#$%&") in STOP_WORDS for w in words) / len(words)
    if len(text) < LENGTH_LOW:
        return SHORT
    if stops >= STOP_HIGH:
        return GOOD if len(text) > LENGTH_HIGH or core else NEAR
    if stops >= STOP_LOW:
        return NEAR
    # the page's author marked it as main text: too little to call it bad
    return NEAR if core else BAD


def second_pass(kinds: list[str], cores: list[bool], headings: list[bool]) -> list[bool]:
    """Settle the undecided blocks from their nearest decided neighbours."""
    n = len(kinds)
    before, after = [BAD] * n, [BAD] * n
    last = BAD
    for i in range(n):
        before[i] = last
        if kinds[i] in (GOOD, BAD):
            last = kinds[i]
    last = BAD
    for i in range(n - 1, -1, -1):
        after[i] = last
        if kinds[i] in (GOOD, BAD):
            last = kinds[i]
    out = []
    for i, kind in enumerate(kinds):
        if kind == GOOD:
            out.append(True)
        elif kind == BAD:
            out.append(False)
        elif cores[i]:
            # inside the article the border to the page's frame is no neighbour
            out.append(True)
        elif headings[i]:
            out.append(after[i] == GOOD)
        elif before[i] == after[i]:
            out.append(before[i] == GOOD)
        else:
            out.append(kind == NEAR)
    return out


def main_text(source: str | None) -> str:
    """The page's main blocks in page order, one on each line."""
    if not source:
        return ""
    blocks = _Page(source).blocks
    if not blocks:
        return ""
    kinds = [first_pass(*b) for b in blocks]
    if GOOD not in kinds:  # a page of short paragraphs: its best blocks decide
        kinds = [GOOD if k == NEAR else k for k in kinds]
    keep = second_pass(kinds, [b[4] for b in blocks], [b[2] in _HEADING for b in blocks])
    return "\n".join(b[0] for b, k in zip(blocks, keep) if k)


def extract(df: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per input row: id, url, text, n_chars (code points).

    Null, empty and text-free pages give an empty text; broken markup is read
    as far as it goes; repeated rows give repeated results. Only the three
    named columns are read.
    """
    ship(df.sparkSession)
    types = {c: df.schema[c].dataType.simpleString() for c in (id_col, url_col)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(h) for h in strings(batch.column(2))]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                [id_col, url_col, "text", "n_chars"],
            )

    return df.select(id_col, url_col, html_col).mapInArrow(run, f"{id_col} {types[id_col]}, {url_col} {types[url_col]}, text string, n_chars bigint")
