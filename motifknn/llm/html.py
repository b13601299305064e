"""Main-text extraction by two-pass block rules.

One scan turns a page into blocks: runs of text between block-level tags, each with its words, its linked
characters and the containers it stands in. Pass one decides a block by its text: link density, length and the
density of frequent function words make it good or bad; short blocks and those of middling density stay open.
What the mark-up states outright goes before that: a menu, footer, aside, form or dialog element, or a class,
id or role that names an advert, notice, sidebar, comments and the like, is bad.

Then the article element, if there is one, is weighed against the rest by pass one's own figures: where its blocks
hold no less good text than those outside, blocks outside are bad, and bad ones inside are open again unless they
are mostly links. Pass two gives each open block the label of its nearest decided neighbours: good if both sides
are good; if they differ, that of the nearer one, ties to good; a block with no decided neighbour is good inside an
article and bad outside.

A class token names boilerplate if it is one of the words itself ("sidebar") or is made of them with other
words ("site-footer"); tokens that tell a state of the page ("has-sidebar", "search-enabled") do not, and
where an article or main element starts, only whole words still count. Character references are decoded, white
space inside a block becomes one space, blocks are joined by one line feed in page order.

The scan is linear in the page: a tag ends at ">" or before the next "<", and a quoted value may hold either
only if its closing quote is where one can be. Links end with their block.

Defined results: null or empty html gives an empty text; unclosed or stray tags and quotes are tolerated; a page
of plain text is one block (kept). Repeated rows are extracted each; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

TOKEN = re.compile(r"""<!--(?:-?>|.*?(?:--!?>|\Z))|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</?[A-Za-z](?:[^<>"'=]|=\s*+(?:"[^"<>]*"|'[^'<>]*'|"[^"]{0,300}"(?=[\s/>])|'[^']{0,300}'(?=[\s/>])|)|["'])*+(?:>|(?=<)|\Z)""", re.S)
TAG = re.compile(r"<(/?)([A-Za-z][A-Za-z0-9:-]*)")
NAMED = re.compile(r"""\b(?:class|id|role|aria-label)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
HIDDEN = re.compile(r"""\bhidden\b(?!\s*=\s*["']?false)|aria-hidden\s*=\s*["']?true|display\s*:\s*none|visibility\s*:\s*hidden""", re.I)
QUOTED = re.compile(r""""[^"]*"|'[^']*'""")

#: Their text is never shown or is no text.
SILENT = frozenset("script style noscript template head title svg math iframe object canvas audio video map select textarea button datalist".split())
RAW = frozenset("script style textarea title noscript iframe template".split())
BOILER = frozenset("nav footer aside form dialog menu header".split())
ARTICLE = frozenset("article main".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: A start tag of the key ends an open element of these kinds.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "td": {"td", "th"}, "th": {"td", "th"}, "tr": {"tr", "td", "th"}, "option": {"option"}}
#: Words of class, id and role values that name boilerplate.
MARKS = frozenset("ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored sponsors promo promotion promoted sidebar nav navbar navigation menu menubar breadcrumb breadcrumbs footer masthead cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login comment comments commentlist disqus respond reply replies discussion share sharing social related recommended recommendations teaser outbrain taboola pagination pager toolbar widget complementary contentinfo search skip".split())
#: Frequent function words of a few languages.
STOP = frozenset(
    "the of and to in a is that it for was on as with be by at this from are or an not have which you he they but his "
    "der die das und in zu den mit von ist im dem nicht ein eine auf für als auch es an er sich des sie "
    "le la les de des du et à un une en que qui est pour dans il sur ne pas au par avec ce se "
    "el los las y que en un una por con no para se es del al lo su como más o".split()
)
#: Parts of a class token that tell a state or a layout, not what the element is: before or after the word.
STATE_FIRST = frozenset("has have with without no not is show hide hidden use uses js can page body layout supports enable disable toggle".split())
STATE_LAST = frozenset("enabled disabled open opened closed active inactive on off ready loaded visible hidden left right page layout wrapper".split())
#: Elements that text-level content may leave open; a block ends them.
LEFT_OPEN = frozenset("button select".split())
SHORT, LONG, LINKS, LOW, HIGH = 70, 200, 0.4, 0.12, 0.24
#: Link density that makes a block bad inside the article too.
MOSTLY = 0.66
_WORDS = re.compile(r"[^\W_]+(?:[-_/]?[^\W_]+)*")


@dataclass(slots=True)
class Block:
    text: str
    linked: int
    heading: bool
    inside: bool  # of an article
    marked: bool  # as boilerplate
    label: str = ""


def _token(token: str) -> int:
    """2 if the class token is a word of MARKS, 1 if it is made with one, 0 otherwise."""
    words = [w for w in re.split(r"[^a-z]+", re.sub(r"([a-z])([A-Z])", r"\1 \2", token).lower()) if w]
    if not words or MARKS.isdisjoint(words):
        return 0
    if len(words) > 1 and (words[0] in STATE_FIRST or words[-1] in STATE_LAST):
        return 0
    return 2 if MARKS.issuperset(words) else 1


def _marked(name: str, attrs: str, in_article: bool) -> int:
    """How surely the element is boilerplate: 2 for its name or a whole word, 1 for a part of a token."""
    if name in BOILER:
        return 0 if name == "header" and in_article else 2  # an article's own header has its headline
    return max((_token(t) for m in NAMED.finditer(attrs) for t in next(g for g in (*m.groups(), "") if g is not None).split()), default=0)


def blocks(page: str) -> list[Block]:
    out: list[Block] = []
    stack: list[tuple[str, bool, bool, int]] = []  # name, silent, article, marked
    parts: list[tuple[str, bool]] = []
    heading = False

    def state(i: int) -> int:
        return stack[-1][i] if stack else 0

    def end() -> None:
        nonlocal parts
        text = " ".join(entities.unescape("".join(p for p, _ in parts)).split())
        if text:
            linked = sum(len("".join(entities.unescape(p).split())) for p, a in parts if a)
            out.append(Block(text, linked, heading, bool(state(2)), state(3) > 0))
        parts = []

    at = anchors = 0
    for m in [*TOKEN.finditer(page), None] if page else []:
        start = m.start() if m else len(page)
        if start < at:
            continue  # inside a raw element
        if start > at and not state(1):
            parts.append((page[at:start], anchors > 0))
        if m is None:
            break
        at = m.end()
        tag = TAG.match(m[0])
        if not tag:
            continue
        closing, name = bool(tag[1]), tag[2].lower()
        attrs = m[0][tag.end() :]
        if name in BLOCK:
            end()
            anchors = 0
            if name == "body" or (stack and stack[-1][0] in LEFT_OPEN and not closing):
                while stack and stack[-1][1] and stack[-1][0] in (*LEFT_OPEN, "head"):
                    stack.pop()
            heading = not closing and name in ("h1", "h2", "h3", "h4", "h5", "h6")
        elif name == "br":
            parts.append((" ", False))
        if name == "a":
            anchors = 0 if closing else 1
        if closing:
            found = next((k for k in range(len(stack) - 1, -1, -1) if stack[k][0] == name), None)
            if found is not None:
                del stack[found:]
        elif name not in VOID and not attrs.rstrip(">").endswith("/"):
            if name in CLOSES and stack and stack[-1][0] in CLOSES[name]:
                stack.pop()
            if name in BLOCK or name in SILENT or name in BOILER or "=" in attrs or "hidden" in attrs:
                hidden = name in SILENT or bool(HIDDEN.search(attrs if "style" in attrs.lower() else QUOTED.sub('"true"' if "aria-hidden" in attrs.lower() else '""', attrs)))
                article = state(2) or name in ARTICLE
                if name not in ("a", "p"):
                    above = state(3) if name not in ARTICLE or state(3) == 2 else 0
                    stack.append((name, bool(state(1)) or hidden, bool(article), max(above, 0 if name in ("html", "body", "article", "main") else _marked(name, attrs, bool(article)))))
            if name in RAW:
                close = re.compile(rf"</{name}\b", re.I).search(page, at)
                at = close.start() if close else len(page)
    end()
    return out


def by_text(b: Block) -> tuple[str, float]:
    """(label, link density) of a block by its text alone."""
    n = len(b.text)
    links = b.linked / max(1, len("".join(b.text.split())))
    if links > LINKS and not b.heading:
        return "bad", links
    if n < SHORT:
        return "open", links
    words = _WORDS.findall(b.text.lower())
    stops = sum(w in STOP for w in words) / max(1, len(words))
    if stops >= HIGH:
        return "good", links
    if stops >= LOW:
        return ("good" if n >= LONG else "open"), links
    return ("bad" if links > 0.1 else "open"), links


def classify(found: list[Block]) -> None:
    """Label every block good or bad."""
    judged = [("bad", 0.0) if b.marked else by_text(b) for b in found]
    size = lambda inside, labels: sum(len(b.text) for b, (label, _) in zip(found, judged, strict=True) if b.inside == inside and not b.marked and label in labels)
    inside, rest = size(True, ("good", "open", "bad")), size(False, ("good",))
    article = inside > 0 and (size(True, ("good",)) >= rest or inside >= rest)
    for b, (label, links) in zip(found, judged, strict=True):
        b.label = label
        if article and not b.marked:
            if not b.inside:
                b.label = "bad"
            elif label == "bad":
                b.label = "bad" if links > MOSTLY else "open"
    inherit(found)


def inherit(found: list[Block]) -> None:
    """Open blocks take the label of the nearest decided neighbours."""
    n = len(found)
    before: list[int | None] = [None] * n
    after: list[int | None] = [None] * n
    for order, into in ((range(n), before), (range(n - 1, -1, -1), after)):
        last = None
        for i in order:
            into[i] = last
            if found[i].label != "open":
                last = i
    labels = [b.label for b in found]
    for i, b in enumerate(found):
        if labels[i] == "open":
            p, q = before[i], after[i]
            if b.inside:  # the article's edge is no neighbour
                p = p if p is not None and found[p].inside and not found[p].marked else None
                q = q if q is not None and found[q].inside and not found[q].marked else None
            sides = [k for k in (p, q) if k is not None]
            if not sides:
                b.label = "good" if b.inside or n == 1 else ("good" if all(x == "open" for x in labels) else "bad")
            elif len({labels[k] for k in sides}) == 1:
                b.label = labels[sides[0]]
            else:
                near = min(abs(k - i) for k in sides)
                b.label = "good" if any(abs(k - i) == near and labels[k] == "good" for k in sides) else "bad"


def extract(page: str | None) -> str:
    found = blocks(page or "")
    classify(found)
    return "\n".join(b.text for b in found if b.label == "good")


def main_text(pages: DataFrame, id_col: str = "page_id", url: str = "url", source: str = "html") -> DataFrame:
    """page_id, url, text, n_chars of every page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [extract(v.as_py()) for v in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [id_col, url, "text", "n_chars"])

    kinds = dict(pages.select(id_col, url).dtypes)
    return pages.select(id_col, url, source).mapInArrow(run, f"{id_col} {kinds[id_col]}, {url} {kinds[url]}, text string, n_chars long")


def op4_html_main_text(spark, sf_dir: str) -> DataFrame:
    return main_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
