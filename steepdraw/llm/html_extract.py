"""Main text of web pages by two passes of block rules.

Pass one reads a page into blocks (runs of text between block-level tags) and labels each from
its own figures: the share of stop words, its length and the share of its characters inside
links.  Blocks inside containers that never hold an article (menus, page headers, footers,
sidebars, notices, adverts, forms, reader comments) are boilerplate whatever they say.
Pass two settles the ambiguous short and middling blocks: each takes the label of its nearest
decided neighbours, good if either side is good, inside an article container always good.

Null html gives an empty text; so does a page without good blocks.  Pages that end in the
middle of a tag, comment or reference are read as far as they go.  No block is cut short.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Frequent function words of English, German, French and Spanish.
STOP_WORDS = frozenset(
    "the of and a to in is it that for on with as was be by are this at from or an not have which "
    "der die das und in zu den von mit sich des auf ist im dem nicht ein eine als auch es an "
    "de la le les et des en un une du que qui dans pour sur au pas est par plus avec "
    "el los las y se del al una con no su para como por lo más o".split()
)
#: Elements by their role.
BLOCK_TAGS = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul".split())
DROPPED_TAGS = frozenset("script style noscript template svg math iframe object canvas textarea select option button title head".split())
RAW_TAGS = frozenset("script style textarea title iframe noscript".split())
OUTER_TAGS = frozenset("nav header footer aside form menu dialog".split())
ARTICLE_TAGS = frozenset("article main".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: An element that begins closes these open ones, as HTML says for tags that may be left out.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "body": {"head"}}
PARAGRAPH_ENDERS = BLOCK_TAGS - {"body", "html", "head", "title", "option"}
OUTER_NAMES = re.compile(
    r"(?:^|[\s_-])(?:ad|ads|advert\w*|sponsor\w*|promo\w*|banner|nav|navbar|navigation|menu|breadcrumbs?|header|masthead|footer|sidebar|aside|"
    r"cookies?|consent|notice|gdpr|popup|modal|newsletter|subscribe|signup|login|comments?|replies|disqus|share|social|related|recommended|widget|toolbar|pagination|copyright)(?:$|[\s_-])",
    re.IGNORECASE,
)
OUTER_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())

LENGTH_LOW, LENGTH_HIGH = 70, 200
STOPS_LOW, STOPS_HIGH = 0.30, 0.32
STOPS_UNKNOWN = 0.05  # a page whose prose has fewer is in a language without a list; length and links decide
MAX_LINK_DENSITY = 0.33
ALL_LINKS = 0.9  # inside an article

#: A tag ends at the first > outside quotes; where quotes don't pair up before the next <, they are read as any character.
_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<![^>]*(?:>|\Z)|<\?[^>]*(?:>|\Z)|"
    r"<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"'<]|\"[^\"<]*\"|'[^'<]*')*>|(?:[^>\"']|=\s*\"[^\"=]*\"|=\s*'[^'=]*')*>|[^>]*(?:>|\Z))",
    re.DOTALL,
)
_ATTRIBUTE = re.compile(r"""([^\s=/>"']+)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""")
_SPACE = re.compile(r"\s+")
_WORD = re.compile(r"[^\W\d_]+")


class Block:
    __slots__ = ("parts", "linked", "outer", "article", "heading", "text", "label")

    def __init__(self, outer: bool, article: bool, heading: bool) -> None:
        self.parts, self.linked, self.outer, self.article, self.heading = [], [], outer, article, heading
        self.text, self.label = "", ""


def _is_outer(tag: str, attributes: str, in_article: bool) -> bool:
    if tag in OUTER_TAGS:
        return not (tag == "header" and in_article)
    if not attributes or tag in ("body", "html", "article", "main"):
        return False
    for name, *values in _ATTRIBUTE.findall(attributes):
        value = next((v for v in values if v), "")
        name = name.lower()
        if name in ("class", "id") and OUTER_NAMES.search(value) or name == "role" and value.lower() in OUTER_ROLES:
            return True
        if name == "style" and re.search(r"display\s*:\s*none", value, re.IGNORECASE):
            return True
    return bool(re.search(r"(?:^|\s)hidden(?:\s|$)", attributes))


def blocks_of(page: str) -> list[Block]:
    """The page's blocks in order, without dropped elements."""
    found: list[Block] = []
    stack: list[tuple[str, bool, bool, bool]] = []  # tag, outer, article, dropped
    outer = article = dropped = False
    links = 0
    current: Block | None = None
    at, n = 0, len(page)

    def put(text: str) -> None:
        nonlocal current
        if not text or dropped:
            return
        if current is None:
            if text.isspace():
                return
            heading = any(t[0] in ("h1", "h2", "h3", "h4", "h5", "h6") for t in stack[-3:])
            current = Block(outer, article, heading)
            found.append(current)
        decoded = html.unescape(text) if "&" in text else text
        current.parts.append(decoded)
        if links:
            current.linked.append(decoded)

    def pop_to(k: int) -> None:
        nonlocal outer, article, dropped, links
        for t in stack[k:]:
            links -= t[0] == "a"
        del stack[k:]
        outer, article, dropped = stack[-1][1:] if stack else (False, False, False)

    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            put(page[at:])
            break
        put(page[at : m.start()])
        at = m.end()
        if m.group(2) is None:
            continue
        tag, closing = m.group(2).lower(), m.group(1)
        if tag == "br":
            put(" ")
            continue
        if tag in BLOCK_TAGS or tag in DROPPED_TAGS:
            current = None
        if closing:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    pop_to(k)
                    break
                if stack[k][0] in BLOCK_TAGS and tag not in BLOCK_TAGS:
                    break  # an inline end tag doesn't close a block
            continue
        if tag in VOID_TAGS:
            continue
        if tag in PARAGRAPH_ENDERS:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == "p":
                    pop_to(k)
                    break
                if stack[k][0] in BLOCK_TAGS:
                    break
        if tag in CLOSES:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] in CLOSES[tag]:
                    pop_to(k)
                    if tag != "tr":
                        break
                elif stack[k][0] in ("ul", "ol", "dl", "table", "tbody", "thead", "html"):
                    break
        attributes = m.group(3).removesuffix(">")
        outer = outer or _is_outer(tag, attributes, article)
        article = article or tag in ARTICLE_TAGS or 'role="main"' in attributes
        dropped = dropped or tag in DROPPED_TAGS
        if not attributes.rstrip().endswith("/") or tag in BLOCK_TAGS:
            stack.append((tag, outer, article, dropped))
            links += tag == "a"
        if tag in RAW_TAGS:
            end = re.compile(rf"</{tag}(?=[\s/>]|\Z)", re.IGNORECASE).search(page, at)
            at = end.start() if end else n
    for b in found:
        b.text = _SPACE.sub(" ", "".join(b.parts)).strip()
    return [b for b in found if b.text]


def _stops(text: str) -> tuple[int, int]:
    words = _WORD.findall(text.lower())
    return sum(w in STOP_WORDS for w in words), len(words)


def _known_language(blocks: list[Block]) -> bool:
    """Whether the stop words say anything about this page's prose."""
    counts = [_stops(b.text) for b in blocks if not b.outer and len(b.text) >= LENGTH_LOW]
    return sum(c[0] for c in counts) >= STOPS_UNKNOWN * sum(c[1] for c in counts)


def _first_pass(b: Block, known: bool = True) -> str:
    """good, bad, near (middling) or short (ambiguous), from the block alone."""
    if b.outer:
        return "bad"
    linked = len(_SPACE.sub(" ", "".join(b.linked)).strip())
    if b.article:  # prose with many links is prose; a block that is nothing but links is a list of them
        if linked >= ALL_LINKS * len(b.text):
            return "bad"
        return "good" if len(b.text) >= LENGTH_LOW else "short"
    if linked > MAX_LINK_DENSITY * len(b.text):
        return "bad"
    if b.text.startswith(("©", "(c) ")):
        return "bad"
    if len(b.text) < LENGTH_LOW:
        return "short" if not linked else "bad"
    if not known:
        return "good" if len(b.text) > LENGTH_HIGH else "near"
    stops, words = _stops(b.text)
    if stops >= STOPS_HIGH * max(1, words):
        return "good" if len(b.text) > LENGTH_HIGH else "near"
    return "near" if stops >= STOPS_LOW * max(1, words) else "bad"


def label_blocks(blocks: list[Block]) -> list[Block]:
    """Both passes; every block ends as good or bad."""
    known = _known_language(blocks)
    first = [_first_pass(b, known) for b in blocks]
    if "good" not in first:  # pages of middling paragraphs only: the longest stand for the text
        first = ["good" if x == "near" and len(b.text) > LENGTH_LOW else x for b, x in zip(blocks, first, strict=True)]
    before, last = [], "bad"
    for b, x in zip(blocks, first, strict=True):
        before.append(last)
        if x in ("good", "bad") and not b.outer:
            last = x
        elif b.outer:
            last = "bad"
    after, last = [], "bad"
    for b, x in zip(reversed(blocks), reversed(first), strict=True):
        after.append(last)
        if x in ("good", "bad") and not b.outer:
            last = x
        elif b.outer:
            last = "bad"
    after.reverse()
    for b, x, left, right in zip(blocks, first, before, after, strict=True):
        if x in ("short", "near") and b.article:
            b.label = "good"
        elif x == "short":
            b.label = "good" if (right == "good" and (b.heading or left == "good")) else "bad"
        elif x == "near":
            b.label = "good" if "good" in (left, right) else "bad"
        else:
            b.label = x
    return blocks


def main_text(page: str | None) -> str:
    if not page:
        return ""
    return "\n".join(b.text for b in label_blocks(blocks_of(page)) if b.label == "good")


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url and the main text of each page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([main_text(x) for x in b.column(2).to_pylist()], pa.string())], names=["page_id", "url", "text"])

    kind = dict(pages.dtypes)
    own = pages.select("page_id", "url", F.col("html").cast("string").alias("html"))
    return own.mapInArrow(run, f"page_id {kind['page_id']}, url {kind['url']}, text string")
