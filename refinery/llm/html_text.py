"""Main text of web pages by tag-path ratios.

A page is read into text nodes, each with its root-to-leaf tag path. Per path, the text length and the punctuation
of its nodes are summed and divided by its number of nodes. Both ratios are laid along the page's nodes in order,
smoothed by a Gaussian window, fused (product, punctuation counted from one) and cut at a share of their spread: the
nodes above are content nodes. What is returned hangs on them:

- the region is the innermost container with nearly all of the content nodes' weight (score times length), widened to the
  container that holds its headline (an article or main around it, or one with a heading before it);
- inside it, blocks with a content node are text; a container without any is not (an advert, a box of links, a footer); lone
  paragraphs, headings, lists and tables between them are, unless most of their text is links.

Names of tags and classes are a second signal only: a part named as something else than article (a nav or aside, a class
`sidebar` or `cookie-notice` as a whole word, not a piece of one as in `has-sidebar`) has its nodes' scores weighed down, so it loses
against the rest of the page; where all of a page stands in such a part, it changes nothing.

Runs in mapInArrow, a page at a time, so memory is bounded by the longest page. Defined results: null or empty html, or
a page without text, gives an empty text. Broken markup (unclosed, stray or cut-off tags) is read as browsers do in
outline: a start tag closes what cannot hold it, a stray end tag is ignored. Repeated rows are handled each.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

#: Tags whose content is not text, or not the article's.
RAW = frozenset("script style textarea title noscript iframe svg math template object canvas xmp noembed noframes".split())
OTHER = frozenset("nav aside footer form dialog menu fieldset".split())
GONE = RAW | frozenset("head button select datalist audio video map".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr br img".split())
#: Blocks that hold text themselves, and containers that may stand between paragraphs without one of the content nodes.
LEAVES = HEADINGS | frozenset("p li td th dt dd pre figcaption caption address summary".split())
LOOSE = frozenset("ul ol dl table thead tbody tfoot tr figure blockquote details hgroup".split())
#: Words that name a part as something else than the article; what may stand before or after them in one word of a class, id or role.
NAMES = (
    "ads?|adverts?|advertisements?|advertising|adbox|adslot|sponsor(?:ed|s)?|promo(?:ted|tions?)?|nav|navbar|navigation|menu|topnav|breadcrumbs?|sidebars?|aside|foot|footer|masthead|topbar|banner|cookies?|consent|gdpr|notices?|notifications?|"
    "alerts?|popups?|modal|overlay|newsletter|subscribe|subscription|signup|login|comments?|commentlist|discussion|disqus|replies|respond|share|sharing|social|related|recommended|recommendations|widgets?|pagination|pager|toc|contentinfo|"
    "complementary|searchbox|search|paywall|toolbar|copyright|disclaimer|tags|taglist"
)
BEFORE = "site|page|main|global|top|bottom|left|right|primary|secondary|post|article|blog|entry|user|reader|ad|cookie|google|sticky|mobile|footer|header|social|newsletter"
AFTER = "area|bar|box|container|wrapper|wrap|section|list|block|widget|inner|holder|banner|notice|form|links?|menu|thread|slot|unit|panel|buttons?|bottom|top|left|right|nav|signup|consent|message|posts?|articles?|content"
NAMED = re.compile(rf"(?:(?:{BEFORE})[-_]?)?(?:{NAMES})(?:[-_]?(?:{AFTER}))?(?:[-_]?\d+)?|more-from|skip-link|byline-share")
HEADER_NAMED = re.compile(r"(?:site|page|top|main|global)?[-_]?header")
#: Weight of the scores below a part that is named so.
WEIGH_DOWN = 0.01
#: A start tag of these closes an open p; of the others, their like up to the container.
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul li dt dd".split())
LIKE = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table", "tbody", "thead", "tfoot"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"(class|id|role|hidden|aria-hidden|style|itemprop)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
PUNCTUATION = re.compile(r"[.,;:!?…。、，；：！？·]")
SPACE = re.compile(r"\s+")
#: Half width of the smoothing window, its spread, and the cut as a share of the standard deviation.
REACH, SPREAD, CUT = 2, 1.0, 0.5
#: Share of the content nodes' weight that the region holds at least; share of links from which an unscored block is not text.
NEARLY_ALL, LINKED = 0.98, 0.5
WINDOW = [math.exp(-(k * k) / (2 * SPREAD * SPREAD)) for k in range(-REACH, REACH + 1)]


class Element:
    __slots__ = ("tag", "up", "gone", "weight", "mass", "chars", "linked", "path", "is_block")

    def __init__(self, tag: str, label: str, up: Element | None, gone: bool, weight: float):
        self.tag, self.up, self.gone, self.weight = tag, up, gone, weight
        self.mass, self.chars, self.linked = 0.0, 0, 0
        self.path = f"{up.path}/{label}" if up else label
        self.is_block = tag not in INLINE


@lru_cache(100_000)
def named(attributes: str) -> tuple[bool, bool, bool, str]:
    """Of a tag's attributes: whether it is hidden, named as another part, named as a header; its class."""
    hidden = other = header = False
    label = ""
    for m in ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name in ("hidden", "aria-hidden"):
            hidden |= value == "true" or name == "hidden" and value in ("", "hidden")
        elif name == "style":
            hidden |= bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value))
        else:
            other |= any(NAMED.fullmatch(w) for w in value.split())
            header |= any(HEADER_NAMED.fullmatch(w) for w in value.split())
            if name == "class":
                label = " ".join(value.split())
    return hidden, other, header, label


def text_nodes(page: str) -> tuple[list[tuple[Element, int, str]], Element]:
    """(element, block number, text) of each text node in page order, without scripts and hidden parts; and the root."""
    root = Element("#", "#", None, False, 1.0)
    at, nodes, block, i, articles = root, [], 0, 0, 0

    def emit(text: str) -> None:
        if text and not at.gone:
            nodes.append((at, block, text))

    for m in TAG.finditer(page):
        if m.start() < i:
            continue
        emit(page[i : m.start()])
        i = m.end()
        tag = m[2]
        if tag is None:
            if m[0].startswith("<![CDATA["):
                emit(m[0][9:].removesuffix("]]>"))
            continue
        tag = tag.lower()
        if m[1]:  # an end tag
            if tag == "br":
                emit(" ")
                continue
            x = at
            while x is not root and x.tag != tag:
                if not x.is_block and tag in INLINE or tag not in INLINE:
                    x = x.up
                else:
                    break
            if x is not root and x.tag == tag:
                while True:
                    gone, at = at, at.up
                    block += gone.is_block
                    articles -= gone.tag in ("article", "main")
                    if gone is x:
                        break
            elif tag not in INLINE:
                block += 1
            continue
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*(?:>|\Z)", re.I).search(page, i)
            if not m[0].endswith("/>") or tag in ("script", "style", "textarea", "title"):
                i = end.end() if end else len(page)
            continue
        if tag == "br":
            emit("\n")
            continue
        if tag == "hr":
            block += 1
        if tag in VOID:
            continue
        if tag in CLOSES_P:
            x = at
            while x is not root and (not x.is_block or x.tag == "p") and x.tag != "p":
                x = x.up
            if x.tag == "p":
                while at is not x:
                    at = at.up
                at, block = x.up, block + 1
        if tag in HEADINGS and at.tag in HEADINGS:
            at, block = at.up, block + 1
        if tag in LIKE:
            like, until = LIKE[tag]
            x = at
            while x is not root and x.tag not in until and x.tag not in like:
                x = x.up
            if x.tag in like:
                while at is not x:
                    at = at.up
                at = x.up
        hidden, other, header, label = named(m[3]) if m[3] and not m[3].isspace() else (False, False, False, "")
        if tag in ("html", "body", "main", "article"):
            other = header = False
        other = other or tag in OTHER or (header or tag == "header") and not articles
        at = Element(tag, f"{tag}.{label}" if label else tag, at, at.gone or hidden or tag in GONE, at.weight * (WEIGH_DOWN if other else 1))
        articles += tag in ("article", "main")
        block += at.is_block
    emit(page[i:] if not page[i:].startswith("<") or page[i : i + 2].strip() in ("<",) else "")
    return nodes, root


def scores(nodes: list[tuple[Element, int, str]]) -> list[float]:
    """The fused, smoothed path ratios of the nodes, weighed by the names around them; nodes without text score 0."""
    text, marks, count = {}, {}, {}
    for e, _, t in nodes:
        n = len(t.strip())
        if n:
            text[e.path] = text.get(e.path, 0) + n
            marks[e.path] = marks.get(e.path, 0) + len(PUNCTUATION.findall(t))
            count[e.path] = count.get(e.path, 0) + 1
    real = [k for k, (_, _, t) in enumerate(nodes) if t.strip()]
    both = []
    for ratio in (text, marks):
        line = [ratio[nodes[k][0].path] / count[nodes[k][0].path] for k in real]
        smooth = []
        for k in range(len(line)):
            lo, hi = max(0, k - REACH), min(len(line), k + REACH + 1)
            weights = WINDOW[lo - k + REACH : hi - k + REACH]
            smooth.append(sum(w * v for w, v in zip(weights, line[lo:hi])) / sum(weights))
        # a path's own ratio counts as much as its surroundings
        both.append([(v + s) / 2 for v, s in zip(line, smooth)])
    out = [0.0] * len(nodes)
    for k, a, b in zip(real, *both):
        out[k] = a * (1 + b) * nodes[k][0].weight
    return out


def main_blocks(page: str | None) -> list[str]:
    """The article's blocks in page order."""
    if not page:
        return []
    nodes, root = text_nodes(page)
    fused = scores(nodes)
    live = [s for s in fused if s > 0]
    if not live:
        return []
    mean = sum(live) / len(live)
    cut = CUT * math.sqrt(sum((s - mean) ** 2 for s in live) / len(live))
    kids: dict[Element, dict[Element, None]] = {}
    heads: dict[Element, int] = {}
    for k, (at, _, t) in enumerate(nodes):
        n = len(t.strip())
        chosen, e, linked, heading = fused[k] >= cut and n > 0, at, False, False
        while e is not None:
            linked |= e.tag == "a"
            e.chars += n
            e.linked += n if linked else 0
            if chosen:
                e.mass += fused[k] * n
                if e.up is not None:
                    kids.setdefault(e.up, {})[e] = None
            if heading and n:
                heads.setdefault(e, k)  # the first heading right below it, or below its header
            heading = e.tag in HEADINGS or heading and e.tag in ("header", "hgroup")
            e = e.up
    region = root
    while True:  # down to nearly all of the weight
        child = max(kids.get(region, ()), key=lambda e: e.mass, default=None)
        if child is None or child.mass < NEARLY_ALL * region.mass or not child.is_block or child.tag in LEAVES or child.tag in LOOSE:
            break
        region = child
    first = next(k for k, (e, _, t) in enumerate(nodes) if fused[k] >= cut and t.strip())
    e, around = region, None
    while e is not None:
        if e.tag == "article" or e.tag == "main" and around is None:
            around = e
        e = e.up
    if around is not None:
        region = around
    else:  # up to the container whose heading stands before the text
        e = region
        while e.up is not None and e.up.tag not in ("body", "html", "#"):
            e = e.up
            if heads.get(e, first) < first and e.weight == region.weight:
                region = e
    blocks: list[tuple[int, list[str]]] = []
    verdicts: dict[Element, bool] = {}
    for e, block, t in nodes:
        if e not in verdicts:
            verdicts[e] = is_text(e, region)
        if verdicts[e]:
            if not blocks or blocks[-1][0] != block:
                blocks.append((block, []))
            blocks[-1][1].append(t)
    whole = (SPACE.sub(" ", entities.unescape("".join(parts))).strip() for _, parts in blocks)
    return [b for b in whole if b]


def is_text(e: Element, region: Element) -> bool:
    """Whether the text nodes right below an element are the article's."""
    x, heading, linked = e, False, False
    while x is not None and x is not region:
        heading |= x.tag in HEADINGS
        if x.tag == "header" and not heading:
            return False  # an article's own header keeps its headings only
        if x.is_block and not x.mass:
            if x.weight < region.weight or x.tag not in LEAVES and x.tag not in LOOSE and not (x.tag == "header" and heading):
                return False
            linked |= x.linked >= LINKED * x.chars
        x = x.up
    return x is not None and not linked


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars, n_blocks for every row of pages (page_id, url, html)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            blocks = [main_blocks(h) for h in b.column("html").to_pylist()]
            text = ["\n\n".join(x) for x in blocks]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64()), pa.array([len(x) for x in blocks], pa.int32())], names=["page_id", "url", "text", "n_chars", "n_blocks"])

    rows = pages.select(pages["page_id"].cast("long").alias("page_id"), pages["url"].cast("string").alias("url"), "html")
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long, n_blocks int")
