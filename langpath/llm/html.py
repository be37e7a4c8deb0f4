"""Main text of web pages by tag-path ratios.

A page is read as a list of text blocks, each with the path of block-level tags (and their classes)
from the root.  Per tag path the text length, the number of blocks and the punctuation are summed.  Two
ratios follow: text length per block, and punctuation per block; both are smoothed along the paths in
page order and fused by their product.  Paths that reach a share of the page's deviation are
content.  The container that most content text shares then decides about short blocks: what stands directly inside it,
and headings anywhere inside it, belong to the article.  An <article> or <main> has no say of its own.

Text of blocks that can't be article text by their tag or class (menus, headers, footers, sidebars, notices,
adverts, forms, scripts, styles, reader comments) never enters a path's sums.  A class or id counts only as a
whole name, never on the page's frame (html, body, main, article) nor on what holds ``MOST`` of the text; if all
blocks are barred, the ratios decide among all.

Defined cases: null or empty html gives an empty text; a page without markup is one block; broken and
unclosed tags are closed as browsers do; repeated rows give equal results; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

# Element classes of the page language.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe svg math object canvas textarea select title".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img br".split())
CLOSES_P = frozenset("address article aside blockquote center details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
BARRED = frozenset("nav header footer aside form button dialog menu head".split())
MARKS = frozenset(".,;:!?…。，、；：！？")
# whole class names and ids; parts of longer names say nothing ("no-sidebar" is a layout)
NAMES = re.compile(
    r"(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|comments?|commentlist|respond|disqus|replies|sidebar|side|rail|widget\w*|menu|nav\w*|breadcrumbs?|footer|foot|header|masthead|topbar|consent|gdpr|notices?|popup|modal|overlay|newsletter|subscribe|subscription|signup|login|search|share|sharing|social|related|recommend\w*|more-stories|pagination|pager|toolbar|skip|hidden|legal|copyright|disclaimer"
    r"|(?:cookies?|ads?|advert|sponsored|promo|popup|newsletter)(?:[_-]\w+)*"
    r"|(?:site|page|main|top|global|primary|secondary|left|right)[_-](?:header|footer|nav\w*|menu|sidebar)"
    r"|(?:comments?|related|share|social|nav|menu|sidebar|widget|footer|breadcrumbs?|search)[_-](?:list|area|section|posts?|articles?|stories|links?|buttons?|bar|box|form|menu|left|right))",
    re.I,
)
UNNAMED = frozenset("html body main article".split())  # never barred for their names
MOST = 0.8
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>"']|"[^"]*"|'[^']*')*)>""", re.S)
MARKER = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I)
CLOSE_ITEM = {"li": ("li", ("ul", "ol", "menu")), "dt": ("dt dd", ("dl",)), "dd": ("dt dd", ("dl",)), "tr": ("tr td th", ("table",)), "td": ("td th", ("tr", "table")), "th": ("td th", ("tr", "table")), "option": ("option", ("select",))}
SHARE = 0.25


def blocks(page: str) -> list[tuple[tuple[str, ...], str, bool]]:
    """(tag path, text, barred) of each block with text, in page order."""
    found: list[tuple[tuple[str, ...], str, bool, list[int]]] = []
    stack: list[tuple[str, str, bool, int]] = []  # tag, tag with class, barred, number if barred for its name
    text: list[str] = []
    named = 0

    def close_block() -> None:
        if text:
            said = " ".join("".join(text).split())
            if said:
                found.append((tuple(x[1] for x in stack), said, any(x[2] for x in stack), [x[3] for x in stack if x[3]]))
            text.clear()

    def pop_to(names: tuple[str, ...], stop: tuple[str, ...] = ()) -> None:
        for k in range(len(stack) - 1, -1, -1):
            if stack[k][0] in names:
                del stack[k:]
                return
            if stack[k][0] in stop:
                return

    at, end = 0, len(page)
    while at < end:
        m = TOKEN.search(page, at)
        run = page[at : m.start() if m else end]
        if run:
            text.append(entities.unescape(run) if "&" in run else run)
        if not m:
            break
        at = m.end()
        tag = (m.group(2) or "").lower()
        if not tag:
            continue
        closing = bool(m.group(1))
        if tag in RAW and not closing:
            if not m.group(3).rstrip().endswith("/"):
                shut = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
                at = shut.end() if shut else end
            continue
        if tag in INLINE:
            if tag == "br":
                text.append(" ")
            elif not closing and m.group(3) and (_barred(m.group(3)) or _named(m.group(3))):
                # an inline element that is hidden or an advert: its text is left out
                shut = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
                at = shut.end() if shut else at
            continue
        close_block()
        if closing:
            pop_to((tag,))
            continue
        if tag in CLOSES_P:
            pop_to(("p",), ("td", "th", "table", "li", "div", "article", "section"))
        if tag in CLOSE_ITEM:
            names, stop = CLOSE_ITEM[tag]
            pop_to(tuple(names.split()), stop)
        if tag in VOID:
            continue
        if m.group(3).rstrip().endswith("/") and ":" in tag:
            continue
        mark = " ".join(a.lower() for k, a in _marks(m.group(3)) if k == "class")
        by_name = tag not in UNNAMED and _named(m.group(3))
        named += by_name
        stack.append((tag, f"{tag}.{mark}" if mark else tag, tag in BARRED or _barred(m.group(3)), named if by_name else 0))
    close_block()
    # a name does not bar what holds most of the text
    total, inside = 0, [0] * (named + 1)
    for _, said, barred, names in found:
        if not barred:
            total += len(said)
            for k in names:
                inside[k] += len(said)
    return [(path, said, barred or any(inside[k] < MOST * total for k in names)) for path, said, barred, names in found]


def _marks(attributes: str) -> list[tuple[str, str]]:
    return [(k.lower(), v.strip("\"'")) for k, v in MARKER.findall(attributes)] if attributes else []


def _barred(attributes: str) -> bool:
    for k, v in _marks(attributes):
        if k == "hidden" or (k == "aria-hidden" and v.lower() == "true"):
            return True
        if k == "role" and v.lower() in ("navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "menu"):
            return True
    return False


def _named(attributes: str) -> bool:
    return any(k in ("class", "id") and any(map(NAMES.fullmatch, v.split())) for k, v in _marks(attributes))


def smooth(xs: list[float], radius: int = 1) -> list[float]:
    """Gaussian means over neighbours; the ends use what there is."""
    w = [math.exp(-(d * d) / (2 * radius * radius)) for d in range(-radius, radius + 1)]
    out = []
    for i in range(len(xs)):
        pairs = [(w[d + radius], xs[i + d]) for d in range(-radius, radius + 1) if 0 <= i + d < len(xs)]
        out.append(sum(a * b for a, b in pairs) / sum(a for a, _ in pairs))
    return out


def path_scores(items: list[tuple[tuple[str, ...], str, bool]]) -> dict[tuple[str, ...], float]:
    """Fused ratio of each tag path."""
    length: dict[tuple[str, ...], int] = {}
    count: dict[tuple[str, ...], int] = {}
    marks: dict[tuple[str, ...], int] = {}
    for path, said, _ in items:
        length[path] = length.get(path, 0) + len(said)
        count[path] = count.get(path, 0) + 1
        marks[path] = marks.get(path, 0) + sum(map(said.count, MARKS))
    paths = list(length)
    text = smooth([length[p] / count[p] for p in paths])
    stop = smooth([(1 + marks[p]) / count[p] for p in paths])
    return {p: a * b for p, a, b in zip(paths, text, stop, strict=True)}


def extract(page: str | None) -> str:
    """Main text of one page."""
    if not page:
        return ""
    every = blocks(page)
    items = [x for x in every if not x[2]] or every
    if not items:
        return ""
    scores = path_scores(items)
    mean = sum(scores.values()) / len(scores)
    sigma = math.sqrt(sum((s - mean) ** 2 for s in scores.values()) / len(scores))
    chosen = {p for p, s in scores.items() if s >= min(SHARE * max(scores.values()), max(sigma, SHARE * mean))}
    # the deepest container that holds most of the chosen text
    weight: dict[tuple[str, ...], int] = {}
    for path, said, _ in items:
        if path in chosen:
            for k in range(len(path)):
                weight[path[:k]] = weight.get(path[:k], 0) + len(said)
    most = weight.get((), 0)
    home = max((p for p, n in weight.items() if n >= 0.8 * most), key=len, default=())

    def belongs(path: tuple[str, ...]) -> bool:
        rest = path[len(home) :]
        return bool(home) and path[: len(home)] == home and (len(rest) < 2 or rest[-1].split(".")[0] in HEADINGS)

    return " ".join(said for path, said, _ in items if path in chosen or belongs(path))


def extract_pages(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """page_id, url, text and n_chars of each page.  No shuffle."""
    src = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).alias("url"), F.col(html).alias("html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "html"):
            texts = [extract(x) for x in batch.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return src.mapInArrow(run, "page_id long, url string, text string, n_chars long")
