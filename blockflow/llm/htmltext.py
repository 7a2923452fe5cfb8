"""Main text of web pages by the distribution of text over line blocks.

A page is cut into lines, one for each block of markup, with the markup stripped. A line's length is that of its text, or 0
where the line belongs to something that is never main text: menus, headers and footers of the page, sidebars, notices,
adverts, forms, scripts, styles and reader comments, told by element, role or class name. Where a page marks its article, the
marks decide: its lines with length are the text, and the lines outside have length 0.

On other pages the distribution over line blocks decides. A line's weight is the part of its length outside links, and a
block's the sum over a sliding window of lines. Blocks of weight 0 part the page into stretches. In a stretch the text
surges where a block first exceeds a threshold and dives after the last block that does; at both ends the short lines of that
block are left out, but for headings before the first long line. Short lines between long ones stay. A stretch without a
surge holds menus and notices and is left out, unless no stretch of the page has one: then all lines with length are kept.
What this can't tell: unmarked boilerplate whose blocks are as heavy as text, and short text lines at a stretch's ends.

Defined cases: null and empty html, and pages without main text, give an empty text; markup that ends early or is not
closed is read as far as it goes; rows that repeat are read one by one; an empty table gives an empty result; a column named
main_text or main_chars is replaced. The work grows with the page, however deep its elements lie.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

#: Lines of a block, and the block weight above which text surges: short boilerplate lines stay below, paragraphs above.
BLOCK, SURGE = 3, 40

#: Elements whose content is no text, elements outside the main text, elements that begin a new line.
SILENT = frozenset("script style noscript template svg math iframe object canvas audio video title select option datalist textarea map".split())
OUTSIDE = frozenset("nav footer aside form menu dialog button fieldset".split())
LINES = frozenset(
    "address article aside blockquote body caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html"
    " li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
#: Elements of the head; whatever else begins closes it, as does text.
HEAD = frozenset("head title meta link base script style noscript template".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6 caption".split())
#: Elements that a new one of the same kind closes.
CLOSES = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}}
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar toolbar".split())
NAMES = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisement|advertising|adbox|adsense|sponsor(?:ed|s)?|promo(?:tion)?s?|banner|nav(?:bar|igation)?|menu|breadcrumbs?|"
    r"sidebar|side|aside|widgets?|foot(?:er)?|masthead|site-?header|page-?header|top-?bar|cookies?|consent|gdpr|notice|notification|alert|popup|modal|overlay|"
    r"newsletter|subscribe|subscription|signup|login|search|share|sharing|social|related|recommend(?:ed|ations)?|comments?|commentlist|disqus|respond|"
    r"repl(?:y|ies)|discussion|pagination|pager|toolbar|tags|copyright|legal|skip-?link|hidden)(?:$|[\s_-])",
    re.I,
)
#: A quote opens a value only after an equals sign, and stands for itself elsewhere, as in browsers.
_MARKUP = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:=\s*+(?:\"[^\"]*+\"|'[^']*+')|[^>])*+)(?:>|\Z)",
    re.S,
)
_ATTRIBUTE = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))")
_SPACE = re.compile(r"\s+")


def _is_outside(name: str, attributes: str, in_article: bool) -> bool:
    if name in OUTSIDE or name == "header" and not in_article:
        return True
    if "=" not in attributes:
        return False
    for key, *values in _ATTRIBUTE.findall(attributes):
        value, key = next((v for v in values if v), ""), key.lower()
        if key == "role" and value.lower() in ROLES and name not in ("article", "main", "body"):
            return True
        if key in ("class", "id") and name not in ("html", "body", "article", "main") and NAMES.search(value):
            return True
        if key == "style" and "display:none" in value.replace(" ", "").lower() or key == "aria-hidden" and value == "true":
            return True
    return False


def _clean(parts: list[str]) -> str:
    return _SPACE.sub(" ", html.unescape("".join(parts))).strip()


def lines_of(page: str) -> list[tuple[str, bool, bool, int, bool]]:
    """The page's lines as (text, outside of any main text, in a marked article, characters outside links, heading)."""
    out: list[tuple[str, bool, bool, int, bool]] = []
    open_: list[tuple[str, bool, bool]] = []
    #: How many elements of a name are open.
    held: Counter[str] = Counter()
    parts: list[str] = []
    #: Where in `parts` the line's links begin and end.
    links: list[int] = []

    def state() -> tuple[bool, bool]:
        return open_[-1][1:] if open_ else (False, False)

    def end_line() -> None:
        if parts:
            text = _clean(parts)
            if text:
                plain = len(text)
                if links:
                    edges = [0, *links, len(parts)]
                    plain = len(_clean([x for a, b in zip(edges[::2], edges[1::2], strict=False) for x in parts[a:b]]))
                out.append((text, *state(), plain, any(held[x] for x in HEADINGS)))
            parts.clear()
        links.clear()

    def close(name: str) -> None:
        """Close the innermost element of a name and what is open in it."""
        end_line()
        while open_:
            last = open_.pop()[0]
            held[last] -= 1
            if last == name:
                break

    def add(text: str) -> None:
        if open_ and open_[-1][0] == "head" and not text.isspace():
            close("head")
        parts.append(text)

    at, n = 0, len(page)
    while at < n:
        found = _MARKUP.search(page, at)
        if found is None:
            add(page[at:])
            break
        if found.start() > at:
            add(page[at : found.start()])
        at = found.end()
        name = (found.group(2) or "").lower()
        if not name:
            continue
        if name == "a" and bool(found.group(1)) == bool(len(links) % 2):
            links.append(len(parts))
        if found.group(1):
            if held[name]:
                close(name)
            elif name in LINES or name in OUTSIDE:
                end_line()
            continue
        if open_ and open_[-1][0] == "head" and name not in HEAD:
            close("head")
        if name in SILENT:
            end_of = re.compile(rf"</{name}\s*>", re.I).search(page, at)
            at = end_of.end() if end_of else n
            end_line() if name not in ("svg", "math", "map") else parts.append(" ")
            continue
        if name == "br":
            parts.append(" ")
            continue
        attributes = found.group(3)
        outside, article = state()
        hides = _is_outside(name, attributes, article)
        if name in LINES or hides:
            end_line()
            drop = CLOSES.get(name)
            if drop and any(held[x] for x in drop):
                for x, *_ in reversed(open_):
                    if x in drop:
                        close(x)
                        break
                    if x in ("ul", "ol", "table", "div", "article", "section", "main", "dl"):
                        break
                outside, article = state()
            if name not in VOID and not attributes.endswith("/"):
                open_.append((name, outside or hides or name == "head", article or name in ("article", "main")))
                held[name] += 1
    end_line()
    return out


def _regions(weight: list[int], heading: list[bool]) -> list[tuple[int, int]]:
    """[from, to) of the lines between a surge and its dive, for each stretch between blocks of weight 0."""
    n = len(weight)
    blocks = [sum(weight[i : i + BLOCK]) for i in range(n)]
    found, i = [], 0
    while i < n:
        if blocks[i] == 0:
            i += 1
            continue
        end = next((j for j in range(i, n) if blocks[j] == 0), n)
        surges = [j for j in range(i, end) if blocks[j] > SURGE]
        if surges:
            long = [j for j in range(surges[0], min(end, surges[-1] + BLOCK)) if weight[j] * BLOCK > SURGE]
            first = long[0]
            while first > i and heading[first - 1] and weight[first - 1]:
                first -= 1
            found.append((first, long[-1] + 1))
        i = end
    return found


def main_text(page: str | None) -> str:
    """The main text's lines, with an empty line between each two."""
    lines = lines_of(page or "")
    marked = any(article and not outside for _, outside, article, *_ in lines)
    length = [0 if outside or marked and not article else len(text) for text, outside, article, *_ in lines]
    regions = [(0, len(lines))]
    if not marked:
        weight = [min(x, plain) for x, (*_, plain, _) in zip(length, lines, strict=True)]
        regions = _regions(weight, [h for *_, h in lines]) or regions
    return "\n\n".join(lines[j][0] for a, b in regions for j in range(a, b) if length[j])


def _extracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [main_text(x) for x in batch.column("html").to_pylist()]
        rest = [n for n in batch.schema.names if n != "html"]
        columns = [batch.column(n) for n in rest] + [pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())]
        yield pa.RecordBatch.from_arrays(columns, names=[*rest, "main_text", "main_chars"])


def extract(pages: DataFrame) -> DataFrame:
    """All columns of pages but `html`, with main_text and main_chars (its code points)."""
    pages = pages.drop("main_text", "main_chars")
    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in pages.schema if f.name != "html"]
    return pages.mapInArrow(_extracted, ", ".join([*kinds, "main_text string", "main_chars long"]))
