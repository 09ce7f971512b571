"""Main text of HTML pages by tag-path ratios.

A page is read once into blocks of text, each with its root-to-leaf path of tags. For each
path the text's length, its punctuation and its number of nodes are summed. Text and
punctuation a node, and the spread of the nodes' lengths, which is high where paragraphs are
and none for a lone line, are smoothed over the paths in page order and fused by their
product. Paths over a share of the ratios' spread are content, and their blocks are taken.
With them go headings, short paragraphs and items that stand in the same parts of the page;
parts without a block of a content path, and blocks that are mostly links, don't.

What the elements themselves declare, menus, footers, asides, forms, scripts and hidden
parts, is no text to begin with. Class and id names only weigh a path: one that is named
after adverts, notices or comments needs a ratio as many times higher as ``NAMED`` says.

Defined results: a null or empty page, or one without text in its body, has an empty text;
a quote that is never closed ends with its tag; what follows a cut-off end is read as far as
it goes; rows are independent of each other.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

# HTML elements by their part.
RAW = frozenset("script style noscript template svg math canvas iframe object video audio textarea title head select".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split()
)
BOILER = frozenset("nav footer aside form button menu dialog".split())
ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog form menu menubar".split())
#: Words of class and id names that tell what isn't the article.
NAMES = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo\w*|banner|cookies?|consent|gdpr|notice|alert|newsletter|subscri\w+|signup|popup|modal|overlay|"
    r"nav\w*|menu\w*|breadcrumbs?|sidebar\w*|side|aside|widget\w*|footer\w*|foot|comments?|comment-\w+|respond|replies|disqus\w*|discussion|"
    r"share\w*|sharing|social\w*|related\w*|recommend\w*|trending|popular|pagination|pager|toolbar|login|search\w*|skip\w*|masthead|topbar|site-header|page-header|header|tags?|copyright)(?=$|[\s_-])",
    re.I,
)
_CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split()
)
_SAME = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
_SCOPE = frozenset("table ul ol dl div article section main body aside nav".split())
#: Quotes count after an equals sign only, as in don't.
_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:=\s*(?:\"[^\"]*\"|'[^']*')?|[^>=]++)*+)(?:>|\Z)", re.S)
_ATTR = re.compile(r"(?:^|\s)(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_PUNCTUATION = re.compile(r"[.,;:!?…。，、；：！？]")
_SPACE = re.compile(r"\s+")


#: Paths with a ratio of so many standard deviations of the page's ratios are content.
SPREAD = 0.75
#: A path that is named after adverts, notices, comments and the like weighs so much less.
NAMED = 32.0
#: Elements of running text, which go with the content that they stand beside.
FLOW = frozenset("p h1 h2 h3 h4 h5 h6 hgroup ul ol li dl dt dd blockquote pre figure figcaption table caption thead tbody tfoot tr td th address details summary header".split())


class Element:
    """path: a number for the root-to-leaf run of block-level tags, each with its being named."""

    __slots__ = ("boiler", "in_article", "in_link", "name", "named", "parent", "path", "seeds")

    def __init__(self, name: str, parent: Element | None, boiler: bool, named: bool, paths: dict[tuple[int, str, bool], int]):
        self.name, self.parent, self.boiler, self.seeds = name, parent, boiler, 0
        if parent is None:
            self.path, self.named, self.in_article, self.in_link = 0, False, False, False
            return
        self.named = parent.named or named
        self.path = parent.path if name in INLINE and not named else paths.setdefault((parent.path, name, named), len(paths) + 1)
        self.in_article = parent.in_article or name in ("article", "main")
        self.in_link = name == "a" or parent.in_link and name in INLINE


class Block:
    __slots__ = ("links", "owner", "text")

    def __init__(self, text: str, owner: Element, links: int):
        self.text, self.owner, self.links = text, owner, links


def _declared(name: str, attrs: str, inside_article: bool) -> tuple[bool, bool]:
    """Whether the element is no content by what it is, and whether it is named like such."""
    boiler, named = name in BOILER or name == "header" and not inside_article, False
    for key, a, b, c in _ATTR.findall(attrs) if attrs.strip() else ():
        key, value = key.lower(), a or b or c
        if key in ("class", "id"):
            named = named or name not in ("html", "body", "article", "main") and NAMES.search(value) is not None
        elif key == "hidden" or key == "aria-hidden" and value.lower() == "true" or key == "role" and value.lower() in ROLES:
            boiler = True
        elif key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            boiler = True
    return boiler, named


def read_blocks(page: str) -> tuple[list[Block], list[Element]]:
    """Runs of text between block-level tags, with white space made one space; and the elements."""
    paths: dict[tuple[int, str, bool], int] = {}
    root = Element("", None, False, False, paths)
    now, out, elements, parts, links = root, [], [root], [], 0
    owner, at = root, 0

    def flush() -> None:
        nonlocal parts, links
        text = _SPACE.sub(" ", html.unescape("".join(parts))).strip()
        if text:
            out.append(Block(text, owner, links))
        parts, links = [], 0

    def block_owner(e: Element) -> Element:
        while e.parent is not None and e.name in INLINE and e.path == e.parent.path and not e.boiler:
            e = e.parent
        return e

    def close(names: tuple[str, ...] | frozenset[str], stop: frozenset[str]) -> None:
        nonlocal now
        e = now
        while e.parent is not None and e.name not in stop:
            if e.name in names:
                now = e.parent
                return
            e = e.parent

    def text(s: str) -> None:
        nonlocal links
        parts.append(s)
        if now.in_link:
            links += len(s)

    n = len(page)
    while at < n:
        m = _TAG.search(page, at)
        if m is None:
            text(page[at:])
            break
        text(page[at : m.start()])
        at = m.end()
        name = m[2]
        if name is None:
            continue
        name = name.lower()
        if m[1]:
            inline = name in INLINE
            e = now
            while e.parent is not None and e.name != name:
                if inline and e.name not in INLINE:
                    break
                e = e.parent
            if e.parent is None or e.name != name:
                if name == "br":
                    parts.append(" ")
                continue
            if not inline or e.boiler or e.path != e.parent.path:
                flush()
            now = e.parent
            owner = block_owner(now)
            continue
        if name in RAW:
            ended = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
            inline_raw = name in ("title", "head")
            if name == "head":
                body = re.compile(r"</head\s*>|<body[\s>]", re.I).search(page, at)
                ended = body if body is not None else ended
                at = n if ended is None else ended.start() if ended[0][1] != "/" else ended.end()
            else:
                at = n if ended is None else ended.end()
            if not inline_raw:
                parts.append(" ")
            continue
        if name in VOID:
            if name == "hr":
                flush()
            elif name != "wbr":
                parts.append(" ")
            continue
        if name in _CLOSES_P:
            close(("p",), _SCOPE)
        if name in _SAME:
            close(_SAME[name], frozenset(x for x in _SCOPE if x not in ("div",)))
        boiler, named = _declared(name, m[3], now.in_article)
        boiler = boiler or now.boiler
        new = Element(name, now, boiler, named, paths)
        elements.append(new)
        if name not in INLINE or boiler and not now.boiler or named:
            flush()
        if m[3].endswith("/") and name not in INLINE and m[3].strip() == "/":
            continue
        now = new
        owner = block_owner(now)
    flush()
    return out, elements


def path_ratios(blocks: list[Block]) -> dict[int, float]:
    """The fused ratio of each path; 0 for paths mostly of links, which smoothing would lift beside long texts."""
    place = {p: i for i, p in enumerate(dict.fromkeys(b.owner.path for b in blocks))}
    chars, squares, links, marks, nodes, named = np.zeros((6, len(place)))
    for b in blocks:
        i, own = place[b.owner.path], len(b.text) - b.links
        chars[i] += own
        squares[i] += own * own
        links[i] += b.links
        marks[i] += len(_PUNCTUATION.findall(b.text))
        nodes[i] += 1
        named[i] = b.owner.named

    def smooth(x: np.ndarray) -> np.ndarray:
        padded = np.pad(x, 1, mode="edge")
        return 0.25 * padded[:-2] + 0.5 * padded[1:-1] + 0.25 * padded[2:] if len(x) > 2 else x

    text, spread = chars / nodes, np.sqrt(np.maximum(squares / nodes - (chars / nodes) ** 2, 0.0))
    fused = smooth(text) * smooth((marks + 1) / nodes) * smooth(1 + spread) / np.where(named > 0, NAMED, 1.0)
    return dict(zip(place, np.where(links > chars, 0.0, fused).tolist(), strict=True))


def main_text(page: str | None, spread: float = SPREAD) -> str:
    """The text of the blocks on content paths, and of the running text beside them."""
    blocks, elements = read_blocks(page or "")
    body = [b for b in blocks if not b.owner.boiler]
    if not body:
        return ""
    ratio = path_ratios(body)
    values = np.array(list(ratio.values()))
    limit = min(spread * float(values.std()), float(values.max()))
    seeds = [ratio[b.owner.path] >= limit for b in body]
    for b, seed in zip(body, seeds, strict=True):
        b.owner.seeds += seed
    for e in reversed(elements):
        if e.parent is not None:
            e.parent.seeds += e.seeds

    beside: dict[int, bool] = {}

    def stands_beside(e: Element) -> bool:
        """Whether e is running text, up to a part that has a seed."""
        chain = []
        while id(e) not in beside and not e.seeds:
            chain.append(id(e))
            if e.name not in FLOW and e.name not in INLINE or e.parent is None:
                beside[id(e)] = False
                break
            e = e.parent
        found = beside.get(id(e), True)
        beside.update(dict.fromkeys(chain, found))
        return found

    def goes_along(b: Block) -> bool:
        return not b.owner.named and 2 * b.links <= len(b.text) and stands_beside(b.owner)

    return " ".join(b.text for b, seed in zip(body, seeds, strict=True) if seed or goes_along(b))


def extract(pages: DataFrame, html_col: str = "html", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The kept columns (all but the HTML, if None) and the main text."""
    keep = [c for c in pages.columns if c not in (html_col, text_col)] if keep is None else keep
    source = pages.select(*(F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)), F.col(f"`{html_col}`").alias("_html"))
    schema = pa.schema([(f"_k{i}", to_arrow_type(source.schema[f"_k{i}"].dataType)) for i in range(len(keep))] + [("_text", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py()) for x in batch.column(len(keep))]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(texts, pa.string())], schema=schema)

    kinds = "".join(f"_k{i} {source.schema[f'_k{i}'].dataType.simpleString()}, " for i in range(len(keep)))
    out = source.mapInArrow(run, kinds + "_text string")
    return out.select(*(F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)), F.col("_text").alias(text_col))
