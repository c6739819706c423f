"""Main-text extraction by tag-path ratios.

A page is cut into text nodes with their root-to-leaf tag paths. Per path the text length, the punctuation marks and
the number of nodes are summed; a path's two ratios are length per node and marks per node. Both ratio series over the
page's nodes are smoothed with a small Gaussian window, fused as their product, and a path's nodes are content when
their fused value reaches the page's threshold (a share of the mean). This runs on every page, over all text that the
page does not declare as something else: text of menus, headers, footers, sidebars, notices, adverts, forms, scripts,
styles and comments never counts.

*Region.* Content nodes show where the main text lies; short nodes in it (titles, lists) have low ratios of their own.
Where at least half of the content text lies in ``article`` and ``main`` elements, these are the region. Elsewhere it
is the smallest container of all content nodes, with the last ``h1`` before it or, without one, the headings beside it,
and what lies between; a ``main``, a sole ``article`` and articles with content nodes stay as well, other articles are
teasers. All of the region is kept but one thing: nodes before the first and after the last content node that are
links only and no headings, on paths without content (menus without a telling name).

Defined results: null and empty pages give an empty text; unclosed and stray tags are tolerated; an unterminated
comment or script runs to the end of the page; repeated rows give equal texts.
"""

from __future__ import annotations

import html as entities
import re
from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import text_column

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_ATTR = re.compile(r"(?:^|\s)(class|id|role|aria-label|hidden|aria-hidden|itemprop|style)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
# HTML element names by their role.
_RAW = {"script", "style", "textarea", "title", "xmp", "iframe", "noembed", "noframes"}
_SKIP = {"head", "script", "style", "title", "nav", "footer", "aside", "form", "button", "select", "option", "textarea", "input", "label", "fieldset", "noscript", "template", "iframe", "object", "embed", "svg", "canvas", "dialog", "menu", "noembed", "noframes", "xmp"}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
_INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "br", "cite", "code", "data", "del", "dfn", "em", "font", "i", "img", "ins", "kbd", "mark", "q", "ruby", "rp", "rt", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr"}
_BOILER = re.compile(r"(?:^|[\s_-])(?:ad|ads|adv|advert|adverts|advertisement|advertising|sponsor|sponsored|promo|promotion|banner|nav|navbar|navigation|menu|breadcrumb|breadcrumbs|sidebar|side|aside|widget|related|recommended|share|sharing|social|cookie|cookies|consent|notice|notices|gdpr|popup|modal|overlay|newsletter|subscribe|subscription|signup|login|comment|comments|commentlist|disqus|respond|reply|replies|footer|copyright|pagination|pager|search|skip|toolbar|masthead|header|site-header|page-header|topbar|tags|hidden|complementary|contentinfo|search|alert)(?:$|[\s_-]|\d)", re.I)
_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alertdialog", "alert", "menu", "menubar", "toolbar"}
_MARKS = re.compile(r"[.,;:!?…。，、！？]")
_BLANK = re.compile(r"\s+")
_WORD = re.compile(r"\w")
_HREF = re.compile(r"(?:^|\s)href\s*=", re.I)
_CAMEL = re.compile(r"(?<=[a-z0-9])(?=[A-Z])")
_CLOSES_P = {"p", "div", "ul", "ol", "dl", "table", "h1", "h2", "h3", "h4", "h5", "h6", "section", "article", "main", "aside", "footer", "header", "nav", "form", "blockquote", "pre", "hr", "address", "figure", "fieldset", "details"}
_SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
_PARTS = _HEADINGS | {"p", "ul", "ol", "li", "dl", "dt", "dd", "table", "thead", "tbody", "tfoot", "tr", "caption", "blockquote", "pre", "address", "figure", "figcaption", "header", "hgroup"}
_SCOPES = {"ul", "ol", "dl", "table", "select", "article", "section", "main", "div", "body"}


def _declared(name: str, attrs: str, inside_content: bool) -> bool:
    """Whether an element's own markup says that its text is not main text."""
    if name in _SKIP or name == "header" and not inside_content:
        return True
    if not attrs or name in ("html", "body", "article", "main"):
        return False
    for m in _ATTR.finditer(attrs):
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key == "hidden" or key == "aria-hidden" and value.lower() == "true" or key == "role" and value.lower() in _ROLES:
            return True
        if key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            return True
        if key in ("class", "id") and _BOILER.search(_CAMEL.sub("-", value)):
            return True
    return False


class Block(NamedTuple):
    text: str
    path: str
    skip: bool  # declared as not main text
    inside: int  # the outermost article or main around it, 0: none
    chain: tuple[tuple[str, int], ...]  # names and numbers of the elements around it, without inline ones
    linked: bool  # all words are link text


def blocks_of(page: str) -> list[Block]:
    """Blocks in page order."""
    out: list[Block] = []
    stack: list[tuple[str, bool, int, int, bool]] = []  # name, declared boilerplate here or above, Block.inside, number, in a link
    piece: list[str] = []
    state = {"path": "", "skip": False, "inside": 0, "chain": (), "link": False, "linked": True}
    made = 0

    def add(text: str) -> None:
        piece.append(text)
        if state["linked"] and not state["link"] and _WORD.search(text):
            state["linked"] = False

    def flush() -> None:
        text = _BLANK.sub(" ", entities.unescape("".join(piece))).strip()
        piece.clear()
        if text:
            out.append(Block(text, state["path"], state["skip"], state["inside"], state["chain"], state["linked"]))
        state["linked"] = True

    def moved() -> None:
        state["chain"] = tuple((e[0], e[3]) for e in stack if e[0] not in _INLINE)
        state["path"] = "/".join(n for n, _ in state["chain"])
        state["skip"], state["inside"], state["link"] = (stack[-1][1], stack[-1][2], stack[-1][4]) if stack else (False, 0, False)

    at, size = 0, len(page)
    while at < size:
        m = _TOKEN.search(page, at)
        if not m:
            add(page[at:])
            break
        add(page[at : m.start()])
        at = m.end()
        if m[2] is None:  # comment, doctype or processing instruction
            continue
        name, attrs = m[2].lower(), m[3] or ""
        if m[1]:
            if any(e[0] == name for e in stack):
                if name not in _INLINE or stack[-1][1] or any(e[0] == name and e[1] != stack[-1][1] for e in stack):
                    flush()
                if name in _INLINE:  # a stray inline end closes only within its block
                    k = next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == name)
                    if all(e[0] in _INLINE for e in stack[k:]):
                        del stack[k:]
                else:
                    while stack.pop()[0] != name:
                        pass
                moved()
            elif name == "p" or name not in _INLINE:
                flush()
            continue
        if name == "br":
            piece.append(" ")
            continue
        if name not in _INLINE:
            flush()
            if name in _CLOSES_P:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == "p":
                        del stack[k:]
                        break
                    if stack[k][0] in _SCOPES:
                        break
            if name in _SIBLINGS:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] in _SIBLINGS[name]:
                        del stack[k:]
                        break
                    if stack[k][0] in _SCOPES:
                        break
            moved()
        if name in _RAW:
            end = re.compile(rf"</{name}\b[^>]*(?:>|\Z)", re.I).search(page, at)
            at = end.end() if end else size
            continue
        if name in _VOID or attrs.rstrip().endswith("/") and name not in _INLINE and name not in _CLOSES_P:
            continue
        above = stack[-1] if stack else ("", False, 0, 0, False)
        boiler = above[1] or _declared(name, attrs, above[2] > 0)
        if boiler != above[1]:
            flush()
        made += 1
        stack.append((name, boiler, above[2] or (made if name in ("article", "main") else 0), made, above[4] or name == "a" and bool(_HREF.search(attrs))))
        moved()
    flush()
    return out


def _smooth(x: np.ndarray) -> np.ndarray:
    kernel = np.array([0.06, 0.24, 0.4, 0.24, 0.06])
    return np.convolve(np.pad(x, 2, mode="edge"), kernel, "valid")


def _content(blocks: list[Block], share: float) -> list[bool]:
    """Whether the tag-path ratios call a block's path content."""
    sums: dict[str, list[float]] = {}
    for b in blocks:
        s = sums.setdefault(b.path, [0, 0, 0])
        s[0] += len(b.text)
        s[1] += len(_MARKS.findall(b.text))
        s[2] += 1
    length = _smooth(np.array([sums[b.path][0] / sums[b.path][2] for b in blocks]))
    marks = _smooth(np.array([sums[b.path][1] / sums[b.path][2] for b in blocks]))
    fused = length * (marks + 0.1)
    score: dict[str, float] = {}
    for b, v in zip(blocks, fused, strict=True):
        score[b.path] = max(score.get(b.path, 0.0), float(v))
    limit = share * float(np.mean(fused))
    return [score[b.path] >= limit for b in blocks]


def _region(blocks: list[Block], content: list[bool]) -> list[bool]:
    """Whether a block lies in the region that the content blocks show."""
    total = sum(len(b.text) for b, c in zip(blocks, content, strict=True) if c)
    if 2 * sum(len(b.text) for b, c in zip(blocks, content, strict=True) if c and b.inside) >= total:
        return [b.inside > 0 for b in blocks]
    chains = [b.chain for b, c in zip(blocks, content, strict=True) if c]
    depth = 0
    while all(len(x) > depth and x[depth] == chains[0][depth] for x in chains):
        depth += 1
    root = chains[0][:depth]
    while root and root[-1][0] in _PARTS:
        root = root[:-1]
    within = [b.chain[: len(root)] == root for b in blocks]
    first = within.index(True)
    titles = [k for k in range(first) if blocks[k].chain and blocks[k].chain[-1][0] in _HEADINGS]
    tops = [k for k in titles if blocks[k].chain[-1][0] == "h1"]
    if tops:
        first = tops[-1]
    else:
        first = min((k for k in titles if root[: len(blocks[k].chain) - 1] == blocks[k].chain[:-1]), default=first)
    stop = within.index(True)
    declared = {b.inside: False for b in blocks if b.inside}
    for b, c in zip(blocks, content, strict=True):
        if b.inside:
            declared[b.inside] |= c or len(declared) == 1 or ("main", b.inside) in b.chain
    return [w or first <= k < stop or declared.get(b.inside, False) for k, (b, w) in enumerate(zip(blocks, within, strict=True))]


def extract(page: str, share: float = 0.5) -> str:
    """Main text of one page: content blocks joined by newlines."""
    blocks = [b for b in blocks_of(page) if not b.skip]
    if not blocks:
        return ""
    content = _content(blocks, share)
    region = _region(blocks, content)
    span = [k for k, (c, r) in enumerate(zip(content, region, strict=True)) if c and r]
    out = []
    for k, (b, c, r) in enumerate(zip(blocks, content, region, strict=True)):
        menu = b.linked and not c and not span[0] < k < span[-1] and not any(n in _HEADINGS for n, _ in b.chain)
        if r and not menu:
            out.append(b.text)
    return "\n".join(out)


def main_text(pages: DataFrame, *, html: str = "html", out: str = "text") -> DataFrame:
    """All rows and columns of ``pages`` plus ``out``, the extracted text (in place of a column of that name)."""

    def setup():
        return lambda rows: [extract(r.decode("utf-8", "replace")) if r else "" for r in rows]

    return pages.withColumn(out, text_column(setup, "string", html))


def op10_html(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 10 over whole ``pages``."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return main_text(pages).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
