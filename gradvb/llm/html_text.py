"""Main text of web pages by tag-path ratios."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import small_batches, table

#: Comments, declarations and tags. Quotes delimit only what directly follows an equals sign; elsewhere, and where none closes them, they are characters like others.
MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:=\s*(?:\"[^\"]*\"|'[^']*')|[^>])*)(?:>|\Z)", re.S)
NAMES = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)

#: Elements whose content is never text of the page.
RAW = {"script", "style", "noscript", "template", "textarea", "svg", "iframe", "object", "head", "title"}
#: Elements that hold no content.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
#: Elements that begin a block of text.
BLOCKS = {
    "address", "article", "aside", "blockquote", "body", "center", "dd", "details", "dialog", "div", "dl", "dt", "fieldset",
    "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hgroup", "hr", "html", "li", "main",
    "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul",
}
#: Elements that are page furniture.
FURNITURE = {"nav", "footer", "aside", "form", "button", "select", "menu", "dialog", "fieldset", "label", "input"}
#: Words of class, id and role that name page furniture.
FURNITURE_NAMES = {
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "alert", "banner", "breadcrumb", "breadcrumbs", "comment", "comments",
    "complementary", "contentinfo", "consent", "cookie", "cookies", "disqus", "footer", "form", "gdpr", "header", "masthead", "menu",
    "modal", "nav", "navbar", "navigation", "newsletter", "notice", "notification", "pagination", "pager", "popup", "promo", "promoted",
    "recommended", "related", "replies", "reply", "search", "share", "sharing", "sidebar", "signup", "social", "sponsor", "sponsored", "subscribe",
    "toolbar", "widget",
}
#: A start tag of the key ends an open element of the set.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
ENDS_P = BLOCKS - {"html", "body"}
PUNCTUATION = re.compile(r"[.,;:!?…。，،¿¡]")
SPACE = re.compile(r"\s+")


#: Words that say where or how a named element stands, and not what it holds.
PLACES = {
    "area", "bar", "block", "body", "bottom", "box", "button", "buttons", "cell", "col", "column", "container", "content", "fixed", "global", "group",
    "holder", "icon", "icons", "inner", "item", "items", "left", "link", "links", "list", "main", "media", "mobile", "outer", "page", "panel",
    "post", "posts", "primary", "right", "row", "secondary", "section", "site", "slot", "sticky", "text", "thread", "title", "top", "unit", "us",
    "wrap", "wrapper",
}
#: Names that say nothing against an element inside an article, where they stand at its title.
HEADINGS = {"header", "masthead", "banner"}


def named(given: str, in_article: bool) -> int:
    """What the names of an element say: 2, it is furniture; 1, it may be, its text has to tell; 0, nothing."""
    found = 0
    for name in re.sub(r"([a-z])([A-Z])", r"\1 \2", given).lower().split() if given else ():
        words = set(filter(None, re.split(r"[^a-z]+", name)))
        listed = words & FURNITURE_NAMES - (HEADINGS if in_article else set())
        if listed:
            found = max(found, 2 if words <= FURNITURE_NAMES | PLACES else 1)
    return found


@dataclass
class Node:
    """A text block: its tag path, the open containers' numbers, what its containers say (as ``named``), those that may be furniture, and its text."""

    path: tuple[str, ...]
    inside: tuple[int, ...]
    furniture: int
    doubtful: tuple[int, ...]
    text: str


def blocks(html: str) -> tuple[list[Node], dict[int, str]]:
    """The page's blocks in order, and each container's element name."""
    stack: list[tuple[str, str, int, int]] = []
    names: dict[int, str] = {}
    out: list[Node] = []
    piece: list[str] = []
    number, at, end = 0, 0, len(html)

    def flush() -> None:
        text = SPACE.sub(" ", unescape("".join(piece)).replace("\xa0", " ")).strip() if piece else ""
        piece.clear()
        if text:
            out.append(Node(tuple(s[1] for s in stack if s[0] in BLOCKS), tuple(s[2] for s in stack), max((s[3] for s in stack if s[3] != 1), default=0), tuple(s[2] for s in stack if s[3] == 1), text))

    while at < end:
        found = MARKUP.search(html, at)
        if found is None:
            piece.append(html[at:])
            break
        if found.start() > at:
            piece.append(html[at : found.start()])
        at = found.end()
        tag = (found[2] or "").lower()
        if not tag:
            continue
        if found[1]:
            if tag in BLOCKS:
                flush()
            depth = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), None)
            if depth is not None and (tag in BLOCKS or not any(s[0] in BLOCKS for s in stack[depth:])):
                del stack[depth:]
            continue
        if tag in RAW:
            if not found[3].endswith("/"):
                close = re.compile(rf"</{re.escape(tag)}\b[^>]*(?:>|\Z)", re.I).search(html, at)
                at = close.end() if close else (at if tag in ("head", "title") else end)
            continue
        if tag == "br" or tag in VOID:
            piece.append(" ")
            if tag == "hr":
                flush()
            continue
        if tag in BLOCKS:
            flush()
            open_p = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == "p"), None)
            if open_p is not None and tag in ENDS_P:
                del stack[open_p:]
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] in ("ul", "ol", "dl", "table", "select") and tag not in ("ul", "ol", "dl", "table"):
                    break
                if stack[i][0] in CLOSES.get(tag, ()):
                    del stack[i:]
                    break
        given = " ".join(a or b or c for a, b, c in NAMES.findall(found[3])) if found[3] else ""
        in_article = any(s[0] in ("article", "main") for s in stack)
        furniture = 3 if tag in FURNITURE or tag == "header" and not in_article else named(given, in_article) if tag not in ("html", "body", "article", "main") else 0
        number += 1
        names[number] = tag
        if not found[3].endswith("/"):
            stack.append((tag, f"{tag}.{given}" if given else tag, number, furniture))
    flush()
    return out, names


def path_ratios(nodes: list[Node], width: float = 1.0) -> np.ndarray:
    """Each block's fused ratio: of its path, characters a block times punctuation marks a block, smoothed along the page."""
    total: dict[tuple[str, ...], list[float]] = {}
    for node in nodes:
        x = total.setdefault(node.path, [0.0, 0.0, 0.0])
        x[0] += len(node.text)
        x[1] += len(PUNCTUATION.findall(node.text))
        x[2] += 1
    fused = np.array([np.sqrt((total[n.path][0] / total[n.path][2]) * (1 + total[n.path][1] / total[n.path][2])) for n in nodes])
    reach = int(np.ceil(width))
    kernel = np.exp(-0.5 * (np.arange(-reach, reach + 1) / max(width, 1e-9)) ** 2)
    padded = np.pad(fused, reach, mode="edge")
    return np.convolve(padded, kernel / kernel.sum(), mode="valid")


def main_text(html: str | None) -> str:
    """The article's blocks, one per line.

    Blocks of elements for furniture (menus, headers, forms and so on) never count, and those of elements named as furniture
    (adverts, comments and so on) only on pages that have no others. Of the rest, paths whose smoothed ratio reaches half a standard
    deviation of all are content; an element whose name only hints at furniture goes unless half its text is content.
    Where articles are marked, they are the text, all of them. Else the innermost container
    that holds most of the content adds its other blocks, and content outside it stays.
    """
    nodes, names = blocks(html or "")
    nodes = [n for n in nodes if not n.furniture] or [n for n in nodes if n.furniture < 3]
    if not nodes:
        return ""
    ratio = path_ratios(nodes)
    chosen = ratio >= 0.5 * ratio.std()
    share: dict[int, list[int]] = {}
    for node, yes in zip(nodes, chosen, strict=True):
        for c in node.doubtful:
            x = share.setdefault(c, [0, 0])
            x[0] += len(node.text)
            x[1] += len(node.text) * bool(yes)
    thin = {c for c, (whole, content) in share.items() if 2 * content < whole}
    stays = [k for k, n in enumerate(nodes) if not thin.intersection(n.doubtful)] or list(range(len(nodes)))
    nodes, chosen = [nodes[k] for k in stays], chosen[stays]
    weight: dict[int, float] = {}
    for node, yes in zip(nodes, chosen, strict=True):
        if yes:
            for c in node.inside:
                weight[c] = weight.get(c, 0.0) + len(node.text)
    whole = sum(len(n.text) for n, yes in zip(nodes, chosen, strict=True) if yes)
    marked = [c for c, w in weight.items() if names[c] in ("article", "main") and w >= 0.2 * whole]
    if marked:
        best = {c for c in weight if names[c] in ("article", "main")}
        return "\n".join(n.text for n in nodes if best.intersection(n.inside))
    holders = [c for c, w in weight.items() if names[c] in ("body", "div", "section", "td") and w >= 0.6 * whole]
    best = max(holders, default=0)
    kept = [n.text for n, yes in zip(nodes, chosen, strict=True) if yes or best and best in n.inside]
    return "\n".join(kept)


def extract(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", keep: tuple[str, ...] = ("url",)) -> DataFrame:
    """(page_id, the ``keep`` columns, text, n_chars) for every page.

    Null and empty pages, and pages that are furniture throughout, give an empty text. Pages of
    any length are read whole, broken markup included. Repeated rows come back as often as they came; an empty
    table gives no rows; other columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(h) for h in batch.column(batch.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*names, "text", "n_chars"])

    chosen = small_batches(pages).select(F.col(id_col).cast("long").alias("page_id"), *keep, F.col(html_col).alias("html"))
    names = chosen.columns[:-1]
    schema = chosen.drop("html").schema.add("text", "string").add("n_chars", "long")
    return chosen.mapInArrow(run, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
