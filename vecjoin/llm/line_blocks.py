"""Main text of HTML pages by line-block distribution.

Markup is taken off so that every block-level tag ends a line; comments, scripts, styles, forms and the
elements that are furniture by tag or by class, id or role leave empty lines. The lengths of text outside links are summed
over ``window`` lines from each line on; where that sum reaches the threshold (surge) a stretch begins, where it falls to
zero (dive) it ends, and the text between its first and its last line with text outside links is kept, link lines in
between included. Lists of links are dives of their own, wherever they stand. The threshold is 86 characters, or half of the page's
largest sum if that is less; on a page with an ``article`` or ``main`` element only lines in there count and any text is
a surge, so that short paragraphs and a heading between notices aren't lost.

A class, id or role marks furniture if all parts of one of its names are furniture words or say a place (``site-header``,
``cookie_notice``, ``sidebar-left``); names that only mention such a word (``has-sidebar``, ``entry-header``, ``related-work``) don't. A
``header`` element inside an article is its heading and stays.

Rows: null or empty html gives an empty text; unclosed and stray tags are tolerated (an ``article`` ends any open
furniture); repeated rows are treated alike, each on its own; long pages go one by one; other columns of ``extract`` pass
through, but for those named text and n_chars, which it replaces.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WINDOW, THRESHOLD = 3, 86

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_NAMES = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_RAW = {"script", "style", "noscript", "template", "textarea", "title", "svg", "math", "iframe", "object", "select", "option", "canvas", "audio", "video", "head"}
_FURNITURE = {"nav", "header", "footer", "aside", "form", "menu", "dialog", "button", "fieldset", "datalist"}
_INLINE = set("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr br".split())
_VOID = set("area base br col embed hr img input link meta param source track wbr".split())
_WORDS = set(
    "ad ads advert adverts advertisement adsense sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert comment comments disqus respond replies sidebar sidebars nav navbar navigation menu breadcrumb "
    "breadcrumbs header masthead footer share sharing social related recommended newsletter subscribe signup popup modal overlay widget toolbar pagination pager complementary contentinfo search login".split()
)
#: Parts of names that say where something stands; they don't make furniture by themselves.
_PLACES = set("site page global main top bottom left right upper lower box area block wrapper container inner outer bar list links section item items col column primary secondary js".split())
_SPACE = re.compile(r"\s+")
_PARTS = re.compile(r"[^a-z]+")


def _is_furniture(name: str, attributes: str, in_article: bool) -> bool:
    if name in _FURNITURE:
        return not (in_article and name == "header")
    if name in ("html", "body", "article", "main") or not attributes:
        return False
    for m in _NAMES.finditer(attributes):
        for said in (m[1] or m[2] or m[3] or "").lower().split():
            parts = {x for x in _PARTS.split(said) if x}
            if parts & _WORDS and parts <= _WORDS | _PLACES:
                return True
    return False


def lines_of(page: str, window: int = WINDOW) -> tuple[list[str], list[int], list[bool]]:
    """Text of each line, its length without link text, and whether it lies in an article or main element."""
    texts: list[str] = []
    sizes: list[int] = []
    inner: list[bool] = []
    part: list[str] = []
    linked = depth = links = 0
    skip: list[str] = []  # open elements inside (and with) the furniture that is left out

    def newline() -> None:
        nonlocal linked
        text = _SPACE.sub(" ", html.unescape("".join(part))).strip()
        texts.append(text)
        sizes.append(max(0, len(text) - linked))
        inner.append(depth > 0)
        part.clear()
        linked = 0

    at = 0
    find = _TAG.search
    while True:
        m = find(page, at)
        if not skip:
            piece = page[at : m.start()] if m else page[at:]
            if piece:
                part.append(piece)
                linked += len(piece) if links else 0
        if not m:
            break
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        closing = bool(m[1])
        if name in _RAW and not closing:
            if name == "head":  # its parts follow one by one
                continue
            end = re.compile(rf"</{name}\s*>", re.I).search(page, at)
            if end:
                at = end.end()
            elif name in ("script", "style", "title", "textarea"):
                at = len(page)
            if name not in ("option", "select") and not skip:
                newline()
            continue
        if name in ("article", "main"):
            if not closing:
                skip.clear()
                newline()
                depth += 1
            elif not skip:
                newline()
                depth = max(0, depth - 1)
            continue
        if skip:
            if closing and name in skip:
                while skip.pop() != name:
                    pass
            elif not closing and name not in _VOID and not m[3].rstrip().endswith("/") and (name == skip[0] or _is_furniture(name, m[3], depth > 0)):
                skip.append(name)
            continue
        if not closing and name not in _VOID and _is_furniture(name, m[3], depth > 0):
            if not m[3].rstrip().endswith("/"):
                skip.append(name)
            for _ in range(window + 1):
                newline()
            continue
        if name == "a":
            links = 0 if closing else 1
        elif name == "br":
            part.append(" ")
        elif name not in _INLINE:
            newline()
            links = 0
    newline()
    return texts, sizes, inner


def main_text(page: str | None, window: int = WINDOW, threshold: int = THRESHOLD) -> str:
    """The page's main text; blocks are parted by an empty line."""
    if not page:
        return ""
    texts, sizes, inner = lines_of(page, window)
    if within := any(inner):
        texts = [t if i else "" for t, i in zip(texts, inner, strict=True)]
        sizes = [n if i else 0 for n, i in zip(sizes, inner, strict=True)]
    return "\n\n".join(t for a, z in stretches(sizes, window, 1 if within else threshold) for t in texts[a:z] if t)


def stretches(sizes: list[int], window: int, threshold: int) -> list[tuple[int, int]]:
    """First and one-past-last line of each stretch between a surge and the next dive."""
    n = len(sizes)
    sums = [sum(sizes[i : i + window]) for i in range(n)]
    least = min(threshold, max(sums, default=0) / 2)
    found, i = [], 0
    while i < n:
        if not sums[i]:
            i += 1
            continue
        j = i
        while j < n and sums[j]:
            j += 1
        # a line's window may end beyond it: the stretch is from its first line with text to its last
        while not sizes[i]:
            i += 1
        if max(sums[i:j]) >= least:
            found.append((i, j))
        i = j
    return found


def extract(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """``pages`` with text and n_chars (code points) of the main text."""
    keep = [c for c in pages.columns if c not in ("text", "n_chars")]
    kind = pages.select(*keep).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p) for p in batch.column(keep.index(html_col)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*keep, "text", "n_chars"])

    from pyspark.sql import types as T

    return pages.select(*keep).mapInArrow(run, T.StructType([*kind.fields, T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())]))


def page_texts(pages: DataFrame, page_id: str = "page_id", url: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text, n_chars; the html itself is left behind in the task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p.as_py()) for p in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), F.col(html_col).cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string, n_chars long")
