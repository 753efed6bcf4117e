"""Main text of web pages from flat text blocks.

A page is cut in blocks at block-level tags. A block knows its word count and link density, those of its neighbours, and whether an
enclosing element says what it is (an article; a menu, footer, advert, comment ...). A decision tree trained on the small labelled table
`TRAINING_PAGES` decides which blocks are kept. Pages that name their parts are settled by the names; elsewhere the neighbours decide. The
first and the last block, which lack a neighbour, take themselves for it, so that no page's edge looks like a menu's.
"""

from __future__ import annotations

import html as entities
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import chunks
from semimul.llm.html_pages import TRAINING_PAGES

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?:.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_NAMED = re.compile(r"""\b(?:class|id|role|aria-label|itemprop)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|$)|display\s*:\s*none|aria-hidden\s*=\s*["']?true""", re.I)
_PARTS = re.compile(r"[a-z]+")

# Elements by their part in a page.
_RAW = {"script", "style", "noscript", "template", "textarea", "title", "iframe", "object", "svg", "math", "canvas", "video", "audio", "select", "datalist", "button", "xmp", "noembed", "noframes"}
_INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "img", "ins", "kbd", "label", "mark", "nobr", "q", "ruby", "rb", "rp", "rt", "rtc", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr"}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
_OUTSIDE = {"nav", "footer", "aside", "form", "menu", "dialog", "fieldset"}
_BODY = {"article", "main"}
# Names that make even an article element no main text, and words that deny the name after them.
_OUTSIDE_ARTICLE = {"comment", "comments", "reply", "replies", "ad", "ads", "advert", "adverts", "advertisement", "sponsored", "promo", "promotion", "related", "recommended"}
_DENIALS = {"has", "with", "no", "without", "not"}
# Words in class, id and role names.
_OUTSIDE_WORDS = {"nav", "navbar", "navigation", "menu", "menubar", "breadcrumb", "breadcrumbs", "footer", "foot", "header", "masthead", "banner", "sidebar", "side", "aside", "complementary", "contentinfo", "widget", "ad", "ads", "advert", "adverts", "advertisement", "adsense", "sponsor", "sponsored", "promo", "promotion", "cookie", "cookies", "consent", "gdpr", "notice", "notification", "alert", "popup", "modal", "overlay", "newsletter", "subscribe", "subscription", "signup", "login", "share", "sharing", "social", "related", "recommended", "recommendations", "popular", "trending", "comment", "comments", "disqus", "reply", "replies", "respond", "search", "toolbar", "pagination", "pager", "copyright", "disclaimer", "legal", "tags", "tagcloud", "skip"}
_BODY_WORDS = {"article", "articlebody", "content", "main", "post", "entry", "story", "body", "text"}

#: Names of a block's features, in the order of its vector.
FEATURES = ("words", "link density", "words before", "link density before", "words after", "link density after", "outside", "in article", "heading", "sentence ends")


def _marks(tag: str, attributes: str) -> tuple[int, int]:
    """(outside, body) of an element by its tag and names."""
    outside, body = int(tag in _OUTSIDE), int(tag in _BODY)
    if attributes:
        names = set()
        for m in _NAMED.finditer(attributes):
            for name in (m[1] or m[2] or m[3] or "").lower().split():
                parts = _PARTS.findall(name)
                names.update(p for k, p in enumerate(parts) if not (k and parts[k - 1] in _DENIALS))
        outside |= int(bool(names & (_OUTSIDE_ARTICLE if tag == "article" else _OUTSIDE_WORDS))) & int(tag != "main")
        outside |= 2 * int(_HIDDEN.search(attributes) is not None)
        body |= int(bool(names & _BODY_WORDS))
    return outside, body


def blocks(page: str) -> list[tuple[str, np.ndarray]]:
    """The text blocks of a page in order, with their own features (those of neighbours are filled in by `features`)."""
    out: list[tuple[str, list[float]]] = []
    stack: list[tuple[str, int, int]] = []
    text: list[str] = []
    linked = heading = depth_out = depth_body = in_link = 0
    lowered = None

    def flush():
        nonlocal linked, heading
        joined = "".join(text)
        text.clear()
        lines = [" ".join(x.split()) for x in joined.split("\0")]
        words = sum(len(x.split()) for x in lines)
        if words:
            kept = "\n".join(x for x in lines if x)
            ends = sum(kept.count(c) for c in ".!?") + kept.count("。")
            out.append((kept, [words, min(1.0, linked / words), 0, 0, 0, 0, min(depth_out, 1), min(depth_body, 1), heading, min(ends, 3)]))
        linked = heading = 0

    def data(raw: str):
        nonlocal linked
        if raw:
            if "\0" in raw:
                raw = raw.replace("\0", "�")
            raw = entities.unescape(raw).replace("\0", "�") if "&" in raw else raw
            text.append(raw)
            if in_link:
                linked += len(raw.split())

    at, n = 0, len(page)
    while at < n:
        start = page.find("<", at)
        if start < 0:
            data(page[at:])
            break
        if start > at:
            data(page[at:start])
        m = _TOKEN.match(page, start)
        if not m:
            data("<")
            at = start + 1
            continue
        at = m.end()
        if m[2] is None:
            if page.startswith("<![CDATA[", start):
                data(page[start + 9 : at - 3] if page.endswith("]]>", 0, at) else page[start + 9 : at])
            continue
        tag = m[2].lower()
        if m[1]:
            if tag == "a":
                in_link = 0
            if tag not in _INLINE:
                flush()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    for _, o, b in stack[k:]:
                        depth_out -= bool(o)
                        depth_body -= bool(b)
                    del stack[k:]
                    break
            continue
        if tag in _RAW:
            if not m[3].rstrip().endswith("/"):
                if lowered is None:
                    lowered = page.lower() if len(page.lower()) == n else "".join(c.lower() if c.isascii() else c for c in page)
                end = lowered.find("</" + tag, at)
                at = n if end < 0 else (lowered.find(">", end) + 1 or n)
            continue
        if tag == "a":
            in_link = 1
        if tag == "br":
            text.append("\0")
            continue
        if tag not in _INLINE:
            flush()
        if tag == "body" or tag == "html":
            continue
        if tag in _VOID or m[3].rstrip().endswith("/"):
            continue
        outside, body = _marks(tag, m[3])
        if tag == "header" and not depth_body:
            outside = 1
        if outside or body or tag not in {"p", "li", "td", "tr", "th", "dt", "dd", "option"} and tag not in _INLINE:
            stack.append((tag, outside, body))
            depth_out += bool(outside)
            depth_body += bool(body)
        if tag in {"h1", "h2", "h3", "h4", "h5", "h6"}:
            heading = 1
    flush()
    return [(t, np.array(f, dtype=float)) for t, f in out]


def features(found: list[tuple[str, np.ndarray]]) -> np.ndarray:
    x = np.array([f for _, f in found]) if found else np.zeros((0, len(FEATURES)))
    if len(x):
        x[1:, 2:4], x[:-1, 4:6] = x[:-1, :2], x[1:, :2]
        x[0, 2:4], x[-1, 4:6] = x[0, :2], x[-1, :2]
    return x


def _gini(pos: np.ndarray, n: np.ndarray) -> np.ndarray:
    share = pos / np.maximum(n, 1)
    return n * share * (1 - share)


def grow(x: np.ndarray, y: np.ndarray, depth: int = 8, least: int = 2):
    """A binary decision tree by least Gini impurity: (feature, threshold, tree up to it, tree above it), or the share of main text."""
    if depth == 0 or y.min() == y.max() or len(y) < 2 * least:
        return float(y.mean())
    best = None
    for f in range(x.shape[1]):
        order = np.argsort(x[:, f], kind="stable")
        values, hits = x[order, f], np.cumsum(y[order])
        n = np.arange(1, len(y) + 1)
        cost = _gini(hits, n)[:-1] + _gini(hits[-1] - hits, len(y) - n)[:-1]
        ok = (values[1:] > values[:-1]) & (n[:-1] >= least) & (len(y) - n[:-1] >= least)
        if ok.any():
            k = int(np.where(ok, cost, np.inf).argmin())
            if best is None or cost[k] < best[0] - 1e-12:
                best = (cost[k], f, (values[k] + values[k + 1]) / 2)
    if best is None or best[0] >= _gini(y.sum(), np.float64(len(y))) - 1e-12:
        return float(y.mean())
    _, f, cut = best
    low = x[:, f] <= cut
    return (f, float(cut), grow(x[low], y[low], depth - 1, least), grow(x[~low], y[~low], depth - 1, least))


@lru_cache(maxsize=1)
def default_tree():
    """The tree grown on `TRAINING_PAGES`."""
    xs, ys = [], []
    for page in TRAINING_PAGES:
        found = blocks(page)
        xs.append(features(found))
        ys += [float(t[0] == "+") for t, _ in found]
    return grow(np.concatenate(xs), np.array(ys))


def main_text(page: str, tree=None) -> str:
    """Kept blocks joined by newlines; white space inside a block is one space, and a line break element inside it a newline."""
    tree = tree if tree is not None else default_tree()
    found = blocks(page)
    kept = []
    for (text, _), row in zip(found, features(found).tolist()):
        node = tree
        while isinstance(node, tuple):
            node = node[2] if row[node[0]] <= node[1] else node[3]
        if node >= 0.5:
            kept.append(text)
    return "\n".join(kept)


def extract(pages: DataFrame, *, html_col: str = "html", name: str = "text", tree=None) -> DataFrame:
    """`pages` with the string column `name` appended: the main text of the whole page, with character references decoded.

    A null or empty page has an empty text, as has one without main text; a page of one block is judged like any other. A column called `name` in the input is replaced; repeated rows are
    extracted each; an empty table gives an empty result. Broken markup never fails: what is no tag is text.
    """
    rest = [c for c in pages.columns if c != name]
    source = pages.select(*rest, F.col(html_col).cast("string").alias("__in"))

    def run(batches):
        used = tree if tree is not None else default_tree()
        for batch in batches:
            values = batch.column(len(rest)).to_pylist()
            for start, end in chunks(values):
                made = pa.array([main_text(v, used) if v else "" for v in values[start:end]], pa.string())
                yield pa.RecordBatch.from_arrays([batch.column(i).slice(start, end - start) for i in range(len(rest))] + [made], names=[*rest, name])

    return source.mapInArrow(run, pages.select(*rest).schema.add(name, "string"))
