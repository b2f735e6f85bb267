"""Operator 6: main text of web pages by a style tree of each site."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, small, tidy

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|<[/a-zA-Z][^>]*\Z", re.S)
NAMED = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none|visibility\s*:\s*hidden", re.I)
#: Elements by what they do, and names that tell it.
RAW = {"script", "style", "textarea", "noscript", "template", "iframe", "svg", "math", "title", "noembed", "noframes", "xmp", "object", "canvas", "audio", "video"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
BLOCKS = {
    "address", "article", "aside", "blockquote", "body", "center", "dd", "details", "dialog", "dir", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6",
    "head", "header", "hgroup", "hr", "html", "legend", "li", "main", "menu", "nav", "ol", "optgroup", "option", "p", "pre", "search", "section", "select", "summary", "table", "tbody", "tfoot", "thead", "tr", "ul", "caption",
}
SPACED = {"br", "td", "th", "img", "wbr"}
CHROME_TAGS = {"nav", "footer", "aside", "form", "menu", "dialog", "button", "select", "option", "datalist", "head", "fieldset", "label", "search", "marquee"}
READER_ROLES = {"comment", "comments", "discussion", "disqus", "replies", "reply", "respond", "responses"}
CHROME_ROLES = {
    "ad", "ads", "advert", "advertisement", "adverts", "advertising", "adsense", "banner", "billboard", "breadcrumb", "breadcrumbs", "byline-share", "captcha", "complementary", "consent", "contentinfo", "cookie", "cookies",
    "copyright", "disclaimer", "feedback", "footer", "gdpr", "header", "login", "masthead", "menu", "menubar", "modal", "nav", "navbar", "navigation", "newsletter", "notice", "notices", "notification", "pager",
    "pagination", "popup", "promo", "promoted", "promotion", "recommended", "related", "search", "share", "sharing", "sidebar", "signup", "skip", "social", "sponsor", "sponsored", "subscribe",
    "subscription", "tags", "toolbar", "topbar", "trending", "warning", "alert", "widget", "widgets",
}
CONTENT_TAGS = {"article", "main"}
#: A tag that opens closes what may not hold it.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = {"ul", "ol", "dl", "table", "article", "main", "section", "div", "body", "html"}

#: Deeper elements count as part of their ancestor at this depth.
DEPTH = 10
#: How much of an element's importance comes from below it.
BELOW = 0.9
#: Branches of lower importance go wherever they are, where at least so many pages of the site have them.
LEAST_IMPORTANCE, LEAST_PAGES = 0.2, 8
#: What names call a frame, or what is outside of the article, goes below this importance; in a place of fewer pages the names decide.
FRAME_IMPORTANCE, FRAME_PAGES = 0.97, 50
#: Counts that a worker gathers before it passes them on.
HELD = 200_000


class Block:
    """Text between two block boundaries: its place in the style tree (hashes of the elements it is in), whether it is no content by what its elements are (chrome) or are called (frame), and whether it is in an article."""

    __slots__ = ("chrome", "content", "frame", "nodes", "parts", "within")

    def __init__(self, nodes: tuple[int, ...], chrome: bool, frame: bool, content: bool, within: int):
        self.nodes, self.chrome, self.frame, self.content, self.within, self.parts = nodes, chrome, frame, content, within, []

    def text(self) -> str:
        return " ".join(unescape("".join(self.parts)).split())


def _role(tag: str, attrs: str, inside: bool) -> tuple[str, bool, bool]:
    """Style of an element, whether it is no content by its tag, and whether its name says so: a whole name inside an article, a part of one outside."""
    names = sorted({re.sub(r"\d+", "0", w) for m in NAMED.finditer(attrs) for w in (m[1] or m[2] or m[3] or "").lower().split()}) if attrs else []
    parts = {w for n in names for w in (n, *re.split(r"[-_]+", n))}
    chrome = tag in CHROME_TAGS or tag == "header" and not inside or bool(parts & READER_ROLES and tag not in ("body", "html", "main")) or bool(attrs and HIDDEN.search(attrs))
    frame = bool((set(names) if inside else parts) & CHROME_ROLES) and tag not in ("body", "html", "main")
    return tag + "".join("." + n for n in names), chrome, frame


def blocks(html: str) -> list[Block]:
    """Blocks of a page in order. Broken markup is read the way browsers do, as far as it matters here."""
    out: list[Block] = []
    # tag, place, no content by tag, by name, in an article, how many elements lead to it
    stack: list[tuple[str, tuple[int, ...], bool, bool, bool, int]] = [("", (), False, False, False, 0)]
    current, at, skip = None, 0, None

    def put(text: str, fresh: bool = False) -> None:
        nonlocal current
        if current is None:
            if not text.strip():
                return
            current = Block(*stack[-1][1:])
            out.append(current)
        current.parts.append(text)

    for m in TOKEN.finditer(html):
        if m.start() < at:
            continue
        if m.start() > at:
            put(html[at : m.start()])
        at = m.end()
        tag = m[2] or m[5]
        if tag is None:
            continue
        tag, closing, attrs = tag.lower(), bool(m[1] or m[4]), m[3] or m[6] or ""
        if tag in RAW:
            if not closing and not attrs.endswith("/"):
                end = re.compile(rf"</{tag}\b[^>]*>", re.I).search(html, at)
                if end:
                    at = end.end()
                elif tag not in ("title", "noscript", "object", "svg", "math"):
                    at = len(html)
            continue
        if tag in BLOCKS:
            current = None
        elif tag in SPACED and current is not None:
            current.parts.append(" ")
        if tag in VOID:
            continue
        if closing:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] == tag:
                    if current is not None and stack[i][2:4] != stack[i - 1][2:4]:
                        current = None
                    del stack[i:]
                    break
                if tag not in BLOCKS and stack[i][0] in BLOCKS or tag == "p":
                    break
            continue
        block = tag in BLOCKS
        style, chrome, frame = _role(tag, attrs, stack[-1][4]) if attrs or block or tag in CHROME_TAGS else (tag, False, False)
        if not block and not chrome and not frame:
            continue  # inline markup has no place in the tree
        if block and stack[-1][0] == "p":
            stack.pop()
        for i in range(len(stack) - 1, 0, -1):
            if stack[i][0] in CLOSES.get(tag, ()):
                del stack[i:]
                break
            if stack[i][0] in SCOPES:
                break
        if chrome and not stack[-1][2] or frame and not stack[-1][3]:
            current = None
        _, nodes, over, named, content, within = stack[-1]
        if len(nodes) < DEPTH:
            nodes = (*nodes, xxhash.xxh64_intdigest(style, nodes[-1] & (1 << 63) - 1 if nodes else 0) - (1 << 63))
        opens = tag in CONTENT_TAGS
        stack.append((tag, nodes, over or chrome, named or frame, (content or opens) and not chrome, len(nodes) if opens else within))
    if at < len(html):
        put(html[at:])
    return out


def page_counts(html: str) -> set[tuple[tuple[int, ...], int, int]]:
    """What a page has in its site's tree: (place, 0, 0) elements, (place, 1, hash) their make-up, (place, 2, hash) texts."""
    found, below, texts = set(), {}, {}
    for b in blocks(html):
        if not b.nodes:
            continue
        for i in range(1, len(b.nodes) + 1):
            found.add((b.nodes[:i], 0, 0))
            if i > 1:
                kids = below.setdefault(b.nodes[: i - 1], [])
                if not kids or kids[-1] != b.nodes[i - 1]:
                    kids.append(b.nodes[i - 1])
        texts.setdefault(b.nodes, []).append(b.text())
    for place, kids in below.items():
        found.add((place, 1, xxhash.xxh64_intdigest(",".join(map(str, kids))) - (1 << 63)))
    for place, own in texts.items():
        found.update((place, 2, xxhash.xxh64_intdigest(t) - (1 << 63)) for t in own)
    return found


def host_of(url):
    """Host of an address in lower case; '' where there is none."""
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.\-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def site_tree(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(host, node, pages, importance): the merged trees of all pages of each host.

    An element whose make-up differs from page to page, and a text place whose texts differ, have
    high entropy and so importance near 1; what all pages share has importance near 0. An element's
    importance is the mean over itself and all below it, weighted by pages and, each level down,
    by BELOW. Workers pass on counts, never pages, so a hot host is summed before it is shuffled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def flush() -> pa.RecordBatch:
            rows = [(h, list(p), k, v, n) for (h, p, k, v), n in held.items()]
            held.clear()
            kinds = [pa.string(), pa.list_(pa.int64()), pa.int32(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["host", "place", "kind", "value", "n"])

        for b in batches:
            for host, html in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                held.update((host, *x) for x in page_counts(html.as_py() or ""))
                if len(held) > HELD:
                    yield flush()
        if held:
            yield flush()

    counts = pages.select(host_of(pages[url_col]).alias("host"), pages[html_col].alias("html")).mapInArrow(tidy(run), "host string, place array<long>, kind int, value long, n long")
    counts = counts.groupBy("host", "place", "kind", "value").agg(F.sum("n").alias("n"))
    nodes = counts.groupBy("host", "place").agg(
        F.sum(F.when(F.col("kind") == 0, F.col("n"))).alias("m"), F.sum(F.when(F.col("kind") == 1, F.col("n") * F.log("n"))).alias("made"), F.sum(F.when(F.col("kind") == 1, F.col("n"))).alias("with"),
        F.sum(F.when(F.col("kind") == 2, F.log("n"))).alias("told"), F.sum(F.when(F.col("kind") == 2, 1)).alias("texts"),
    )
    log_m = F.log("m")
    shape = F.when(F.col("with").isNotNull(), F.when(F.col("m") > 1, (F.log("with") - F.col("made") / F.col("with")) / log_m).otherwise(1.0))
    words = F.when(F.col("texts").isNotNull(), F.when(F.col("m") > 1, 1 - F.col("told") / F.col("texts") / log_m).otherwise(1.0))
    nodes = nodes.select("host", "place", "m", F.coalesce(words, shape, F.lit(1.0)).alias("own"), F.when(words.isNotNull(), 1.0).otherwise(1 - BELOW).alias("share"))
    up = nodes.select("host", "m", "own", "share", "place", F.posexplode("place").alias("at", "node"))
    weight = F.col("share") * F.col("m") * F.pow(F.lit(BELOW), F.size("place") - 1 - F.col("at"))
    here = F.when(F.col("at") == F.size("place") - 1, F.col("m"))
    return up.groupBy("host", "node").agg(F.max(here).alias("pages"), (F.sum(weight * F.col("own")) / F.sum(weight)).alias("importance"))


def decisions(tree: DataFrame) -> DataFrame:
    """(host, low, text): places of each host, by hash, that go because all pages are alike there, and that are text because hardly any two are."""
    low = (F.col("importance") < LEAST_IMPORTANCE) & (F.col("pages") >= LEAST_PAGES)
    text = (F.col("importance") >= FRAME_IMPORTANCE) & (F.col("pages") >= FRAME_PAGES)
    kept = lambda c: F.collect_set(F.when(c, F.col("node")))
    return tree.where(low | text).groupBy("host").agg(kept(low).alias("low"), kept(text).alias("text"))


def main_text(html: str, low: frozenset | set = frozenset(), text: frozenset | set = frozenset()) -> str:
    """Main text of a page; low, text: places of its site's tree (see ``decisions``).

    What elements are comes first: menus, footers, forms, reader comments and so on go. The rest
    is in an article, or may be a frame: called one (an advert, a notice), or outside of the article
    where a page has one. The tree decides on frames: those whose texts are each page's own stay,
    those that the site repeats go, and so do those that too few pages have to tell. Branches of
    low importance go everywhere, in an article those below it. An article that is low throughout
    stays, since then the site's pages are copies and nothing tells text from frame.
    """
    found = [b for b in blocks(html) if not b.chrome]
    article = any(b.content for b in found)
    kept = [b for b in found if not (b.frame or article and not b.content) or b.nodes and b.nodes[-1] in text]
    inside = [b for b in kept if b.content]
    if inside:
        high = [b for b in kept if not low.intersection(b.nodes[b.within :] if b.content else b.nodes)]
        kept = high if any(b.content for b in high) else inside
    else:
        kept = [b for b in kept if not low.intersection(b.nodes)]
    return "\n".join(t for b in kept if (t := b.text()))


def extract(pages: DataFrame, url_col: str = "url", html_col: str = "html", id_col: str = "page_id") -> DataFrame:
    """(page_id, url, text, n_chars) of whole pages.

    Null and empty html have the empty text; a null or odd address has the host ''; repeated rows
    count as pages of their own; pages of any length are read whole; an empty table gives no rows.
    """
    tree = materialize(site_tree(pages, url_col, html_col))
    # a site has at most as many places as its templates have elements, and only those of many pages are kept here
    sets = small(materialize(decisions(tree)), 50_000)
    x = pages.select(pages[id_col].cast("long").alias("page_id"), pages[url_col].alias("url"), pages[html_col].alias("html"), host_of(pages[url_col]).alias("host")).join(sets, "host", "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            places = zip(*(c.to_pylist() for c in b.columns[3:]), strict=True)
            texts = [main_text(h.as_py() or "", *(frozenset(p or ()) for p in ps)) for h, ps in zip(b.column(2), places, strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return x.select("page_id", "url", "html", "low", "text").mapInArrow(tidy(run), "page_id long, url string, text string, n_chars long")


def op6(pages: DataFrame) -> DataFrame:
    return extract(pages)
