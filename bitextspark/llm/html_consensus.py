"""Main text of web pages by consensus of a host's pages.

Each page's containers are scored by the running text they hold; the page
votes for the path of its best one. A path is the chain of the open
containers' tags and classes, generalised: classes in lower case, without
digits, ids left out. Votes are counted per host in Spark, and every page is
read again with its host's winning paths, the one with most votes that the
page has first. A page without any of them uses its own best container.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, slices, tidy

# Element names by what they do to text.
RAW = ("script", "style", "noscript", "template", "svg", "math", "iframe", "object", "textarea", "title", "head")
CONTAINERS = frozenset(("html", "body", "main", "article", "section", "div", "nav", "header", "footer", "aside", "form", "ul", "ol", "dl", "table", "tbody", "tr", "td", "th", "figure", "fieldset", "details", "dialog", "menu", "center", "blockquote"))
BLOCKS = CONTAINERS | frozenset(("p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "dt", "dd", "pre", "hr", "address", "figcaption", "caption", "thead", "tfoot", "summary", "legend", "option", "hgroup", "search"))
NEVER = frozenset(("nav", "footer", "aside", "form", "menu", "dialog", "fieldset", "button", "select"))
# Words of classes, ids and roles that name what isn't the article.
SIDE = frozenset((
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "sponsor", "sponsored", "promo", "promotion", "banner", "menu", "nav", "navbar", "navigation", "breadcrumb", "breadcrumbs",
    "sidebar", "side", "footer", "foot", "header", "masthead", "topbar", "cookie", "cookies", "consent", "notice", "notices", "gdpr", "popup", "modal", "overlay", "newsletter", "subscribe", "signup", "login",
    "share", "sharing", "social", "related", "recommended", "comment", "comments", "disqus", "reply", "replies", "widget", "toolbar", "pager", "pagination", "search", "alert", "complementary", "contentinfo", "skip",
))

_MARKUP = re.compile(
    r"<!--.*?(?:-->|\Z)|<(?P<raw>" + "|".join(RAW) + r")\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*>.*?(?:</(?P=raw)\s*>|\Z)|<(?P<close>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*)(?P<rest>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>",
    re.S | re.I,
)
_NAMES = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_VOID = re.compile(r"/\s*\Z")
#: A path that as large a share of its host's pages votes for is a consensus, so a host has a bounded number of them; a page has one of them or its own.
CONSENSUS = 0.01
BROADCAST_ROWS = 100_000


def component(tag: str, rest: str) -> tuple[str, bool]:
    """(generalised tag and classes, whether it isn't part of an article)."""
    side, classes = tag in NEVER, []
    if rest:
        for m in _NAMES.finditer(rest):
            value = (m[2] or m[3] or m[4] or "").lower()
            words = value.split()
            side = side or any(w in SIDE for name in words for w in re.split(r"[-_\d]+", name))
            if m[1].lower() == "class":
                classes += [re.sub(r"\d+", "", w).strip("-_") for w in words]
    return ".".join([tag, *sorted({c for c in classes if c})]), side


def blocks(html: str) -> list[tuple[str, tuple[str, ...], bool, int]]:
    """(text, path of its container, whether it's beside the article, characters in links) of every block with text, in page order.

    Unclosed elements end with what holds them, a paragraph where the next block begins.
    """
    out: list[tuple[str, tuple[str, ...], bool, int]] = []
    stack: list[tuple[str, str, bool]] = []
    path: tuple[str, ...] = ()
    beside = False
    text: list[str] = []
    linked, in_link, last, hidden = 0, False, 0, None

    def end():
        nonlocal linked
        words = " ".join(unescape("".join(text)).split())
        if words:
            out.append((words, path, beside, linked))
        text.clear()
        linked = 0

    def look():
        nonlocal path, beside
        path = tuple(x[1] for x in stack)
        # a header inside the article holds its headline
        inside = False
        beside = False
        for tag, _, side in stack:
            inside = inside or tag in ("article", "main")
            beside = beside or side or (tag == "header" and not inside)

    for m in _MARKUP.finditer(html):
        if m.start() > last:
            part = html[last : m.start()]
            if hidden is None:
                text.append(part)
                linked += len(part) * in_link
        last = m.end()
        tag = m["tag"]
        if tag is None:
            continue
        tag, closing = tag.lower(), bool(m["close"])
        if hidden is not None:
            if closing and tag == hidden:
                hidden = None
            continue
        if tag in ("button", "select") and not closing:
            hidden = tag
            continue
        if tag == "a":
            in_link = not closing
        elif tag == "br":
            text.append(" ")
        elif tag in BLOCKS:
            end()
            in_link = False
            if tag in CONTAINERS:
                if not closing:
                    if not _VOID.search(m["rest"]):
                        stack.append((tag, *component(tag, m["rest"])))
                        look()
                else:
                    for i in range(len(stack) - 1, -1, -1):
                        if stack[i][0] == tag:
                            del stack[i:]
                            look()
                            break
    if hidden is None:
        text.append(html[last:])
    end()
    return out


def scores(found) -> dict[tuple[str, ...], float]:
    """Of every container that holds running text: its own blocks in full, those of its containers by halves."""
    out: dict[tuple[str, ...], float] = {}
    for words, path, beside, linked in found:
        worth = len(words) - 2 * linked
        if beside or worth <= 0 or not path:
            continue
        for up in range(min(3, len(path))):
            own = path[: len(path) - up]
            out[own] = out.get(own, 0.0) + worth / 2**up
    return out


def best(found) -> tuple[str, ...] | None:
    made = scores(found)
    return max(made, key=lambda p: (made[p], len(p), p)) if made else None


def extract(html: str | None, winners: list[str] | None) -> str:
    """Text of the first of winners that the page has, else of its own best container; blocks joined by an empty line."""
    found = blocks(html or "")
    wanted = [*(tuple(w.split(" ")) for w in winners or ()), best(found)]
    for path in wanted:
        if path:
            text = [words for words, own, beside, _ in found if not beside and own[: len(path)] == path]
            if text:
                return "\n\n".join(text)
    return "\n\n".join(words for words, _, beside, _ in found if not beside)


def host(url: Column) -> Column:
    """Lower-case host of a URL, empty where there is none."""
    return F.coalesce(F.lower(F.regexp_extract(url, r"^\s*(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def votes(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(host, path, votes) over all pages."""

    def run(batches):
        for whole in batches:
            for batch in slices(whole, "h"):
                own = [best(blocks(h or "")) for h in batch.column("h").to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column("host"), pa.array([" ".join(p) if p else None for p in own], pa.string())], names=["host", "path"])

    read = pages.select(host(F.col(url_col)).alias("host"), F.col(html_col).alias("h"))
    return read.mapInArrow(tidy(run), "host string, path string").filter("path is not null").groupBy("host", "path").agg(F.count("*").alias("votes"))


def winners(voted: DataFrame, share: float = CONSENSUS) -> DataFrame:
    """(host, paths): the paths with share of their host's votes or more, by votes, ties to the longer and then the first by order."""
    total = voted.groupBy("host").agg(F.sum("votes").alias("all"))
    held = voted.join(total, "host").filter(F.col("votes") >= share * F.col("all"))
    order = F.struct((-F.col("votes")).alias("v"), (-F.length("path")).alias("l"), "path")
    return held.groupBy("host").agg(F.array_sort(F.collect_list(order)).alias("x")).select("host", F.col("x.path").alias("paths"))


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(id, url, text, n_chars) of every row of pages.

    A null or empty page has empty text; pages without a host vote and are
    read as one host; a null id or url is carried. Repeated rows each get
    their text, and each vote. An empty table gives an empty result. Other
    columns of pages are not read.
    """
    won = cut(winners(votes(pages, url_col, html_col)), "winners")
    read = pages.select(F.col(id_col).alias("i"), F.col(url_col).alias("u"), F.col(html_col).alias("h"), host(F.col(url_col)).alias("host"))
    read = read.join(F.broadcast(won) if won.count() <= BROADCAST_ROWS else won, "host", "left")

    def run(batches):
        for whole in batches:
            for batch in slices(whole, "h"):
                text = [extract(h, w) for h, w in zip(batch.column("h").to_pylist(), batch.column("paths").to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("i"), batch.column("u"), pa.array(text, pa.string()), pa.array(map(len, text), pa.int64())], names=["i", "u", "text", "n_chars"])

    kind = pages.schema[id_col].dataType.simpleString()
    out = read.select("i", "u", "h", "paths").mapInArrow(tidy(run), f"i {kind}, u string, text string, n_chars long")
    return out.withColumnRenamed("i", id_col).withColumnRenamed("u", url_col)
