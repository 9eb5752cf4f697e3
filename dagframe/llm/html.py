"""Main text of web pages by consensus of a host's pages.

Each page's containers are scored by the prose that they hold themselves; every page votes, with all its containers, for
their generalised paths (tags with classes, digits and identifiers taken out). The votes of a host are summed in Spark, first
within tasks; its winning paths are the ``best`` with most votes. Each page is read again where it lies: the first winning path
that the page has is the article, wherever its host's pages put it, with the whole of an article element around it. A page
without any of its host's paths, or on a host of its own, uses its own best container. No page moves: the winning paths go to
all tasks, unless they exceed a size; beyond it pages are dealt by host and salt, so that a hot host has many tasks.

Never text: scripts, styles, templates, navigation, headers, footers, sidebars, forms, menus, adverts, notices and reader
comments, by element or by the words of class, id and role; HTML comments; whatever stands in the head.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import read_table, release, with_checkpoints

SALTS = 32
BROADCAST_BYTES = 16 << 20

#: Fixed values of the HTML standard: elements without end tags, elements whose content is no markup, and blocks.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = ("script", "style", "textarea", "noscript", "template", "iframe", "svg", "title", "xmp", "noembed", "noframes")
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
#: Elements that an end tag of an outer element, or a next element of the kind, closes.
CLOSES = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
#: Elements and words of class, id and role that are never a page's own text.
BOILER = frozenset("nav header footer aside form menu head button select dialog".split())
CONTAINERS = frozenset("article main section div body td center".split())
_BOILER_WORD = re.compile(
    r"(?:^|[-_ ])(?<!no[-_])(?<!has[-_])(?<!with[-_])(?<!without[-_])(?:ads?|advert\w*|adsense|sponsor\w*|promo\w*|banner\w*|nav\w*|menu\w*|breadcrumb\w*|sidebar\w*|side|aside|widget\w*|footer\w*|foot|masthead|site-?header|page-?header|comments?|commentlist|disqus\w*|replies|respond|cookie\w*|consent|gdpr|notice\w*|alert\w*|popup\w*|modal\w*|overlay|subscribe\w*|newsletter\w*|signup|login|share\w*|sharing|social\w*|related\w*|recommend\w*|pagination|pager|toolbar|skip-?link\w*|search\w*|tags?|tagcloud|copyright|legal|disclaimer|contentinfo|navigation|complementary)(?=$|[-_ ])"
)
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role|hidden|aria-hidden)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_RAW_END = {tag: re.compile(rf"</{tag}\b[^>]*(?:>|\Z)", re.I) for tag in RAW}
_SPACE = " \t\n\x0b\x0c\r"


class _Node:
    __slots__ = ("tag", "path", "skip", "kids", "block", "article")

    def __init__(self, tag: str, path: str, skip: bool, article: _Node | None = None):
        self.tag, self.path, self.skip, self.kids, self.block = tag, path, skip, [], tag in BLOCKS
        self.article = article or (self if tag == "article" else None)  # the outermost article element that holds the node


def _described(tag: str, attributes: str, inside: bool = False) -> tuple[str, bool]:
    """The element's place in a generalised path, and whether it is no text of the page's own; an article's own header is."""
    skip = tag in BOILER and not inside
    if not attributes:
        return tag, skip
    words = ""
    for name, a, b, c in _ATTRIBUTE.findall(attributes):
        value, name = (a or b or c).lower(), name.lower()
        if name == "hidden" or (name == "aria-hidden" and value == "true"):
            skip = True
        elif name in ("class", "id", "role"):
            skip |= tag not in ("html", "body", "article", "main") and bool(_BOILER_WORD.search(value))
            if name == "class":
                words = ".".join(sorted({re.sub(r"\d+", "#", w) for w in value.split()}))
    return f"{tag}.{words}" if words else tag, skip


def parse(page: str) -> _Node:
    """The page's elements in order; ``kids`` mixes texts and nodes. Tags that are never closed end with their parents."""
    root = _Node("#", "", False)
    stack, at, low = [root], 0, page

    def text(value: str) -> None:
        if value:
            stack[-1].kids.append(value)

    while True:
        m = _TOKEN.search(low, at)
        if m is None:
            text(low[at:])
            return root
        text(low[at : m.start()])
        at = m.end()
        if m[2] is None:
            if m[0].startswith("<![CDATA["):
                text(m[0][9:].removesuffix("]]>").replace("&", "&amp;"))
            continue
        tag = m[2].lower()
        if m[1]:
            if tag in ("br", "p") and not any(n.tag == tag for n in stack):
                stack[-1].kids.append(_Node(tag, "", False))
                continue
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    del stack[k:]
                    break
                if stack[k].tag in ("article", "body", "html", "main", "table", "td", "section") and tag not in ("article", "body", "html", "main", "table", "section", "div", "nav", "header", "footer", "aside", "form", "ul", "ol"):
                    break
            continue
        if tag in CLOSES_P or tag in CLOSES:
            ends = CLOSES.get(tag, set()) | ({"p"} if tag in CLOSES_P else set())
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in ends:
                    del stack[k:]
                    break
                if stack[k].block:
                    break
        place, skip = _described(tag, m[3] or "", tag == "header" and any(n.tag == "article" for n in stack))
        node = _Node(tag, place, skip, stack[-1].article)
        if tag in RAW:
            end = _RAW_END[tag].search(low, at)
            at = end.end() if end else len(low)
            continue
        stack[-1].kids.append(node)
        if tag not in VOID and not (m[3] or "").endswith("/"):
            stack.append(node)


def _clean(parts: list[str]) -> str:
    return " ".join(unescape("".join(parts)).split())


def blocks(node: _Node) -> list[str]:
    """Texts of the blocks under ``node`` in page order, without what is never text."""
    out: list[str] = []
    now: list[str] = []

    def flush() -> None:
        if now:
            if value := _clean(now):
                out.append(value)
            now.clear()

    todo: list = [iter(node.kids)]
    ends = [False]
    while todo:
        kid = next(todo[-1], None)
        if kid is None:
            todo.pop()
            if ends.pop():
                flush()
        elif isinstance(kid, str):
            now.append(kid)
        elif not kid.skip:
            if kid.block:
                flush()
            todo.append(iter(kid.kids))
            ends.append(kid.block)
        elif kid.block:
            flush()
    flush()
    return out


def _walk(root: _Node):
    """(container, its generalised path) of all containers that are not skipped, in page order."""
    todo = [(root, "")]
    while todo:
        node, path = todo.pop()
        here = f"{path}/{node.path}" if node.path else path
        if node.tag in CONTAINERS:
            yield node, here
        todo += [(kid, here) for kid in reversed(node.kids) if not isinstance(kid, str) and not kid.skip and kid.kids]


def _prose(node: _Node) -> float:
    """Characters in the container's own paragraphs, half of those one plain container below it; links count against it."""
    total = 0.0
    todo = [(node, 1.0, False)]
    while todo:
        now, weight, link = todo.pop()
        for kid in now.kids:
            if isinstance(kid, str):
                n = len(kid.strip(_SPACE))
                total += -0.5 * weight * n if link else weight * n
            elif not kid.skip:
                factor = weight * (0.5 if kid.tag in CONTAINERS else 1.0)
                if factor >= 0.1:
                    todo.append((kid, factor, link or kid.tag == "a"))
    return total * (1.5 if node.tag in ("article", "main") else 1.0)


def votes(page: str) -> list[tuple[str, float]]:
    """The page's votes: the paths of all containers with prose, best first, with their shares of its best score."""
    scored: dict[str, float] = {}
    for node, path in _walk(parse(page)):
        if (value := _prose(node)) > 0:
            scored[path] = max(scored.get(path, 0.0), value)
    top = sorted(scored.items(), key=lambda x: (-x[1], x[0]))
    return [(path, value / top[0][1]) for path, value in top]


def _whole(nodes: list[_Node]) -> list[_Node]:
    """Each node, or the article element around it, once and in page order; what lies in another of them is left out."""
    risen = list(dict.fromkeys(n.article or n for n in nodes))
    inner: set[_Node] = set()
    for node in risen:
        todo = [k for k in node.kids if not isinstance(k, str)]
        while todo:
            kid = todo.pop()
            inner.add(kid)
            todo += [k for k in kid.kids if not isinstance(k, str)]
    return [n for n in risen if n not in inner]


def extract(page: str, paths: list[str]) -> str:
    """The text under the first of ``paths`` that the page has with any text, else under its own best container."""
    root = parse(page)
    places: dict[str, list[_Node]] = {}
    for node, path in _walk(root):
        places.setdefault(path, []).append(node)
    for path in paths:
        if path in places and (found := [b for node in _whole(places[path]) for b in blocks(node)]):
            return " ".join(found)
    own = [(value, -i, node) for i, (node, _) in enumerate(_walk(root)) if (value := _prose(node)) > 0]
    return " ".join(b for node in _whole([max(own)[2] if own else root]) for b in blocks(node))


def host_of(url):
    """The host in lower case, without user and port; empty for null and relative addresses."""
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def host_paths(pages: DataFrame, url: str = "url", html: str = "html", best: int = 5) -> DataFrame:
    """``(host, paths)``: the ``best`` generalised paths of each host, most votes first, ties by path.

    All containers of all pages vote; only sums by host and path are shuffled, a hot host's from each task once.
    """
    slim = pages.where(F.col(html).isNotNull()).select(host_of(F.col(url)).alias("host"), F.col(html).alias("page")).where("host <> ''")

    def vote(batches):
        cast: dict[tuple[str, str], int] = {}

        def sums():
            columns = list(zip(*((h, p, n) for (h, p), n in cast.items()), strict=True)) or [(), (), ()]
            return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.string()), pa.array(columns[1], pa.string()), pa.array(columns[2], pa.int64())], ["host", "path", "n"])

        for b in batches:
            for h, page in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                for path, share in votes(page):
                    if n := round(share * 1000):
                        cast[h, path] = cast.get((h, path), 0) + n
            if len(cast) > 100_000:
                yield sums()
                cast = {}
        yield sums()
        release()

    summed = slim.mapInArrow(vote, "host string, path string, n long").groupBy("host", "path").agg(F.sum("n").alias("votes"))
    salt = F.pmod(F.xxhash64("path"), F.lit(SALTS))
    top = lambda c: F.slice(F.sort_array(c), 1, best)
    some = summed.groupBy("host", salt.alias("salt")).agg(top(F.collect_list(F.struct((-F.col("votes")).alias("v"), "path"))).alias("top"))  # a host may have very many paths
    return some.groupBy("host").agg(F.transform(top(F.flatten(F.collect_list("top"))), lambda x: x["path"]).alias("paths"))


def main_text(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html", best: int = 5, most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``(page_id, url, text, n_chars)`` of every row: blocks in page order, joined by one space.

    Null and empty pages give an empty text; repeated rows stay rows; a page without tags is its own text; other columns may
    have any names. The result is the same on both sides of ``most_bytes``, the size up to which winning paths go to all tasks.
    """
    spark = with_checkpoints(pages.sparkSession)
    rows = pages.select(F.col(page_id).alias("page_id"), F.col(url).alias("url"), F.coalesce(F.col(html), F.lit("")).alias("page"), host_of(F.col(url)).alias("host"))
    found = host_paths(pages, url, html, best).checkpoint()
    size = found.agg(F.sum(F.length("host") + F.length(F.concat_ws("", "paths")) + 32)).first()[0] or 0
    kind = rows.schema["page_id"].dataType.simpleString()
    shape = f"page_id {kind}, url string, text string"
    if size <= most_bytes:
        held = spark.sparkContext.broadcast({r["host"]: r["paths"] for r in found.collect()})  # no more than ``most_bytes``
        joined = rows
        of = lambda column: [held.value.get(h, []) for h in column]
    else:
        salted = found.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")).join(salted, ["host", "salt"], "left").select("page_id", "url", "page", "paths")
        of = lambda column: [p or [] for p in column]

    def run(batches):
        for b in batches:
            texts = [extract(page, paths) for page, paths in zip(b.column(2).to_pylist(), of(b.column(3).to_pylist()), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string())], ["page_id", "url", "text"])
        release()

    return joined.mapInArrow(run, shape).withColumn("n_chars", F.length("text").cast("long"))


def op7_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    return main_text(read_table(spark, sf_dir, "pages"))
