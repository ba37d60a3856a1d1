"""Main text of HTML pages by site style trees.

The element trees of all pages of a host are merged: a node's styles are the ways in which pages lay
out its children, and each style has child nodes of its own. The importance of a node combines the
entropy of its styles over the host's pages with the importance of the nodes below them; that of a
leaf falls as its lines recur on the host. The lines that recur in branches of low importance are
removed from each page, as are branches that HTML itself marks as no content (scripts, forms, navigation,
adverts, reader comments), which is all there is to go by on a host's only page.

Nodes are numbered by hashes of their parent's style and their place in it, so that time and
memory are linear in a page's size however deep its elements nest; blocks deeper than ``DEEPEST`` count
to their ancestor at that depth. Copies of one page count as one page of their host, and entropies are taken as if ``PRIOR``
more pages with contents of their own had been seen, so that few pages prove little at any size.
"""

from __future__ import annotations

import re
import struct
from collections import Counter
from collections.abc import Iterator
from html.parser import HTMLParser

import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import materialize

# HTML element names by role, and words that mark boilerplate in class, id and role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIPPED = frozenset(
    "script style noscript template head nav footer aside form button select textarea option datalist iframe object svg canvas audio video map dialog menu input label fieldset".split()
)
BLOCKS = frozenset(
    "address article blockquote body caption center dd details div dl dt fieldset figcaption figure h1 h2 h3 h4 h5 h6 header hgroup html li main ol p pre section summary table tbody td tfoot th thead tr ul hr".split()
)
CLOSES_P = BLOCKS - frozenset("body html td th tr caption tbody thead tfoot".split())
_NOT_P = BLOCKS - {"p"}
BOILER = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisement|advertising|sponsor(?:ed)?|promo(?:tion)?s?|banner|nav|navbar|navigation|menu|breadcrumbs?|header|masthead|footer|sidebar|side|widget|related|recommended|share|sharing|social|"
    r"comments?|commentlist|respond|replies|reply|disqus|cookies?|consent|gdpr|notices?|alert|newsletter|subscribe|subscription|signup|login|popup|modal|overlay|skip|pagination|pager|copyright|legal)(?:$|[\s_-])",
    re.I,
)
_SPACE = re.compile(r"[ \t\n\r\f\v\x85\xa0  -     　]+")


class Node:
    """An element: its signature, children (elements and strings) and whether HTML marks it as no content."""

    __slots__ = ("children", "kept", "place", "runs", "sig", "tag")

    def __init__(self, tag: str, sig: str, kept: bool):
        self.tag, self.sig, self.kept, self.children = tag, sig, kept, []
        self.place, self.runs = 0, None


class _Builder(HTMLParser):
    """A forgiving tree builder: unclosed elements end with what encloses them."""

    CDATA_CONTENT_ELEMENTS = ("script", "style")

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.root = Node("#root", "#root", True)
        self.stack = [self.root]
        self.articles = [0]  # how many articles enclose each open element
        self.open: Counter = Counter()

    def handle_starttag(self, tag, attrs):
        a = {k: v or "" for k, v in attrs}
        marks = f"{a.get('class', '')} {a.get('id', '')} {a.get('role', '')}".strip()
        in_article = self.articles[-1] > 0
        kept = tag not in SKIPPED and not (tag == "header" and not in_article) and "hidden" not in a
        if kept and marks and tag not in ("html", "body", "article", "main"):
            kept = not BOILER.search(marks)
        if tag in CLOSES_P:
            self._close_open("p", _NOT_P)
        if tag == "li":
            self._close_open("li", frozenset(("ul", "ol", "menu")))
        elif tag in ("dd", "dt"):
            self._close_open("dd", frozenset(("dl",)))
            self._close_open("dt", frozenset(("dl",)))
        elif tag in ("td", "th"):
            self._close_open("td", frozenset(("tr", "table")))
            self._close_open("th", frozenset(("tr", "table")))
        elif tag == "tr":
            self._close_open("tr", frozenset(("table",)))
        node = Node(tag, f"{tag}.{'.'.join(sorted(a.get('class', '').lower().split()))}" if a.get("class") else tag, kept)
        self.stack[-1].children.append(node)
        if tag not in VOID:
            self.stack.append(node)
            self.articles.append(self.articles[-1] + (tag in ("article", "main")))
            self.open[tag] += 1

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID and tag in ("script", "style"):
            self.handle_endtag(tag)

    def _cut(self, i: int) -> None:
        """Close the open elements from the ``i``-th on."""
        for n in self.stack[i:]:
            self.open[n.tag] -= 1
        del self.stack[i:], self.articles[i:]

    def handle_endtag(self, tag):
        if not self.open[tag]:
            return
        for i in range(len(self.stack) - 1, 0, -1):
            if self.stack[i].tag == tag:
                self._cut(i)
                return
            if self.stack[i].tag in ("article", "main", "body", "table", "nav", "footer", "aside", "section") and tag not in BLOCKS and tag not in SKIPPED:
                return  # a stray inline end tag closes nothing outside its block

    def _close_open(self, tag: str, limit: frozenset[str]) -> None:
        if not self.open[tag]:
            return
        for i in range(len(self.stack) - 1, 0, -1):
            if self.stack[i].tag == tag:
                self._cut(i)
                return
            if self.stack[i].tag in limit:
                return

    def handle_data(self, data):
        self.stack[-1].children.append(data)


def parse(page: str | None) -> Node:
    """Element tree of a page; null and empty pages have an empty root."""
    b = _Builder()
    if page:
        b.feed(page)
        b.close()
    return b.root


# Elements without text of their own on a page, further blocks of a site's frame, and elements of running text.
RAW = frozenset("script style noscript template head datalist iframe object svg canvas audio video map".split())
FRAME = BLOCKS | frozenset("nav footer aside form menu dialog".split())
TEXTUAL = frozenset("h1 h2 h3 h4 h5 h6 p li dd dt pre blockquote td th figcaption caption address".split())

DEEPEST = 24
PRIOR = 8
GAMMA = 0.9  # weight of a single style's children against the node's own entropy


def _number(*parts: int | str) -> int:
    """A 63-bit number for a node or style from its parent's."""
    raw = b"".join(struct.pack("<q", x) if isinstance(x, int) else x.encode("utf-8", "surrogatepass") for x in parts)
    return xxhash.xxh64_intdigest(raw) >> 1


def _line(pieces: list[str]) -> str:
    return _SPACE.sub(" ", "".join(pieces)).strip()


def _items(node: Node) -> list:
    """What a block holds in order: blocks, and runs of text as lists of their pieces; inline elements are looked through."""
    out: list = []
    todo = list(reversed(node.children))
    while todo:
        c = todo.pop()
        if isinstance(c, Node) and (c.tag in RAW or c.tag in FRAME):
            if c.tag in FRAME:
                out.append(c)
        elif isinstance(c, Node):
            if c.tag == "br":
                c.children = [" "]
            todo.extend(reversed(c.children))
        elif out and isinstance(out[-1], list):
            out[-1].append(c)
        elif c.strip():
            out.append([c])
    return out


def merged_places(root: Node) -> Iterator[tuple[str, int, int, int, str]]:
    """Number a page's blocks (``place``, and ``runs`` of text beside blocks) and give what they add to their host's tree.

    Rows are ``(kind, place, depth, value, line)``: n a node with its parent's style, s a node's style,
    c a line of a leaf.
    """
    root.place = _number("root")
    yield "n", root.place, 0, 0, ""
    todo = [(root, 0)]
    while todo:
        node, depth = todo.pop()
        items = _items(node)
        blocks = [x for x in items if isinstance(x, Node)]
        if depth >= DEEPEST:
            for x in blocks:
                x.place = node.place
                todo.append((x, depth))
            for x in items:
                if isinstance(x, list) and (t := _line(x)):
                    yield "c", node.place, DEEPEST, 0, t
            continue
        if not blocks:
            yield "s", node.place, depth, _number(node.place, "#leaf"), ""
            for x in items:
                if t := _line(x):
                    yield "c", node.place, depth, 0, t
            continue
        sigs: list[str] = []
        at = []
        for x in items:
            sig = x.sig if isinstance(x, Node) else "#text"
            if not sigs or sigs[-1] != sig:
                sigs.append(sig)
            at.append(len(sigs) - 1)
        style = _number(node.place, *sigs)
        yield "s", node.place, depth, style, ""
        node.runs = {}
        for x, i in zip(items, at, strict=True):
            place = _number(style, i)
            yield "n", place, depth + 1, style, ""
            if isinstance(x, Node):
                x.place = place
                todo.append((x, depth + 1))
            else:
                node.runs[id(x[0])] = place
                if t := _line(x):
                    yield "c", place, depth + 1, 0, t


def line_number(line: str) -> int:
    return xxhash.xxh64_intdigest(line.encode("utf-8", "surrogatepass")) >> 1


def host_of(url):
    """Host of a URL column, lower case; null and broken URLs share the empty host."""
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1)), F.lit(""))


def style_trees(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Merged trees of all hosts: ``(host, place, depth, kind, value, n)``, on how many distinct pages each stands.

    ``kind`` is n for nodes (``value``: their parent's style), s for a node's styles, c for the lines of
    leaves (hashed). Counts of a task are summed before they are sent, so a host with very many pages
    sends one row per task and value. Each of several equal pages of a host counts as a share of one.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: Counter = Counter()

        def flush() -> pd.DataFrame:
            rows = [(*k, n) for k, n in seen.items()]
            seen.clear()
            return pd.DataFrame(rows, columns=["host", "place", "depth", "kind", "value", "n"])

        for b in batches:
            for host, page, w in zip(b["host"], b["html"], b["w"], strict=True):
                # a page counts once for a place's value
                first = {(host, p, d, k, line_number(t) if k == "c" else v) for k, p, d, v, t in merged_places(parse(page if isinstance(page, str) else None))}
                for x in first:
                    seen[x] += w
                if len(seen) > 200_000:
                    yield flush()
        yield flush()

    slim = pages.select(host_of(F.col(url_col)).alias("host"), F.col(html_col).alias("html"))
    slim = slim.where("html is not null and html <> ''").withColumn("_hash", F.xxhash64("html"))
    copies = slim.groupBy("host", "_hash").agg(F.count(F.lit(1)).alias("copies")).where("copies > 1")
    slim = slim.join(materialize(copies, "page-copies"), ["host", "_hash"], "left").select("host", "html", (1 / F.coalesce("copies", F.lit(1))).alias("w"))
    rows = slim.mapInPandas(run, "host string, place long, depth int, kind string, value long, n double")
    return rows.groupBy("host", "place", "depth", "kind", "value").agg(F.round(F.sum("n"), 6).alias("n"))


def importances(tree: DataFrame) -> DataFrame:
    """``(host, place, depth, parent, pages, importance)`` of all nodes, from the deepest up.

    A leaf's importance is one less the mean, over its lines, of log n / log (m + PRIOR) for a line on
    n of the node's m pages. A node with l styles has (1 - GAMMA^l) of its styles' entropy, as a share of
    log (m + PRIOR), and GAMMA^l of the mean importance below, by style and then by child. Everything comes
    from sums over counts, so a large host costs no more per task than its distinct values.
    """
    by = ["host", "place"]
    nodes = tree.where("kind = 'n'").groupBy(*by).agg(F.sum("n").alias("pages"), F.min("depth").alias("depth"), F.min("value").alias("parent"))
    styles = tree.where("kind = 's'").select(*by, F.col("value").alias("style"), "n")
    lines = tree.where("kind = 'c'").groupBy(*by).agg(F.sum("n").alias("ln"), F.sum(F.col("n") * F.log("n")).alias("lnl"))
    shape = styles.groupBy(*by).agg(F.sum("n").alias("sn"), F.sum(F.col("n") * F.log("n")).alias("snl"), F.count(F.lit(1)).alias("l"))
    base = F.log(F.col("pages") + PRIOR)
    n = nodes.join(lines, by, "left").join(shape, by, "left").select(
        *by, "depth", "parent", "pages", "l", "sn", (1 - F.coalesce(F.col("lnl") / F.col("ln"), F.lit(0.0)) / base).alias("leaf"),
        ((F.log("sn") - F.col("snl") / F.col("sn")) / base).alias("own"),
    )
    n, styles = materialize(n, "tree-nodes"), materialize(styles, "tree-styles")
    deepest, out, below = n.agg(F.max("depth")).first()[0] or 0, None, None
    for depth in range(deepest, -1, -1):
        here = n.where(F.col("depth") == depth)
        mean = styles.join(here.select(*by), by, "left_semi")
        if below is not None:
            kids = below.groupBy("host", F.col("parent").alias("style")).agg(F.avg("importance").alias("kids"))
            mean = mean.join(kids, ["host", "style"], "left")
        else:
            mean = mean.withColumn("kids", F.lit(None).cast("double"))
        # a style without children of its own is the leaf's
        mean = mean.join(here.select(*by, "leaf"), by).groupBy(*by).agg(F.sum(F.col("n") * F.coalesce("kids", "leaf")).alias("sum"))
        own = F.pow(F.lit(GAMMA), F.col("l"))
        got = here.join(mean, by, "left").withColumn("importance", F.when(F.col("l").isNull(), F.col("leaf")).otherwise((1 - own) * F.col("own") + own * F.col("sum") / F.col("sn")))
        below = materialize(got.select(*by, "depth", "parent", "pages", F.round("importance", 9).alias("importance")), "tree-level")
        out = below if out is None else out.unionByName(below)
    return out


def low_importance(tree: DataFrame, importance: float = 0.2) -> DataFrame:
    """What to remove, ``(host, drop)``: for every host that has some, numbers of lines at their places.

    A branch is noise if its root's importance lies under the bound. Of the lines in it those go
    that recur there: on two pages at least, and on the square root of the place's pages. So there
    are no more of them to a host than the square root of its pages, times its templates; a line that
    a page has for itself stays wherever it stands.
    """
    nodes = materialize(importances(tree), "importances")
    low = nodes.where(F.col("importance") < importance).select("host", "place")
    found = low
    edges = tree.where("kind = 's'").select("host", F.col("place").alias("up"), F.col("value").alias("parent"))
    links = materialize(nodes.join(edges, ["host", "parent"]).select("host", "place", "depth", "up"), "tree-links")
    deepest = nodes.agg(F.max("depth")).first()[0] or 0
    for depth in range(1, deepest + 1):  # what lies below a branch goes with it
        step = links.where(F.col("depth") == depth).join(found.select("host", F.col("place").alias("up")), ["host", "up"], "left_semi").select("host", "place")
        found = materialize(found.unionByName(step).distinct(), "tree-low")
    lines = tree.where("kind = 'c' and n >= 2").join(found, ["host", "place"], "left_semi").join(nodes.select("host", "place", "pages"), ["host", "place"])
    lines = lines.where(F.col("n") >= F.sqrt("pages")).select("host", F.col("place").bitwiseXOR(F.col("value")).alias("key"))
    return lines.groupBy("host").agg(F.sort_array(F.collect_set("key")).alias("drop"))


def main_text(page: str | None, drop: frozenset[int] = frozenset()) -> str:
    """Text blocks of a page's content joined by newlines, without the lines in ``drop``.

    Headings and running text of the page's article stay even if the host repeats them.
    """
    root = parse(page)
    top = _article(root)
    if not drop:
        return "\n".join(t for t, _, _ in _blocks(top, root is not top))
    for _ in merged_places(root):
        pass
    return "\n".join(t for t, place, safe in _blocks(top, root is not top) if safe or place ^ line_number(t) not in drop)


def _blocks(top: Node, article: bool) -> Iterator[tuple[str, int, bool]]:
    """Lines of the kept blocks under ``top`` with the places of their leaves, and whether they are an article's running text."""
    pieces: list[str] = []
    first: list = [0, False]  # place and safety of the line's first text
    todo: list = [(top, top, False)]
    while todo:
        n, block, leaving = todo.pop()
        ends = leaving or (isinstance(n, Node) and n.tag in BLOCKS and (n.kept or n is top))
        if ends:
            if t := _line(pieces):
                yield t, first[0], first[1]
            pieces.clear()
        if leaving:
            continue
        if isinstance(n, str):
            if n.strip() and not any(x.strip() for x in pieces):
                first[0] = block.runs.get(id(n), 0) if block.runs else block.place
                first[1] = article and block.tag in TEXTUAL
            pieces.append(n)
        elif n.kept or n is top:
            if n.tag == "br":
                pieces.append(" ")
                continue
            if n.tag in BLOCKS:
                block = n
                todo.append((n, n, True))
            todo.extend((c, block, False) for c in reversed(n.children))
    if t := _line(pieces):
        yield t, first[0], first[1]


def _own_text(node: Node) -> str:
    """All text below a node."""
    parts, todo = [], [node]
    while todo:
        n = todo.pop()
        if isinstance(n, str):
            parts.append(n)
        else:
            todo.extend(reversed(n.children))
    return _SPACE.sub(" ", " ".join(parts)).strip()


def _article(root: Node) -> Node:
    """The article or main element of most text, if there is one; else the whole page."""
    best, most, todo = root, 0, [root]
    while todo:
        n = todo.pop()
        for c in n.children:
            if isinstance(c, Node) and c.kept:
                if c.tag in ("article", "main"):
                    size = len(_own_text(c))
                    if size > most:
                        best, most = c, size
                else:
                    todo.append(c)
    return best


def extract(pages: DataFrame, url_col: str = "url", html_col: str = "html", importance: float = 0.2) -> DataFrame:
    """All rows and columns of ``pages`` with ``text`` and ``n_chars`` (code points) of the main text.

    Null, empty and broken HTML gives an empty text or what can be read of it; pages of unknown host
    form a host of their own. An empty table gives an empty result, repeated rows repeat, and equal
    pages have equal texts on a host. Columns named text or n_chars are replaced; other columns may have any name.
    """
    tree = materialize(style_trees(pages, url_col, html_col), "style-trees")
    drops = materialize(low_importance(tree, importance), "style-drops")
    kept = [c for c in pages.columns if c not in ("text", "n_chars")]
    rows = pages.select(F.struct(*(F.col(f"`{c}`") for c in kept)).alias("row"), F.col(html_col).alias("html"), host_of(F.col(url_col)).alias("host"))
    rows = rows.join(drops, "host", "left")

    def run(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for page, drop in batches:
            yield pd.Series([main_text(p if isinstance(p, str) else None, frozenset(d) if d is not None else frozenset()) for p, d in zip(page, drop, strict=True)], dtype=object)

    udf = F.pandas_udf(run, "string")
    out = rows.withColumn("text", udf(F.col("html"), F.col("drop"))).select("row", "text")
    return out.select(*(F.col("row").getField(c).alias(c) for c in kept), "text", F.length("text").cast("long").alias("n_chars"))


def main_texts(spark, sf_dir: str) -> DataFrame:
    """Query op9: main text of all pages."""
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")).select("page_id", "url", "text", "n_chars")
