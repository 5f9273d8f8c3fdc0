"""Main text of web pages, with site templates removed.

A page is read into a tree of elements, forgivingly (unclosed and misnested
tags as browsers treat them, as far as text is concerned) and in time linear in
its length.  Elements that say themselves that they are menus, headers,
footers, sidebars, notices, adverts, forms, scripts or comments by readers are
left out: by tag, role, or a class name or id all of whose parts are such words
(`site-header`, `cookie-banner`; not `article-header` or `related-work`).
Inside `article` and `main` a header is kept, as it holds the title.

What pages do not say themselves is found by repetition: every element subtree
with text is hashed, Spark counts the pages of each host that hold it, and
subtrees found on many pages of the host are deleted, inside `article` and
`main` elements too; there, only whole blocks (no inline element, list item,
row or cell alone, which are parts of a sentence, list or table).  Pages of one
host with the same text count once: copies of an article are no template.  So
do, for what lies in an outermost `article` or `main` that holds half of the
page's text or more, articles with the same text, whatever stands around them.

A subtree recurs if it is on at least `least_pages` pages and, of the host's
pages, on at least `share` or on at least `many_pages`.

Block elements end a block; white space inside a block becomes one space;
blocks are joined by a line feed.  Character references are decoded.

Edge cases: a null or empty page gives an empty text, as does one without
visible text; a page without a host is judged by its own markup alone;
repeated rows count as pages of their own; unclosed tags and quotes, and nesting of any
depth, cost no more than other pages of their length; an empty table gives no rows; extra
columns are not read.
"""

from __future__ import annotations

import html
import re
from dataclasses import dataclass, field

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pieces, stored

LEAST_PAGES = 5
SHARE = 0.1
MANY_PAGES = 100
#: Recurring subtrees (16 bytes and a host name each) up to which their table is sent to every task.
BROADCAST_ROWS = 200_000

# Fixed lists of HTML element names.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split()
)
#: Blocks that are part of a list or table: inside articles they go only with the whole of it.
PARTS = frozenset("caption dd dt legend li tbody td tfoot th thead tr".split())
DROPPED = frozenset("head script style noscript template iframe object embed svg math canvas audio video map nav header footer aside form button select textarea input label option dialog menu title".split())
#: A start tag of these closes an open element of the second list, up to the nearest element of the third.
CLOSES = {
    **dict.fromkeys("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split(), (frozenset({"p"}), frozenset({"button", "table", "td", "th", "caption"}))),
    "li": (frozenset({"li"}), frozenset({"ul", "ol", "menu", "dir"})),
    "dt": (frozenset({"dt", "dd"}), frozenset({"dl"})),
    "dd": (frozenset({"dt", "dd"}), frozenset({"dl"})),
    "tr": (frozenset({"tr", "td", "th"}), frozenset({"table"})),
    "td": (frozenset({"td", "th"}), frozenset({"tr", "table"})),
    "th": (frozenset({"td", "th"}), frozenset({"tr", "table"})),
    "option": (frozenset({"option"}), frozenset({"select"})),
}
# Words that mark what is no article, in class names, ids and roles.
NOT_ARTICLE = frozenset(
    "ad ads advert adverts advertisement advertisements advertising adsense sponsor sponsored promo promoted promotion "
    "nav navbar navigation menu menus menubar breadcrumb breadcrumbs pagination pager skip "
    "header masthead topbar banner footer colophon contentinfo sidebar aside complementary rail "
    "notice notices cookie cookies consent gdpr popup modal dialog alertdialog overlay toast newsletter subscribe subscription paywall "
    "form login signup search searchbox "
    "comment comments commentlist disqus replies respond".split()
)
#: Words that may stand beside those in one name without changing what it says.
NEUTRAL = frozenset("site page global main top bottom left right primary secondary box bar wrap wrapper container inner outer list area section block widget link links slot unit".split())
#: What may hold an article's title.
TITLES = frozenset("header masthead topbar banner".split())
START = re.compile(r"<(?:!--|[!?]|/?[A-Za-z])")
TAG_NAME = re.compile(r"/?([A-Za-z][^\s/>]*+)")
QUOTE_OR_END = re.compile(r"=\s*+([\"'])|>")
ATTRIBUTE = re.compile(r"""([^\s"'=/]++)(?:\s*+=\s*+(?:"([^"]*)"|'([^']*)'|([^\s"'>]++)))?+""")
NAME_PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|[0-9]+")
RAW_END = {tag: re.compile(rf"</{tag}(?=[\s/>])|\Z", re.I) for tag in RAW}
HOST = r"(?i)^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)"


@dataclass(slots=True)
class Node:
    tag: str
    attrs: str = ""
    children: list = field(default_factory=list)  # nodes and (undecoded) strings


class _Open:
    """The open elements, and where in the stack each tag stands, so that no end tag searches the stack."""

    def __init__(self, root: Node):
        self.stack, self.at = [root], {}

    def last(self, tag: str) -> int:
        at = self.at.get(tag)
        return at[-1] if at else 0

    def push(self, node: Node) -> None:
        self.at.setdefault(node.tag, []).append(len(self.stack))
        if node.tag in BLOCK:
            self.at.setdefault("#block", []).append(len(self.stack))
        self.stack.append(node)

    def cut(self, k: int) -> None:
        """Closes the elements from place `k` on."""
        while len(self.stack) > k:
            node = self.stack.pop()
            self.at[node.tag].pop()
            if node.tag in BLOCK:
                self.at["#block"].pop()

    def add(self, child) -> None:
        self.stack[-1].children.append(child)


def _tag_end(page: str, at: int) -> int:
    """Place of the > that ends the tag that starts before `at`; -1 without one.  An unclosed quote is an ordinary character."""
    while (m := QUOTE_OR_END.search(page, at)) is not None:
        if m[1] is None:
            return m.start()
        close = page.find(m[1], m.end())
        if close < 0:
            return page.find(">", m.end())
        at = close + 1
    return -1


def parse(page: str) -> Node:
    """The page's element tree."""
    root = Node("#root")
    open_ = _Open(root)
    at, n = 0, len(page)
    while at < n:
        m = START.search(page, at)
        begin = m.start() if m else n
        if begin > at:
            open_.add(page[at:begin])
        if m is None:
            break
        if m[0] == "<!--":
            end = page.find("-->", begin + 4)
            at = n if end < 0 else end + 3
            continue
        name = TAG_NAME.match(page, begin + 1)
        end = page.find(">", begin) if name is None else _tag_end(page, name.end())
        if end < 0:
            break  # a tag that never ends
        at = end + 1
        if name is None:
            continue
        tag = name[1].lower()
        if page[begin + 1] == "/":
            k = open_.last(tag)
            if tag == "p" and not k:
                open_.add(Node("p"))
            elif k and (tag in BLOCK or k > open_.last("#block")):  # a stray end tag of an inline element closes no block
                open_.cut(k)
            continue
        if tag in CLOSES:
            closed, bounds = CLOSES[tag]
            k = max(map(open_.last, closed))
            if k and k > max(map(open_.last, bounds)):
                open_.cut(k)
        attrs = page[name.end() : end]
        node = Node(tag, attrs)
        open_.add(node)
        if tag in VOID or attrs.endswith("/") and tag not in BLOCK and tag not in RAW:
            continue
        if tag in RAW:
            stop = RAW_END[tag].search(page, at).start()
            node.children.append(page[at:stop])
            end = page.find(">", stop)
            at = n if end < 0 else end + 1
            continue
        open_.push(node)
    return root


def _says(name: str, inside: bool) -> bool:
    """Whether a class name, id or role is made up of words that mark what is no article."""
    parts = [p.lower() for p in NAME_PART.findall(name)]
    marks = [p for p in parts if p in NOT_ARTICLE]
    if not marks or any(p not in NOT_ARTICLE and p not in NEUTRAL and not p.isdigit() for p in parts):
        return False
    return not (inside and all(p in TITLES for p in marks))


def says_no_article(node: Node, inside: bool = False) -> bool:
    """Whether the element's tag, role, class or id marks it as no part of an article (`inside`: it lies in one)."""
    if node.tag in DROPPED:
        return not (inside and node.tag == "header")
    if not node.attrs or node.tag in ("html", "body", "article", "main"):
        return False
    for m in ATTRIBUTE.finditer(node.attrs):
        name, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if name in ("class", "role") and any(_says(x, inside) for x in value.split()) or name == "id" and _says(value, inside):
            return True
        if name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none", value):
            return True
    return False


def subtree_hashes(root: Node) -> dict[int, int]:
    """Hash of every element subtree with text that may be deleted, by the node's identity."""
    found: dict[int, int] = {}
    stack: list[tuple[Node, bool, bool]] = [(root, False, False)]
    parts: dict[int, tuple[str, bool]] = {}
    while stack:
        node, inside, done = stack.pop()
        if not done:
            stack.append((node, inside, True))
            within = inside or node.tag in ("article", "main")
            stack += [(c, within, False) for c in node.children if isinstance(c, Node)]
            continue
        text = [node.tag, re.sub(r"\s+", " ", node.attrs).strip()]
        shown = False
        for c in node.children:
            if isinstance(c, str):
                text.append(" ".join(c.split()))
                shown = shown or bool(text[-1])
            else:
                digest, holds = parts.pop(id(c))
                text.append(digest)
                shown = shown or holds
        d = xxhash.xxh3_64_digest("\x1f".join(text).encode("utf-8", "surrogatepass"))
        parts[id(node)] = d.hex(), shown
        if shown and node is not root and (not inside or node.tag in BLOCK and node.tag not in PARTS):
            found[id(node)] = int.from_bytes(d, "big") - (1 << 63)
    return found


def page_subtrees(root: Node) -> list[tuple[str, bytes, list[int]]]:
    """The page's different subtrees, each under the text by which its copies count once.

    One entry ``page`` with the digest of the page's text, and an entry
    ``article`` for each outermost article that holds half of that text or more.
    """
    hashes = subtree_hashes(root)
    digest = lambda text: xxhash.xxh3_128_digest(text.encode("utf-8", "surrogatepass"))
    text = main_text(root)
    groups: list[tuple[str, bytes, set[int]]] = [("page", digest(text), set())]
    stack = [(root, 0, False)]
    while stack:
        node, group, inside = stack.pop()
        if not inside and node.tag in ("article", "main"):
            inside = True
            own = _blocks(node, {}, frozenset())
            if own and 2 * len(own) >= len(text):
                group = len(groups)
                groups.append(("article", digest(own), set()))
        if id(node) in hashes:
            groups[group][2].add(hashes[id(node)])
        stack += [(c, group, inside) for c in node.children if isinstance(c, Node)]
    seen: set[int] = set()
    out = []
    for kind, d, held in reversed(groups):
        out.append((kind, d, list(held - seen)))
        seen |= held
    return out


def main_text(root: Node, recurring=frozenset()) -> str:
    """Text of the page without marked elements and without subtrees in `recurring`."""
    return _blocks(root, subtree_hashes(root) if recurring else {}, recurring)


def _blocks(top: Node, hashes: dict[int, int], recurring) -> str:
    blocks: list[str] = []
    inline: list[str] = []

    def close():
        text = " ".join(html.unescape("".join(inline)).split())
        inline.clear()
        if text:
            blocks.append(text)

    stack: list = [(top, top.tag in ("article", "main"))]
    while stack:
        item, inside = stack.pop()
        if isinstance(item, str):
            inline.append(item)
        elif item is None:
            close()
        elif item is not top and (says_no_article(item, inside) or hashes.get(id(item)) in recurring):
            if item.tag in BLOCK:
                close()
        else:
            if item.tag == "br":
                inline.append(" ")
            if item.tag in BLOCK:
                close()
                stack.append((None, inside))
            inside = inside or item.tag in ("article", "main")
            stack += [(c, inside) for c in reversed(item.children)]
    close()
    return "\n".join(blocks)


def recurring_subtrees(pages: DataFrame, html_col: str, url_col: str, least_pages: int = LEAST_PAGES, share: float = SHARE, many_pages: int = MANY_PAGES) -> DataFrame:
    """``host``, ``subtree`` of the subtrees to delete."""

    def run(batches):
        for b in pieces(batches):
            rows = [(host, *x) for host, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) for x in page_subtrees(parse(t or ""))]
            kinds = (pa.string(), pa.string(), pa.binary(), pa.list_(pa.int64()))
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["host", "kind", "digest", "subtrees"])

    hosts = pages.select(F.regexp_extract(F.coalesce(F.col(url_col), F.lit("")), HOST, 1).alias("host"), F.col(html_col)).filter("host != ''")
    read = hosts.mapInArrow(run, "host string, kind string, digest binary, subtrees array<long>")
    seen = stored(read.dropDuplicates(["host", "kind", "digest"]), "subtrees")
    held = seen.filter("kind = 'page'").groupBy("host").agg(F.count(F.lit(1)).alias("pages"))
    counts = seen.select("host", F.explode("subtrees").alias("subtree")).groupBy("host", "subtree").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= least_pages)
    return counts.join(held, "host").filter((F.col("n") >= share * F.col("pages")) | (F.col("n") >= many_pages)).select("host", "subtree")


#: Parts that the pages of one host and subtree are spread over in a join.
SALT = 16


def _marked_pages(slim: DataFrame, often: DataFrame) -> DataFrame:
    """``__id``, ``__html`` (hash), ``subtrees``: the recurring subtrees of every page that has any.

    Pages meet the table by host, subtree and a salt, each with only its own
    subtrees; what comes back for a page is no more than it holds.
    """

    def run(batches):
        for b in pieces(batches):
            row, found = [], []
            for k, t in enumerate(b.column(3).to_pylist()):
                held = set(subtree_hashes(parse(t or "")).values())
                row += [k] * len(held)
                found += held
            at = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(k).take(at) for k in range(3)), pa.array(found, pa.int64())], names=["__id", "__html", "host", "subtree"])

    kind = dict(slim.dtypes)["page_id"]
    keyed = slim.filter("host != ''").select(F.col("page_id").alias("__id"), F.xxhash64("html").alias("__html"), "host", "html")
    held = keyed.mapInArrow(run, f"__id {kind}, __html long, host string, subtree long").withColumn("salt", F.pmod("__html", F.lit(SALT)))
    salted = often.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALT - 1).cast("long"))))
    return held.join(salted, ["host", "subtree", "salt"]).groupBy("__id", "__html").agg(F.collect_set("subtree").alias("subtrees"))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least_pages: int = LEAST_PAGES, share: float = SHARE, many_pages: int = MANY_PAGES, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """``page_id``, ``url``, ``text`` of every page."""
    often = stored(recurring_subtrees(pages, html_col, url_col, least_pages, share, many_pages), "recurring")
    host = F.regexp_extract(F.coalesce(F.col(url_col), F.lit("")), HOST, 1)
    slim = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), host.alias("host"))
    kind = dict(slim.dtypes)
    if often.count() <= broadcast_rows:
        table: dict[str, set[int]] = {}
        for row in often.toLocalIterator():
            table.setdefault(row.host, set()).add(row.subtree)
        shared = pages.sparkSession.sparkContext.broadcast(table)
        lists = lambda b: (shared.value.get(h, frozenset()) for h in b.column(3).to_pylist())
    else:
        marks = _marked_pages(slim, often)
        slim = slim.withColumn("__hash", F.xxhash64("html")).join(marks, F.col("page_id").eqNullSafe(F.col("__id")) & (F.col("__hash") == F.col("__html")) & (F.col("host") != ""), "left").select("page_id", "url", "html", "subtrees")
        lists = lambda b: (frozenset(x or ()) for x in b.column(3).to_pylist())

    def run(batches):
        for b in pieces(batches):
            texts = [main_text(parse(t or ""), r) for t, r in zip(b.column(2).to_pylist(), lists(b), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string())], names=["page_id", "url", "text"])

    return slim.mapInArrow(run, f"page_id {kind['page_id']}, url {kind['url']}, text string")


def op3_site_template_removal(spark, sf_dir) -> DataFrame:
    """Main texts of all pages."""
    texts = extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    return texts.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
