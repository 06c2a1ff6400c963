"""Main text of web pages: element subtrees that recur across a host's pages go, then menus, adverts and the like.

Two Arrow passes with one Spark count between them. The first parses each whole page and emits a 64-bit hash of every
element subtree that carries text (tag, attributes but links, words), once per page; Spark counts pages per (host,
hash), with partial sums before the shuffle. A subtree on at least `least_pages` pages, and on `least_share` of its host's
distinct pages or on `enough` of them, is the site's template. The second pass joins each page with its own host's template hashes, deletes those
subtrees, then deletes elements that are not the article by tag, role or a word of their class or id (never one that holds a
marked article, and by no name at all where nothing else of the page would be left), and joins the remaining blocks; where
the page marks its articles (article, main), only those count, and recurring subtrees go inside them as well.

The page's outermost elements (html, body, main, article) and the hashes of pages that are whole copies of one another
do not count: identical pages are counted once, so a page that many others copy keeps its text. Null or empty html
gives an empty text; a null url is a host of its own; repeated rows are each extracted; an empty table gives an empty
result. Unclosed, misnested and unknown tags are read as browsers do in the main: a new paragraph or list item closes
the open one, an end tag closes what is open inside it, an end tag without a start is ignored.
"""

from __future__ import annotations

import html
import re
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_arrow, staged, table

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_ATTR = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
# Element kinds of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noscript iframe noembed noframes template".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr nobr".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tbody", "tfoot"}, "tbody": {"thead", "tbody"}, "tfoot": {"tbody"}}
FENCE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}
BOILER_TAGS = frozenset("nav header footer aside form script style noscript template iframe button select option textarea input svg canvas object embed audio video map menu dialog head title math".split())
BOILER_ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alert alertdialog toolbar tablist".split())
BOILER_WORDS = frozenset("ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner nav navbar navigation menu submenu breadcrumb breadcrumbs header masthead footer sidebar aside widget cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription signup login comment comments respond disqus share sharing social related recommended pagination pager toolbar skip hidden".split())
OUTER = frozenset("html body main article".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
PLAIN_IN_HEADINGS = frozenset("header masthead banner notice notices".split())
LAYOUT = re.compile(r"^(?:no|has|have|with|without|hide|show|is|not)[-_]|[-_](?:open|opened|closed|enabled|disabled|on|off|left|right|layout|page|active|visible)$")


@dataclass
class Node:
    tag: str
    boiler: bool
    seed: int
    named: bool = False  # a class or id says that it is boilerplate
    children: list = field(default_factory=list)  # nodes, or text; "\n" alone breaks a block
    hash: int = 0
    texty: bool = False


def _boiler(tag: str, attrs: dict[str, str]) -> bool:
    """By tag, role or being hidden."""
    hidden = "hidden" in attrs or attrs.get("aria-hidden", "").lower() == "true" or "display:none" in attrs.get("style", "").replace(" ", "").lower()
    return tag in BOILER_TAGS or attrs.get("role", "").lower() in BOILER_ROLES or (hidden and tag not in ("html", "body"))


def _named(tag: str, attrs: dict[str, str]) -> bool:
    """By a word of its class or id. Names that tell what a wrapper has or is (no-sidebar, comments-open) say nothing of
    its text, nor do words for a heading's look."""
    if tag in ("html", "body", "main"):
        return False
    words: set[str] = set()
    for name in re.sub(r"(?<=[a-z])(?=[A-Z])", "-", attrs.get("class", "") + " " + attrs.get("id", "")).lower().split():
        if not LAYOUT.search(name):
            words.update(re.split(r"[^a-z]+", name))
    return not (BOILER_WORDS - PLAIN_IN_HEADINGS if tag in HEADINGS else BOILER_WORDS).isdisjoint(words)


def parse(page: str) -> Node:
    """Tree of a page; explicit stack, so nesting of any depth is read."""
    root, at, n = Node("", False, 0), 0, len(page)
    stack = [root]

    def close_through(k: int) -> None:
        del stack[k:]

    while at < n:
        lt = page.find("<", at)
        if lt < 0:
            stack[-1].children.append(page[at:])
            break
        m = _TOKEN.match(page, lt)
        if not m:
            stack[-1].children.append(page[at : lt + 1])
            at = lt + 1
            continue
        if lt > at:
            stack[-1].children.append(page[at:lt])
        at = m.end()
        if not m[2]:
            if m[0].startswith("<![CDATA["):
                stack[-1].children.append(html.escape(m[0][9:].removesuffix("]]>"), quote=False))
            continue
        tag = m[2].lower()
        if m[1]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    close_through(k)
                    break
            else:
                if tag in ("p", "br"):
                    stack[-1].children.append("\n")
            continue
        if tag in CLOSES_P:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == "p":
                    close_through(k)
                    break
                if stack[k].tag not in INLINE:
                    break
        if tag in SIBLINGS:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in SIBLINGS[tag]:
                    close_through(k)
                    break
                if stack[k].tag in FENCE.get(tag, {"table"}):
                    break
        if tag in ("br", "hr", "wbr"):
            if tag != "wbr":
                stack[-1].children.append("\n")
            continue
        if tag in VOID:
            continue
        attrs = {a.lower(): next((x for x in v if x), "") for a, *v in _ATTR.findall(m[3])} if m[3].strip() else {}
        node = Node(tag, _boiler(tag, attrs), named=_named(tag, attrs), seed=xxhash.xxh3_64_intdigest("\x00".join([tag, *sorted(f"{k}={v}" for k, v in attrs.items() if k not in ("href", "src", "action"))])))
        stack[-1].children.append(node)
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}\s*[^>]*(?:>|\Z)", re.I).search(page, at)
            if tag in ("title", "textarea"):
                node.children.append(page[at : end.start() if end else n])
            at = end.end() if end else n
        elif not m[3].endswith("/") or tag not in ("svg", "path"):
            stack.append(node)
    _settle(root)
    return root


def _settle(root: Node) -> None:
    """Elements that their names call boilerplate are, but those that hold a marked article; and if nothing else of the
    page has text, names are not believed at all."""
    order, todo = [], [root]
    while todo:
        x = todo.pop()
        order.append(x)
        todo.extend(c for c in x.children if isinstance(c, Node))
    holds: set[int] = set()
    for x in reversed(order):
        if (x.tag in ("article", "main") and not x.named) or any(id(c) in holds for c in x.children if isinstance(c, Node)):
            holds.add(id(x))
    todo = [root]
    while todo:
        x = todo.pop()
        if any(isinstance(c, str) and c.strip() for c in x.children):
            break
        todo.extend(c for c in x.children if isinstance(c, Node) and not c.boiler and not (c.named and id(c) not in holds))
    else:
        return
    for x in order:
        x.boiler |= x.named and id(x) not in holds


def walk_hashes(root: Node) -> list[Node]:
    """All elements, children before parents, with `hash` and `texty` set."""
    order, todo = [], [root]
    while todo:
        x = todo.pop()
        order.append(x)
        todo.extend(c for c in x.children if isinstance(c, Node))
    order.reverse()
    for x in order:
        parts = [x.seed.to_bytes(8, "little")]
        for c in x.children:
            if isinstance(c, Node):
                parts.append(c.hash.to_bytes(8, "little"))
                x.texty |= c.texty
            elif words := c.split():
                parts.append(" ".join(words).encode("utf-8", "surrogatepass"))
                x.texty = True
        x.hash = xxhash.xxh3_64_intdigest(b"\x01".join(parts))
    return order


def articles(root: Node) -> list[Node]:
    """Outermost article or main elements that are not inside boilerplate, in page order; the page itself if none has text."""
    found, todo = [], [root]
    while todo:
        x = todo.pop()
        if x.boiler:
            continue
        if x.tag in ("article", "main"):
            found.append(x)
        else:
            todo.extend(c for c in reversed(x.children) if isinstance(c, Node))
    walk_hashes(root)
    return [x for x in found if x.texty] or [root]


def links_mostly(x: Node) -> bool:
    """Half of the words or more are inside links."""
    inside = every = 0
    todo = [(x, False)]
    while todo:
        y, linked = todo.pop()
        for c in y.children:
            if isinstance(c, Node):
                todo.append((c, linked or c.tag == "a"))
            else:
                every += (k := len(c.split()))
                inside += k * linked
    return 2 * inside >= every > 0


def own_blocks(top: Node, template: frozenset[int] | set[int]) -> set[int]:
    """Ids of recurring leaf blocks that are written like an unshared one next to them (same parent, tag and
    attributes), and of titles (h1): the text of the article, though other articles have the sentence too."""
    out, todo = set(), [top]
    while todo:
        x = todo.pop()
        inner = [c for c in x.children if isinstance(c, Node) and not c.boiler]
        todo.extend(inner)
        leaves = [c for c in inner if c.texty and c.tag not in INLINE and not _has_blocks(c)]
        alone = {c.seed for c in leaves if c.hash not in template}
        out.update(id(c) for c in leaves if (c.seed in alone or c.tag == "h1") and c.hash in template)
    return out


def _has_blocks(x: Node) -> bool:
    todo = [c for c in x.children if isinstance(c, Node)]
    while todo:
        y = todo.pop()
        if y.texty and y.tag not in INLINE:
            return True
        todo.extend(c for c in y.children if isinstance(c, Node))
    return False


def _left(top: Node, goes: Callable[[Node], bool]) -> str:
    parts: list[str] = []
    todo: list = [top]
    while todo:
        x = todo.pop()
        if isinstance(x, str):
            parts.append(html.unescape(x) if "&" in x else x)
            continue
        edge = "\n" if x.tag not in INLINE else ""
        if x.boiler or goes(x):
            parts.append(edge)
            continue
        todo.append(edge)
        todo.extend(reversed(x.children))
        todo.append(edge)
    return " ".join("".join(parts).split())


def main_text(root: Node, template: frozenset[int] | set[int]) -> str:
    """Blocks of what is left, in page order. Inside an article a recurring subtree goes too, but for words within a
    line and `own_blocks`; an article of which nothing would be left loses only subtrees that are mostly links."""
    tops = articles(root)
    recurs = lambda x: bool(x.tag) and x.tag not in OUTER and x.hash in template
    if tops == [root]:
        return _left(root, recurs)
    texts = []
    for top in tops:
        own = own_blocks(top, template) if template else set()
        text = _left(top, lambda x: recurs(x) and (links_mostly(x) or x.tag not in INLINE and id(x) not in own))  # noqa: B023
        texts.append(text or _left(top, lambda x: recurs(x) and links_mostly(x)))
    return " ".join(t for t in texts if t)


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[a-zA-Z][\w+.-]*://(?:[^/?#@]*@)?([^/:?#]*)", 1))


def host_templates(pages: DataFrame, least_pages: int, least_share: float, enough: int = 100) -> DataFrame:
    """(host, template): hashes of subtrees that recur across the host's pages; pages (host, html), whole copies once
    in both counts. `enough` pages make a template on a host of any size.

    Only hashes are shuffled, never pages."""

    def batch(b: pa.RecordBatch) -> dict:
        hosts, whole, hashes = [], [], []
        for host, page in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            got = {x.hash for x in walk_hashes(parse(page)) if x.texty and x.tag and x.tag not in OUTER}
            hosts.append(host)
            whole.append(xxhash.xxh3_64_intdigest(page.encode("utf-8", "surrogatepass")) - 2**63)
            hashes.append(np.fromiter(got, np.uint64, len(got)).view(np.int64))
        return {"host": hosts, "page": whole, "hashes": hashes}

    once = map_arrow(pages, batch, "host string, page long, hashes array<long>").groupBy("host", "page").agg(F.first("hashes").alias("hashes"))
    # a null hash a page counts the host's distinct pages in the same exchange
    each = once.select("host", F.explode(F.concat(F.array(F.lit(None).cast("long")), "hashes")).alias("h"))
    counted = each.groupBy("host", "h").agg(F.count(F.lit(1)).alias("n")).filter(F.col("h").isNull() | (F.col("n") >= least_pages))
    by_host = counted.groupBy("host").agg(F.max(F.when(F.col("h").isNull(), F.col("n"))).alias("pages"), F.collect_list(F.when(F.col("h").isNotNull(), F.struct("h", "n"))).alias("c"))
    many = F.least(F.col("pages") * F.lit(least_share), F.lit(float(enough)))
    return by_host.select("host", F.array_sort(F.transform(F.filter("c", lambda x: x["n"] >= many), lambda x: x["h"])).alias("template")).filter(F.size("template") > 0)


def extract(pages: DataFrame, least_pages: int = 5, least_share: float = 0.1) -> DataFrame:
    """One row per page: page_id, url, text, n_chars."""
    read = pages.select("page_id", "url", F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"), host_of(F.col("url")).alias("host"))
    templates = staged(host_templates(read.select("host", "html"), least_pages, least_share))
    joined = read.join(templates, "host", "left").select("page_id", "url", "html", "template")

    def batch(b: pa.RecordBatch) -> dict:
        texts = []
        for page, template in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
            texts.append(main_text(parse(page), {h & 0xFFFFFFFFFFFFFFFF for h in template or ()}))
        return {"page_id": b.column(0), "url": b.column(1), "text": texts, "n_chars": [len(t) for t in texts]}

    return map_arrow(joined, batch, "page_id long, url string, text string, n_chars long")


def op10_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: main text of every page."""
    return extract(table(spark, sf_dir, "pages"))
