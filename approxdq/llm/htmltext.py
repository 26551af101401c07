"""Main text of web pages: site templates go by hash, then what isn't article.

1. Each page is parsed to a tree. The subtrees of elements outside article and main are hashed (tag, attributes,
   text, children), but for those that step 4 drops anyway and those that hold an article or main.
2. Spark counts in how many pages of a host each subtree stands. Pages of a host that say the same (their text before
   step 3 is equal) count as one page, so copies of a page make no templates; the key holds hash and text, so a hot
   host is spread. Subtrees that stand in many pages of their host (at least ``least_pages`` and ``share`` of them)
   are templates.
3. Templates go to the pages of their host (broadcast up to a checked number, else by a salted join), and are deleted. Nothing inside an article or main is
   deleted by hash, whatever its tag and however many pages repeat it, for it is what the page says.
4. Menus, headers, footers, sidebars, notices, adverts, forms, scripts, styles and reader comments go by tag,
   role, class or id; the article (else main, else the body) is what is left. Blocks are joined by line breaks.

A null, empty or markup-free html gives the text it has (or none). Pages without a host have no templates. Broken
markup is closed as browsers do. Texts are whole, whatever their length.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..checkpoints import cut
from . import common as C

# Element kinds of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe xmp".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
ROOTS = frozenset(("article", "main"))
DROP = frozenset("script style noscript template nav aside footer form button select textarea input iframe svg canvas object head title dialog menu".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}
_NAMES = re.compile(r"(?:^|[\s_-])(?:header|toolbars?|topbars?|ads?|adverts?|advertisements?|advertising|banners?|cookies?|consent|gdpr|notices?|newsletter|promos?|promotion|sponsor(?:ed|s)?|share|sharing|social|related|sidebar|menus?|nav|navbar|navigation|breadcrumbs?|footer|masthead|comments?|disqus|replies|popup|modal|subscribe|widgets?)(?:$|[\s_-])")
_OPEN = re.compile(r"<(?:(!--)|([!?])|(/?)([a-zA-Z][^\s/>]*))")
_PLAIN = re.compile(r"[^>\"']*")
_ATTR = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_SPACE = re.compile(r"\s+")
_RAW_ENDS = {tag: re.compile(rf"</{tag}\s*>", re.I) for tag in RAW}


class Node:
    __slots__ = ("tag", "attrs", "children", "hash")

    def __init__(self, tag: str, attrs: str):
        self.tag, self.attrs, self.children, self.hash = tag, attrs, [], None


def tokens(page: str):
    """(start, end, closing, tag, attributes) of each tag, tag None for comments and declarations. A quote or tag that is
    never closed is found once, so the time is linear in the page."""
    at, size, none = 0, len(page), set()  # none: characters that don't come any more

    def find(c: str, start: int) -> int:
        found = -1 if c in none else page.find(c, start)
        if found < 0:
            none.add(c)
        return found

    while m := _OPEN.search(page, at):
        start, at = m.start(), m.end()
        if m[1]:
            end = find("-->", at)
            at = end + 3 if end >= 0 else size
            yield start, at, False, None, ""
            continue
        if m[2]:
            if (end := find(">", at)) >= 0:
                at = end + 1
                yield start, at, False, None, ""
            continue
        if find(">", at) < 0:
            return
        end = at
        while True:
            end = _PLAIN.match(page, end).end()
            if end >= size or page[end] == ">":
                break
            close = find(page[end], end + 1)
            end = close + 1 if close >= 0 else end + 1
        if end >= size:  # no end outside of quotes: the first one ends it
            end = page.find(">", at)
        tag = m[4].lower()
        yield start, end + 1, bool(m[3]), tag, page[at:end]
        at = end + 1 if m[3] or tag not in RAW else _raw_end(page, tag, end + 1)


def _raw_end(page: str, tag: str, at: int) -> int:
    """Where the text of an element that holds no markup ends."""
    m = _RAW_ENDS[tag].search(page, at)
    return m.start() if m else len(page)


def parse(page: str) -> Node:
    """The tree of a page; children are nodes and (undecoded) strings."""
    root = Node("#root", "")
    stack, done = [root], 0
    open_ = Counter()  # open elements of each tag, so that nothing is looked for in vain

    def close(depth: int) -> None:
        for n in stack[depth:]:
            open_[n.tag] -= 1
        del stack[depth:]

    for start, end, closing, tag, attrs in tokens(page):
        if start > done:
            stack[-1].children.append(page[done:start])
        done = end
        if tag is None:
            continue
        if closing:
            if open_[tag]:
                close(next(i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag))
            continue
        if tag in BLOCK and tag not in ("body", "html") and open_["p"]:  # a block ends an open paragraph
            depth = next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag in BLOCK), 0)
            if stack[depth].tag == "p":
                close(depth)
        if tag in CLOSES and any(open_[t] for t in CLOSES[tag]):
            depth = next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag in SCOPES[tag] or stack[i].tag in CLOSES[tag]), 0)
            if depth and stack[depth].tag not in SCOPES[tag]:
                close(depth)
        node = Node(tag, attrs)
        stack[-1].children.append(node)
        if tag in RAW:
            done = _raw_end(page, tag, end)
            node.children.append(page[end:done])
        elif tag not in VOID and not attrs.rstrip().endswith("/"):
            stack.append(node)
            open_[tag] += 1
    if done < len(page):
        stack[-1].children.append(page[done:])
    return root


def walk(node: Node):
    """Nodes, children before their parent, without recursion."""
    stack = [(node, False)]
    while stack:
        n, done = stack.pop()
        if done:
            yield n
        else:
            stack.append((n, True))
            stack.extend((c, False) for c in n.children if isinstance(c, Node))


def unwanted(node: Node, inside: bool) -> bool:
    if node.tag in DROP or node.tag == "header" and not inside:
        return True
    if node.attrs and node.tag not in ("html", "body"):
        for m in _ATTR.finditer(node.attrs):
            name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
            if name in ("class", "id") and _NAMES.search(value) or name == "role" and value in ROLES or name == "hidden" or name == "aria-hidden" and value == "true":
                return True
    return False


def outside(root: Node) -> list[Node]:
    """Elements that hold text or elements and may be templates: outside article and main, not in something unwanted,
    and without an article or main of the page in them."""
    seen: list[tuple[Node, int]] = []
    holds: set[int] = set()
    stack = [(root, -1)]
    while stack:
        n, above = stack.pop()
        if unwanted(n, False):
            continue
        if n.tag in ROOTS:
            while above >= 0 and above not in holds:
                holds.add(above)
                above = seen[above][1]
            continue
        seen.append((n, above))
        own = len(seen) - 1
        stack.extend((c, own) for c in n.children if isinstance(c, Node))
    return [n for i, (n, _) in enumerate(seen) if i not in holds and n.children and n.tag not in ("#root", "html", "body", "head")]


def subtree_hashes(root: Node) -> set[int]:
    """Sets the hash of each node that may be a template, and of those below it; returns the hashes of the former."""
    found = outside(root)
    for top in found:
        for n in walk(top) if top.hash is None else ():
            h = blake2b(n.tag.encode() + b"\0" + _SPACE.sub(" ", n.attrs).strip().encode("utf-8", "replace"), digest_size=8)
            for c in n.children:
                h.update(b"\1%d" % c.hash if isinstance(c, Node) else b"\2" + _SPACE.sub(" ", c).strip().encode("utf-8", "replace"))
            n.hash = int.from_bytes(h.digest(), "little", signed=True)
    return {n.hash for n in found}


def chosen(root: Node) -> list[Node]:
    """The outermost articles that aren't in something unwanted, else the first such main, else the root."""
    roots: dict[str, list[Node]] = {"article": [], "main": []}
    stack = [(root, False)]
    while stack:
        n, inside = stack.pop()
        if unwanted(n, inside):
            continue
        if n.tag in roots:
            roots[n.tag].append(n)
            if n.tag == "article":
                continue
        stack.extend((c, inside or n.tag in roots) for c in reversed(n.children) if isinstance(c, Node))
    return roots["article"] or roots["main"][:1] or [root]


def main_text(page: str, templates: frozenset[int] = frozenset()) -> str:
    return text_of(parse(page), templates)


def text_of(root: Node, templates: frozenset[int] = frozenset()) -> str:
    tops = chosen(root)
    if templates and tops[0] is root:
        subtree_hashes(root)
    blocks: list[str] = []
    text: list[str] = []

    def close() -> None:
        block = _SPACE.sub(" ", html.unescape("".join(text))).strip()
        text.clear()
        if block:
            blocks.append(block)

    for top in tops:
        todo: list = [(top, top.tag in ROOTS)]
        while todo:
            n, inside = todo.pop()
            if n is None:
                close()
            elif isinstance(n, str):
                text.append(n)
            elif n is not top and (unwanted(n, inside) or not inside and n.hash in templates):
                continue
            else:
                if n.tag == "br":
                    text.append(" ")
                if n.tag in BLOCK:
                    close()
                    todo.append((None, inside))
                todo.extend((c, inside or n.tag in ROOTS) for c in reversed(n.children))
        close()
    return "\n".join(blocks)


def _host() -> F.Column:
    return F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def site_templates(pages: DataFrame, least_pages: int = 5, share: float = 0.1) -> DataFrame:
    """host, templates: hashes of the subtrees that stand in many pages of the host, pages of equal text counted once.
    A host has at most (subtrees of a page) / share of them."""
    C.ship(pages.sparkSession)
    own = pages.select(_host().alias("host"), F.col("html").cast("string").alias("html")).where("host <> ''")

    def hashes(batches):
        for batch in batches:
            for piece in C.pieces(batch, "html"):
                host, found, said, n = piece.column("host").to_pylist(), [], [], []
                for page in piece.column("html").to_pylist():
                    root = parse(page or "")
                    own = subtree_hashes(root)
                    found += [0, *own]  # 0 counts the page
                    said.append(int.from_bytes(blake2b(text_of(root).encode("utf-8", "replace"), digest_size=8).digest(), "little", signed=True))
                    n.append(1 + len(own))
                repeat = np.repeat(np.arange(len(n)), n)
                yield pa.RecordBatch.from_arrays([pa.array(host, pa.string()).take(pa.array(repeat)), pa.array(found, pa.int64()), pa.array(np.array(said, np.int64)[repeat])], names=["host", "hash", "said"])

    counted = own.mapInArrow(hashes, "host string, hash long, said long").distinct().groupBy("host", "hash").count()
    pages = counted.where("hash = 0").select("host", F.col("count").alias("pages"))
    many = counted.where((F.col("hash") != 0) & (F.col("count") >= least_pages)).join(pages, "host").where(F.col("count") >= share * F.col("pages"))
    return many.groupBy("host").agg(F.collect_list("hash").alias("templates"))


_OUT = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])
#: Templates (8 bytes each) that are broadcast at most, and parts of a host's pages beyond it, so that a hot host isn't one task.
MOST_TEMPLATES, SALTS = 1 << 20, 1024


def main_texts(pages: DataFrame, least_pages: int = 5, share: float = 0.1, most: int = MOST_TEMPLATES) -> DataFrame:
    """page_id, url, text and n_chars of each page. Templates go to the pages: broadcast up to a checked number, else by a
    salted join."""
    templates = cut(site_templates(pages, least_pages, share))
    own = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).withColumn("host", _host())
    n = templates.agg(F.sum(F.size("templates"))).first()[0] or 0
    if n <= most:
        joined = own.join(F.broadcast(templates), "host", "left")
    else:
        salted = templates.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = own.withColumn("salt", F.pmod(F.xxhash64("page_id", "url", "html"), F.lit(SALTS)).cast("int")).join(salted, ["host", "salt"], "left")
    joined = joined.select("page_id", "url", "html", "templates")

    def extract(piece: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(page or "", frozenset(t or ())) for page, t in zip(piece.column("html").to_pylist(), piece.column("templates").to_pylist(), strict=True)]
        return pa.RecordBatch.from_arrays([piece.column("page_id"), piece.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], schema=_OUT)

    return C.map_pieces(joined, extract, "page_id long, url string, text string, n_chars long", "html")
