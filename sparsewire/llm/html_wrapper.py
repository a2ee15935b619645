"""Main text of web pages by wrapper induction.

For each host, all pages are aligned by simple tree matching and folded into one tree. A node of it is a tag with its
names, so layouts of a host that differ have nodes of their own. It keeps the texts that every page with the node has:
these are the template, all else are slots. Every page is then aligned with its host's tree, and its main text is what
the slots hold, inside of a marked article or not. Navigation, page headers, footers, asides, forms, notices, adverts,
comments and the like are left out by element and by class, since their texts vary from page to page as well.

The mark of an article is read only where the template cannot tell: on hosts without two different pages, and on pages
of which nothing varies (pages of one host may carry the same article).

Siblings alike in tag and names are one node in the alignment, so each node of one tree has at most one counterpart in
another, matching takes time in proportion to the page, and long articles cost no more than short ones. Trees may be
of any depth.
"""

from __future__ import annotations

import json
import math
import re
import sys
from collections import Counter
from collections.abc import Callable, Iterator
from html import unescape

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, small_side, table

#: Parts, at least, whose trees are folded apart before those of a host meet; nodes that a task holds before it passes them on.
PARTS, HELD_NODES = 16, 200_000
#: Calls between plain Python functions take no C stack, so trees may be as deep as their page is long.
DEPTH = 10_000_000
#: Element names by their role in HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg select option button object canvas video audio".split())
#: Elements whose content is no markup, up to their end tag or the page's end.
UNPARSED = frozenset("script style textarea title".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul caption".split())
CLOSES_P = BLOCK - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend"}
CLOSED_BY = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "tbody": {"tr", "td", "th", "thead", "tbody"}, "tfoot": {"tr", "td", "th", "thead", "tbody"}}
SCOPES = frozenset("table ul ol dl div section article main body html nav aside form blockquote td th".split())
LEFT_OUT = frozenset("head nav aside footer form menu dialog search fieldset".split()) | RAW
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
FURNITURE = frozenset(
    "nav navbar navigation menu menubar header masthead footer sidebar aside ad ads advert adverts advertisement adsense sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert popup modal overlay "
    "comment comments respond replies disqus share sharing social breadcrumb breadcrumbs related recommended newsletter subscribe signup login form widget widgets toolbar pagination pager copyright skip".split()
)
#: Words beside one of FURNITURE that leave a name the name of furniture.
BESIDE = frozenset(
    "site page main top bottom left right upper lower side bar box block container wrapper wrap outer inner list lists link links button buttons icon icons area zone group item items slot unit row col column primary secondary global fixed sticky mobile desktop js id posts articles stories section user users reader readers thread post article".split()
)
#: Lists and table rows are constant as a whole or not at all.
ITEMS = frozenset("li dt dd td th tr".split())
COMMENT_NAMES = frozenset("comment comments respond replies disqus".split())
STATES = frozenset("has with no without".split())
#: A quote opens a value only after an equals sign, as in the standard's tokenizer; elsewhere it is a character.
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:=\s*(?:\"[^\"]*\"|'[^']*')?|[^>=])*+)(?:>|\Z)", re.S)
NAMED = re.compile(r"(?<![\w-])(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)


class Node:
    __slots__ = ("tag", "names", "furniture", "comments", "role", "kids", "fixed", "holds")

    def __init__(self, tag: str, attrs: str = "") -> None:
        self.tag, self.names, self.role, self.kids = tag, (), "", []
        #: fixed: its text is the template's; holds: an article or main element is within; furniture: words of names
        #: that say the element is no text, all of them about page furniture.
        self.fixed = self.holds = False
        self.furniture: set[str] = set()
        self.comments = False
        for x in NAMED.finditer(attrs) if len(attrs) > 3 else ():
            value = x[2] or x[3] or x[4] or ""
            if x[1].lower() == "role":
                self.role = (value.split() or [""])[0].lower()
                continue
            for name in value.split():
                words = [w for w in re.split(r"[^a-z0-9]+", re.sub(r"(?<=[a-z])(?=[A-Z])", "-", name).lower()) if w]
                self.names += tuple(words)
                about = FURNITURE.intersection(words)
                if about and STATES.isdisjoint(words):
                    self.comments = self.comments or not COMMENT_NAMES.isdisjoint(words)
                    if all(w in FURNITURE or w in BESIDE or w.isdigit() for w in words):
                        self.furniture |= about


def parse(html: str) -> Node:
    """A tree of elements and texts; forgiving about missing and stray end tags."""
    root = Node("#root")
    stack, open_ = [root], Counter()
    at, n = 0, len(html)

    def text(s: str) -> None:
        if s:
            stack[-1].kids.append(unescape(s) if "&" in s else s)

    def cut(k: int) -> None:
        for x in stack[k:]:
            open_[x.tag] -= 1
        del stack[k:]

    def close(names: set[str] | frozenset[str]) -> None:
        if not any(open_[x] for x in names):
            return
        for k in range(len(stack) - 1, 0, -1):
            if stack[k].tag in names:
                cut(k)
                return
            if stack[k].tag in SCOPES:
                return

    while at < n:
        m = TOKEN.search(html, at)
        if m is None:
            text(html[at:])
            break
        text(html[at : m.start()])
        at = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            if open_[tag]:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k].tag == tag:
                        cut(k)
                        break
            continue
        if tag in CLOSES_P:
            close({"p"})
        if tag in CLOSED_BY:
            close(CLOSED_BY[tag])
        node = Node(tag, m[3])
        stack[-1].kids.append(node)
        if tag in ("article", "main"):
            for x in reversed(stack):
                if x.holds:
                    break
                x.holds = True
        if tag in VOID or m[3].rstrip().endswith("/") and tag in RAW:
            continue
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}\b[^>]*>", re.I).search(html, at)
            at = end.end() if end else n if tag in UNPARSED else at
        else:
            stack.append(node)
            open_[tag] += 1
    return root


def left_out(node: Node, in_article: bool) -> bool:
    """Whether an element is of a kind that is never main text.

    An article may have a header of its own. A name counts only as a whole: notice-period or share-price are no names
    of furniture, and has-sidebar tells of a page, not of the element. An element around an article is none either.
    """
    if node.tag in LEFT_OUT or node.role in ROLES or node.tag == "header" and not in_article:
        return True
    if node.tag == "article":
        return node.comments
    if node.tag in ("html", "body", "main") or not node.furniture or node.holds:
        return False
    return not (in_article and node.furniture <= {"header", "masthead"})


# A shape is [tag, names, hashes of texts, kids, nodes]; kids alike in tag and names are one. In a template the fifth
# entry is the smallest and largest hash of the pages that have the node: two pages at least if they differ.
Shape = list


def text_hash(node: Node) -> int | None:
    """Hash of a node's text outside of the blocks within it, inline elements included."""
    parts: list[str] = []
    todo = list(reversed(node.kids))
    while todo:
        k = todo.pop()
        if isinstance(k, str):
            parts.append(k)
        elif k.tag in BLOCK or k.tag in RAW or k.tag == "br":
            parts.append(" ")
        else:
            todo.extend(reversed(k.kids))
    words = " ".join("".join(parts).split())
    return xxhash.xxh64_intdigest(words.encode("utf-8", "surrogatepass")) if words else None


def shape(node: Node) -> Shape:
    # inline elements inside inline elements are read once, with the block around them
    words = text_hash(node) if node.tag in BLOCK or node.tag == "#root" else None
    kids: dict[tuple[str, str], Shape] = {}
    for k in node.kids:
        if isinstance(k, Node) and k.tag not in RAW and k.tag not in VOID:
            s = shape(k)
            same = kids.setdefault((s[0], s[1]), s)
            if same is not s:
                fold(same, s, match(same, s)[1], _add, _extend)
    return [node.tag, " ".join(w for w in node.names if w.isalpha()), set() if words is None else {words}, list(kids.values()), [node]]


def _add(x: set, y: set) -> set:
    x |= y
    return x


def _extend(x: list, y: list) -> list:
    x.extend(y)
    return x


def fold(a: Shape, b: Shape, pairs: list, texts: Callable, ends: Callable) -> None:
    """b becomes part of a: matched nodes are joined, the others follow the one that they followed in b."""
    a[2], a[4] = texts(a[2], b[2]), ends(a[4], b[4])
    partner = {}
    for p, q, inner in pairs:
        fold(p, q, inner, texts, ends)
        partner[id(q)] = id(p)
    if len(partner) == len(b[3]):
        return
    after: dict[int, list[Shape]] = {}
    last = 0
    for q in b[3]:
        if id(q) in partner:
            last = partner[id(q)]
        else:
            after.setdefault(last, []).append(q)
    kids = list(after.get(0, ()))
    for p in a[3]:
        kids.append(p)
        kids += after.get(id(p), ())
    a[3] = kids


def match(a: Shape, b: Shape) -> tuple[int, list]:
    """Size of the largest match of two trees with equal roots, and the matched pairs of kids.

    No two kids of a node are alike in tag and names, so a kid can match one kid only and all that can match do.
    """
    if a[0] != b[0]:
        return 0, []
    size, pairs, theirs = 1, [], {(q[0], q[1]): q for q in b[3]}
    for p in a[3]:
        q = theirs.get((p[0], p[1]))
        if q is not None:
            n, inner = match(p, q)
            size += n
            pairs.append((p, q, inner))
    return size, pairs


def merge(template: Shape | None, other: Shape) -> Shape:
    """The template of the pages of both: texts that one of them lacks at a node that both have become slots."""
    if template is None:
        return other
    fold(template, other, match(template, other)[1], set.intersection, lambda x, y: [min(x[0], y[0]), max(x[1], y[1])])
    return template


def template_of(html: str) -> Shape:
    """The template of one page."""
    sys.setrecursionlimit(DEPTH)
    name = xxhash.xxh64_intdigest(html.encode("utf-8", "surrogatepass"))

    def named(s: Shape) -> Shape:
        return [s[0], s[1], s[2], [named(k) for k in s[3]], [name, name]]

    return named(shape(parse(html)))


def size_of(s: Shape) -> int:
    total, todo = 0, [s]
    while todo:
        x = todo.pop()
        total += 1 + len(x[2])
        todo += x[3]
    return total


def dumps(s: Shape) -> str:
    """Nodes before their kids, each with the number of its kids."""
    rows, todo = [], [s]
    while todo:
        x = todo.pop()
        rows.append([x[0], x[1], sorted(x[2]), x[4], len(x[3])])
        todo.extend(reversed(x[3]))
    return json.dumps(rows, separators=(",", ":"))


def loads(template: str) -> Shape:
    root: Shape = ["", "", set(), [], []]
    todo = [(root, 1)]
    for tag, names, texts, ends, n in json.loads(template):
        node = [tag, names, set(texts), [], ends]
        parent, left = todo.pop()
        parent[3].append(node)
        if left > 1:
            todo.append((parent, left - 1))
        if n:
            todo.append((node, n))
    return root[3][0]


def induce(pages: list[str]) -> str:
    """The template of pages as JSON; empty if no two differ, so that nothing tells what is constant."""
    tree = None
    for p in pages:
        tree = merge(tree, template_of(p))
    return dumps(tree) if tree and tree[4][0] != tree[4][1] else ""


def mark(root: Node, template: Shape | None) -> None:
    """Sets fixed on the page's nodes whose text every page with the node has."""
    if not template:
        return

    def walk(pairs: list) -> None:
        for a, b, inner in pairs:
            if b[2] and b[4][0] != b[4][1]:
                same = [text_hash(node) in b[2] for node in a[4]]
                for node, x in zip(a[4], same, strict=True):
                    node.fixed = all(same) if a[0] in ITEMS else x
            walk(inner)

    s = shape(root)
    walk([(s, template, match(s, template)[1])])


def articles(root: Node) -> list[Node]:
    """The outermost marked articles in page order."""
    out: list[Node] = []

    def find(node: Node, inside: bool) -> None:
        for k in node.kids:
            if isinstance(k, Node) and not left_out(k, inside):
                if k.tag == "article" or "articlebody" in "".join(k.names):
                    out.append(k)
                else:
                    find(k, inside or k.tag == "main")

    find(root, False)
    return out


def blocks(node: Node, is_article: bool) -> list[str]:
    """Texts of the blocks in page order, white space joined to single spaces."""
    out: list[str] = []
    held: list[str] = []

    def flush() -> None:
        if words := " ".join("".join(held).split()):
            out.append(words)
        held.clear()

    def walk(n: Node, inside: bool, fixed: bool) -> None:
        inside = inside or n.tag in ("article", "main")
        fixed = n.fixed if n.tag in BLOCK else fixed
        for k in n.kids:
            if isinstance(k, str):
                if is_article or not fixed:
                    held.append(k)
            elif k.tag == "br":
                held.append("\n")
            elif not left_out(k, inside):
                if k.tag in BLOCK:
                    flush()
                    walk(k, inside, fixed)
                    flush()
                else:
                    walk(k, inside, fixed)

    walk(node, is_article, False)
    flush()
    return out


def main_text(html: str | None, template: str | Shape | None) -> str:
    if not html:
        return ""
    sys.setrecursionlimit(DEPTH)
    root = parse(html)
    if template:
        mark(root, loads(template) if isinstance(template, str) else template)
        if found := blocks(root, False):
            return "\n\n".join(found)
    if found := articles(root):
        return "\n\n".join(words for a in found for words in blocks(a, True))
    return "" if template else "\n\n".join(blocks(root, False))


def host_of(url_col: str) -> F.Column:
    return F.coalesce(F.lower(F.regexp_extract(F.col(url_col), r"^[a-zA-Z][\w+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def templates(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(host, template) from all pages; each task folds its own, then parts of a host are folded, then the host."""
    rows = bounded_batches(pages.where(F.length(html_col) > 0).select(host_of(url_col).alias("host"), F.col(html_col).alias("html")))

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, Shape] = {}

        def flush() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(held, pa.string()), pa.array(map(dumps, held.values()), pa.string())], names=["host", "tree"])

        for b in batches:
            for host, html in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                held[host] = merge(held.get(host), template_of(html))
            if sum(map(size_of, held.values())) > HELD_NODES:
                yield flush()
                held.clear()
        if held:
            yield flush()

    def join(last: bool) -> Callable:
        def run(t: pa.Table) -> pa.Table:
            sys.setrecursionlimit(DEPTH)
            tree = None
            for x in sorted(t.column("tree").to_pylist()):
                tree = merge(tree, loads(x))
            text = "" if last and tree[4][0] == tree[4][1] else dumps(tree)
            return pa.table({"host": pa.array([t.column("host")[0].as_py()], pa.string()), "tree": pa.array([text], pa.string())})

        return run

    # of the trees that tasks send for one host, no group takes more than about the square root
    n = max(PARTS, math.isqrt(rows.rdd.getNumPartitions()))
    parts = rows.mapInArrow(first, "host string, tree string").withColumn("part", F.pmod(F.xxhash64("tree"), F.lit(n)))
    some = parts.groupBy("host", "part").applyInArrow(join(False), "host string, tree string")
    return some.groupBy("host").applyInArrow(join(True), "host string, tree string").withColumnRenamed("tree", "template")


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text and n_chars of every row; null or empty html gives an empty text.

    A host without two different pages has no template: its text comes from marked elements, or from all. Templates
    are broadcast if their measured size allows it, so pages are not shuffled; else they are joined by host, and a
    host with a large share of all rows can be split by the join.
    """
    known = small_side(templates(pages, id_col, url_col, html_col).withColumnRenamed("host", "sw__host"))
    rows = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), host_of(url_col).alias("host"))
    joined = rows.join(known, F.col("host") == F.col("sw__host"), "left").select("page_id", "url", "html", "template")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees: dict[str, Shape] = {}
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                new = {t for t in part.column(3).to_pylist() if t}
                trees = {t: trees[t] if t in trees else loads(t) for t in new}
                texts = [main_text(h, trees.get(t)) for h, t in zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return bounded_batches(joined).mapInArrow(run, "page_id bigint, url string, text string, n_chars bigint")


def op4_html_wrapper(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
