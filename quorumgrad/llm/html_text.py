"""Main text of web pages by consensus host paths.

Pass one scores the containers of every page (own paragraph text, weighted down by links and by boilerplate marks) and
emits, per page, a vote for the generalised path (tags with their classes, digits folded) of the best one.  Spark sums the votes by
host and path, and the path with most votes wins the host.  Pass two re-extracts each page of the host from the
containers under the winning path; a page without such a container falls back on its own best.

The winners are one short row per host and are written before the join, so the planner knows their size: below its
broadcast threshold they are sent out, over it pages are shuffled by host (splittable where a host is hot).

Defined results: null or empty html has empty text; a null url is a host of its own; repeated rows vote and are
extracted each; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from html import unescape

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import materialized, only

# Element sets of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg math select option object canvas audio video".split())
BLOCKS = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul br".split())
DROPPED = frozenset("nav header footer aside form button menu dialog head label input fieldset".split()) | RAW
CONTAINERS = frozenset("article main section div td body center".split())
CLOSED_BY = {"p": BLOCKS - {"br"}, "li": frozenset(["li"]), "dd": frozenset(["dd", "dt"]), "dt": frozenset(["dd", "dt"]), "tr": frozenset(["tr"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"]), "option": frozenset(["option"])}
#: Parts of class and id names that mark boilerplate.
BOILER = frozenset("""ad ads adv advert adverts advertisement advertising adbox adsense banner banners sponsor sponsored promo promos promotion cookie cookies consent gdpr notice notices alert alerts
    nav navbar navigation menu menus breadcrumb breadcrumbs header masthead topbar footer foot bottombar copyright sidebar sidebars side aside rail widget widgets comment comments commentlist reply replies respond disqus discussion
    share sharing social related recommended recommendations popular trending subscribe subscription newsletter signup login popup modal overlay pagination pager toolbar tags tagcloud skip form search print hidden""".split())
ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alert".split())

#: Longer paths are replaced by their hash, so that a page of ever deeper elements stays linear.
MOST_PATH = 1024

#: What begins a piece of markup, and the rest of a tag: a quote counts where a value begins.  Neither steps back.
MARKUP = re.compile(r"<(?:(!--)|([!?])|(/?)([A-Za-z][A-Za-z0-9:-]*+))")
TAG_END = re.compile(r"((?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+')?+)*+)>")
#: Parts of a name that say how, not what: behind the part that tells, or in front of a name that only mentions it.
GENERIC = frozenset("list box inner outer container wrap wrapper block area section item items row col column group panel bar links link body holder region zone element module component".split())
MENTIONS = frozenset("has with no without is hide show not".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
ATTRIBUTE = re.compile(r"""(?<![\w-])(class|id|role|hidden|aria-hidden|style)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.IGNORECASE)


@dataclass
class Node:
    tag: str
    path: str
    parent: Node | None
    boiler: bool
    #: Whether only its class or id says that it is boilerplate.
    named: bool = False
    #: Pieces in page order: text, or a child node; "\0" marks the edge of a block.
    parts: list[str | Node] = field(default_factory=list)
    #: The innermost block around it, itself included.
    block: Node | None = None

    def __post_init__(self):
        self.block = self if self.tag in BLOCKS else self.parent.block if self.parent else None


def _tells(name: str) -> bool:
    """Whether a class or id names boilerplate: by its last part that is not generic, unless it only mentions it."""
    parts = [p for p in re.split(r"[^a-z]+", re.sub(r"\d+", " ", re.sub(r"(?<=[a-z])(?=[A-Z])", " ", name)).lower()) if p]
    parts = parts[: next((i for i, p in enumerate(parts) if p in MENTIONS), len(parts))]
    if not parts:
        return False
    while len(parts) > 1 and parts[-1] in GENERIC:
        parts.pop()
    return parts[-1] in BOILER or len(parts) > 1 and parts[0] in BOILER


def _marks(attrs: str) -> tuple[str, bool, bool]:
    """The generalised class of an element, whether its names mark it as boilerplate, and whether its role or style does."""
    cls, named, hard = "", False, False
    for m in ATTRIBUTE.finditer(attrs):
        name, value = m[1].lower(), (m[2] or "").strip("\"'")
        if name in ("class", "id"):
            named |= any(map(_tells, value.split()))
            if name == "class" and value:
                cls = "." + ".".join(sorted({re.sub(r"\d+", "#", w) for w in value.lower().split()}))
        elif name == "role":
            hard |= value.lower() in ROLES
        elif name == "hidden" or name == "aria-hidden" and value.lower() == "true":
            hard = True
        elif name == "style":
            hard |= bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value.lower()))
    return cls, named, hard


def _settle(root: Node) -> None:
    """Second thoughts, once the whole page is known.

    An element whose name alone marks it stays if it holds a main heading or an article and over half of the page's
    paragraph text: a layout that is called after its sidebar is no sidebar.  A header inside an article gives its
    headings to the article and nothing else.
    """
    order = list(_walk(root))
    inside: dict[int, int] = {}
    holds: set[int] = set()
    for x in reversed(order):
        text = inside.get(id(x), 0)
        if x.tag == "p":
            text += sum(len(p.strip()) for p in x.parts if isinstance(p, str))
        inside[id(x)] = text
        if x.tag in ("h1", "main") or x.tag == "article" and not x.named:
            holds.add(id(x))
        if x.parent is not None:
            inside[id(x.parent)] = inside.get(id(x.parent), 0) + text
            if id(x) in holds:
                holds.add(id(x.parent))
    within = {id(root): False}
    for x in order[1:]:
        within[id(x)] = within[id(x.parent)] or x.parent.tag in ("article", "main")
        if x.named and id(x) in holds and 2 * inside[id(x)] > inside[id(root)]:
            x.boiler = x.named = False
        if x.tag == "header" and within[id(x)]:
            heads = [h for h in _walk(x) if h.tag in HEADINGS]
            if heads:
                x.parts = [part for h in heads for part in ("\0", h, "\0")]
                x.boiler = False


def parse(html: str) -> Node:
    """A tree of the page: tolerant of elements that are not closed and of ends that nothing opened."""
    root = Node("", "", None, False)
    at, node, depth = 0, root, {}
    lower, strict = None, True
    while m := MARKUP.search(html, at):
        if m.start() > at:
            node.parts.append(html[at : m.start()])
        close, tag = (m[4], None) if m[3] else (None, m[4])
        attrs = ""
        if m[1]:
            at = html.find("-->", m.start() + 2) + 3
            if at < 3:
                at = len(html)
            continue
        end = TAG_END.match(html, m.end()) if tag and strict else None
        if end:
            at, attrs = end.end(), end[1]
        else:  # past a quote that nothing closes, quotes no longer count, so that no part is read twice
            strict = strict and not tag
            at = html.find(">", m.end()) + 1
            if not at:  # the page ends inside a tag
                at = len(html)
                break
            attrs = html[m.end() : at - 1]
        if close:
            close = close.lower()
            if depth.get(close):
                while node.tag != close:
                    depth[node.tag] -= 1
                    node = node.parent
                depth[close] -= 1
                node = node.parent
            if close in BLOCKS:
                node.parts.append("\0")
        elif tag:
            tag = tag.lower()
            if tag in BLOCKS:
                while node.tag in CLOSED_BY and tag in CLOSED_BY[node.tag] or node.tag not in BLOCKS and node.tag not in ("", "a") and _closes(node, tag):
                    depth[node.tag] -= 1
                    node = node.parent
                node.parts.append("\0")
            cls, named, hard = _marks(attrs) if attrs.strip() else ("", False, False)
            if tag in VOID or attrs.endswith("/") and tag not in BLOCKS:
                continue
            path = f"{node.path}>{tag}{cls}"
            if len(path) > MOST_PATH:
                # A long path goes on from its hash, so that every element below still has its own.
                path = f"#{xxhash.xxh3_128_hexdigest(path.encode('utf-8', 'surrogatepass'))}"
            hard = hard and tag not in ("html", "body") or tag in DROPPED
            named = named and not hard and tag not in ("html", "body")
            child = Node(tag, path, node, named or hard, named)
            node.parts.append(child)
            if tag in ("script", "style", "textarea", "title", "noscript", "iframe", "template"):
                lower = lower or html.lower()
                end = lower.find(f"</{tag}", at) if len(lower) == len(html) else _find_end(html, tag, at)
                at = len(html) if end < 0 else end
                close_at = html.find(">", at)
                at = len(html) if close_at < 0 else close_at + 1
                continue
            node = child
            depth[tag] = depth.get(tag, 0) + 1
    rest = html[at:]
    node.parts.append(rest.removesuffix("<"))
    _settle(root)
    return root


def _find_end(html: str, tag: str, at: int) -> int:
    m = re.compile(f"</{tag}", re.IGNORECASE).search(html, at)
    return m.start() if m else -1


def _closes(node: Node, tag: str) -> bool:
    """Whether a block closes inline elements that were left open inside a paragraph."""
    up = node.block
    return up is not None and up.tag in CLOSED_BY and tag in CLOSED_BY[up.tag]


def _walk(node: Node) -> Iterator[Node]:
    stack = [node]
    while stack:
        x = stack.pop()
        yield x
        stack += [p for p in x.parts if isinstance(p, Node)]


def _pieces(node: Node, out: list[str]) -> None:
    """Texts below a node in page order without what is dropped; iterative, so that depth doesn't matter."""
    stack: list[str | Node] = [node]
    first = True
    while stack:
        x = stack.pop()
        if isinstance(x, str):
            out.append(x)
        elif first or not x.boiler:
            stack.extend(reversed(x.parts))
        first = False


def block_text(nodes: list[Node]) -> str:
    """Decoded text of the nodes: white space in a block is one space, blocks are joined by one space."""
    out: list[str] = []
    for node in nodes:
        _pieces(node, out)
        out.append("\0")
    blocks = ("".join(out)).split("\0")
    return " ".join(x for x in (" ".join(unescape(b).split()) for b in blocks) if x)


def scores(root: Node) -> list[tuple[float, Node]]:
    """(score, container) of a page.

    A container earns the text of the paragraphs, headings and list items right below it (inline elements included),
    less three times what is inside links; a third of its nested containers' score is passed up, so that the tightest
    element that holds most of the text wins.
    """
    own: dict[int, float] = {}
    out: list[tuple[float, Node]] = []
    order = [n for n in _walk(root)]
    inside = {id(root): root.boiler}
    for n in order[1:]:
        inside[id(n)] = n.boiler or inside[id(n.parent)]
    for n in reversed(order):
        total = own.get(id(n), 0.0)
        text = sum(len(p.strip()) for p in n.parts if isinstance(p, str) and p != "\0")
        if inside[id(n)]:
            continue
        total += -2.0 * text if n.tag == "a" else text
        if n.tag in CONTAINERS:
            out.append((total * (1.5 if n.tag in ("article", "main") else 1.0), n))
            total *= 0.34 if n.tag != "article" else 0.6
        if n.parent is not None:
            own[id(n.parent)] = own.get(id(n.parent), 0.0) + total
    return sorted(out, key=lambda x: (-x[0], x[1].path))


def best_path(html: str | None) -> str | None:
    """The generalised path that a page votes for; none without text."""
    found = scores(parse(html or ""))
    return found[0][1].path if found and found[0][0] > 0 else None


def under_path(root: Node, path: str) -> list[Node]:
    """The containers at a path, in page order, outermost only and not inside what is dropped."""
    hits, stack = [], [root]
    while stack:
        x = stack.pop()
        if x.boiler and x.tag:
            continue
        if x.path == path:
            hits.append(x)
        else:
            stack += [p for p in reversed(x.parts) if isinstance(p, Node)]
    return hits


def extract(html: str | None, path: str | None) -> str:
    """The main text by the host's path, else by the page's own best container, else of the whole body."""
    if not html:
        return ""
    root = parse(html)
    nodes = under_path(root, path) if path else []
    text = block_text(nodes) if nodes else ""
    if not text:
        found = [n for s, n in scores(root) if s > 0]
        text = block_text(found[:1] or [root])
    return text


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/@?#]*@)?([^/:?#]*)", 1))


def host_paths(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """(host, path, votes): the winning path of each host; of equal votes the first path by code point."""

    def vote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            paths = [best_path(x.as_py()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(paths, pa.string())], names=["host", "path"])

    votes = only(pages, "url", "html").select(host_of(F.col("url")).alias("host"), "html").mapInArrow(vote, "host string, path string")
    counted = votes.where("path is not null").groupBy("host", "path").agg(F.count("*").alias("votes"))
    first = F.row_number().over(W.partitionBy("host").orderBy(F.desc("votes"), "path"))
    return counted.withColumn("n", first).where("n = 1").drop("n")


def main_text(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars, path of each row of ``pages`` (page_id, url, html)."""
    winners = materialized(spark, host_paths(spark, pages).select(F.col("host").alias("of"), "path"), "host-paths", few=True)
    rows = only(pages, "page_id", "url", "html").withColumn("host", host_of(F.col("url")))
    joined = rows.join(winners, F.col("host").eqNullSafe(F.col("of")), "left").select("page_id", "url", "html", "path")

    def take(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [extract(h.as_py(), p.as_py()) for h, p in zip(batch.column(2), batch.column(3), strict=True)]
            arrays = [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64()), batch.column(3)]
            yield pa.RecordBatch.from_arrays(arrays, names=["page_id", "url", "text", "n_chars", "path"])

    return joined.mapInArrow(take, f"page_id {rows.schema['page_id'].dataType.simpleString()}, url string, text string, n_chars long, path string")
