"""Main text of web pages, with site templates removed.

Every element subtree of a page has a hash of its tag, attributes and content, and a path: the tags, classes and ids of
the elements around it, digits aside. Spark counts per host on how many different pages each hash occurs (a page that is
repeated byte for byte counts once). Two kinds of subtrees are template:

- a subtree whose hash recurs on ``LEAST_PAGES`` pages and a share ``CONTENT_SHARE`` of the host's pages or more;
- a slot: a path whose subtrees, over all pages of the host, are for a share ``SLOT_SHARE`` or more such as another page has
  too. Menus, adverts and footers that rotate through a pool fill one slot, so all of them go, those seen once as well.

The few hashes and slots of a host are then handed to its pages, and such subtrees are deleted before text is taken. Where
a page has an article (or main) element, only text in it counts, and there plain text blocks (paragraphs, headings,
list items and the like) are never deleted for being frequent, as a host's articles may share passages; nor is a slot
that holds half of its page's text. Counting tells nothing about hosts of few pages, so elements that HTML itself sets
apart go as well (nav, header, footer, aside, form, script and the like, ARIA roles of landmarks, hidden ones), and those
whose class or id is, as a whole, one of ``MARKED``.

Tags are read as HTML reads them: quotes only quote at the start of a value, an unfinished tag or quoted value runs to the
end of the page, end tags without a start do nothing (that of a paragraph still parts blocks), and paragraphs, list items and cells end where the next begins. The
work is linear in the page, however deep it is nested.

Defined results: a null or empty page gives an empty text; pages without a host form a host of their own; tags may be
unclosed, overlap or end in the middle; an unfinished character reference stays as it is; text outside any block forms
blocks between the block elements around it; repeated rows are extracted each; other columns are ignored; an empty table
gives an empty result.
"""

from __future__ import annotations

import html as entities
import re
from collections import defaultdict

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import read_table, text_or_empty, written

#: A hash is template from so many pages of a host and this share of them on.
LEAST_PAGES, CONTENT_SHARE = 4, 0.01
#: A path is a slot if this share of its subtrees recurs, and it has subtrees for this share of the host's pages. The
#: shares bound what a host keeps to a fixed multiple of the subtrees of one page, however many pages it has.
SLOT_SHARE, SLOT_PAGES = 0.2, 0.05
#: Template hashes of all hosts up to which they are broadcast, by a count; beyond, they are joined by shuffle.
BROADCAST_HASHES = 500_000

# Element kinds of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template svg iframe xmp math".split())
DROP = frozenset(
    "head script style noscript template svg iframe nav header footer aside form button select option input textarea dialog menu title object canvas audio video map math".split()
)
BLOCK = frozenset(
    "html body article main section div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd table thead tbody tfoot tr td th caption blockquote pre figure figcaption address hgroup details summary fieldset center hr nav header footer aside form dialog menu".split()
)
TEXT_BLOCK = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd td th tr blockquote pre figcaption caption".split())
INLINE = frozenset("b i em strong span a u s small font sub sup code q cite mark".split())
#: What a start tag ends: the nearest of the first kinds, unless one of the second kinds is nearer.
CELLS, LISTS = ("td", "th"), ("ul", "ol", "dl", "table", "select")
ENDS = {"li": (("li",), LISTS), "dt": (("dt", "dd"), LISTS), "dd": (("dt", "dd"), LISTS), "tr": (("tr", *CELLS), LISTS), "td": (CELLS, LISTS), "th": (CELLS, LISTS), "option": (("option",), LISTS)}
WHOLE = frozenset("html body article main".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar".split())
#: Whole class names and ids of what is never main text, and of what is not outside an article.
MARKED = frozenset(
    "ad ads advert adverts advertisement adsbygoogle sponsored comment comments comment-list commentlist disqus_thread respond share share-buttons social-share newsletter newsletter-signup cookie-notice cookie-banner cookie-consent cookies".split()
)
MARKED_OUTSIDE = MARKED | frozenset("nav navbar navigation menu breadcrumb breadcrumbs header site-header footer site-footer sidebar widget widgets banner notice popup modal related pagination".split())

_VALUE = r"\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z)|[^\s>\"'][^\s>]*"
_ATTRS = rf"(?:[\s/]++|[^\s/>][^\s/>=]*+(?:\s*+=\s*+(?:{_VALUE})?)?)*+"
_TOKEN = re.compile(rf"<!--(?:>|->|.*?(?:--!?>|\Z))|<[!?][^>]*(?:>|\Z)|</(?![A-Za-z])[^>]+(?:>|\Z)|<(/?)([A-Za-z][^\s/>]*)({_ATTRS})(>|\Z)", re.S)
_ATTR = re.compile(rf"([^\s/>][^\s/>=]*+)(?:\s*+=\s*+({_VALUE})?)?")
_SPACE = re.compile(r"\s+")
_DIGITS = re.compile(r"[0-9]+")
_RAW_END = {tag: re.compile(rf"</{tag}(?=[\s/>])[^>]*>?", re.I) for tag in RAW}


class Node:
    __slots__ = ("tag", "attrs", "parts", "up")

    def __init__(self, tag: str, attrs: str, up: Node | None):
        self.tag, self.attrs, self.parts, self.up = tag, attrs, [], up

    def attributes(self) -> dict[str, str]:
        found: dict[str, str] = {}
        if self.attrs:
            for m in _ATTR.finditer(self.attrs):
                value = m[2] or ""
                found.setdefault(m[1].lower(), entities.unescape(value[1:].removesuffix(value[0]) if value[:1] in "\"'" and value else value))
        return found


class _Open:
    """The open elements, and by tag where in them each is, so that no search walks down the stack."""

    def __init__(self) -> None:
        self.nodes = [Node("#root", "", None)]
        self.places: dict[str, list[int]] = defaultdict(list)
        self.solid = [0]  # places of those that are not inline

    def last(self, tags: tuple[str, ...] | frozenset[str]) -> int:
        return max((self.places[t][-1] for t in tags if self.places.get(t)), default=0)

    def push(self, node: Node) -> None:
        at = len(self.nodes)
        self.nodes.append(node)
        self.places[node.tag].append(at)
        if node.tag not in INLINE:
            self.solid.append(at)

    def close(self, place: int) -> None:
        while len(self.nodes) > place:
            node = self.nodes.pop()
            self.places[node.tag].pop()
            if node.tag not in INLINE:
                self.solid.pop()


def parse(page: str) -> Node:
    """The page's tree; parts of a node are nodes and raw strings."""
    now, pos, n = _Open(), 0, len(page)
    root = now.nodes[0]
    while pos < n:
        m = _TOKEN.search(page, pos)
        if m is None:
            now.nodes[-1].parts.append(page[pos:])
            break
        if m.start() > pos:
            now.nodes[-1].parts.append(page[pos : m.start()])
        pos = m.end()
        if m[2] is None or not m[4]:
            continue  # a comment, a declaration, or a tag that the page breaks off
        tag = m[2].lower()
        if m[1]:
            place = now.last((tag,))
            if place and not (tag in INLINE and now.solid[-1] > place):  # an inline end tag closes no blocks
                now.close(place)
            elif tag == "p" and not place:
                now.nodes[-1].parts.append(Node("p", "", now.nodes[-1]))  # HTML takes a lone end of a paragraph for an empty one
            continue
        if tag in BLOCK and tag not in ("html", "body") and now.nodes[now.solid[-1]].tag == "p":
            now.close(now.solid[-1])
        if tag in ENDS:
            kinds, stops = ENDS[tag]
            place = now.last(kinds)
            if place > now.last(stops):
                now.close(place)
        node = Node(tag, m[3].strip(), now.nodes[-1])
        now.nodes[-1].parts.append(node)
        if tag in VOID:
            continue
        if tag in RAW:
            end = _RAW_END[tag].search(page, pos)
            node.parts.append(page[pos : end.start() if end else n])
            pos = end.end() if end else n
            continue
        now.push(node)
    return root


def set_apart(node: Node, attributes: dict[str, str], outside: bool) -> bool:
    """Whether tag, role, or the whole of a class or id sets a subtree apart from main text."""
    if node.tag in DROP:
        return True
    if not attributes or node.tag in WHOLE:
        return False
    if "hidden" in attributes or attributes.get("aria-hidden") == "true" or attributes.get("role", "").lower() in ROLES:
        return True
    if "display:none" in attributes.get("style", "").replace(" ", "").lower():
        return True
    if node.tag in TEXT_BLOCK or node.tag in INLINE:
        return False
    names = {*attributes.get("class", "").lower().split(), attributes.get("id", "").lower()}
    return not names.isdisjoint(MARKED_OUTSIDE if outside else MARKED)


def _hash(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass")) >> 1


class Page:
    """A parsed page: its nodes, parents first, each with its path, content hash, length of text, and whether in an article."""

    def __init__(self, source: str):
        self.root = parse(source)
        self.nodes = [self.root]
        for node in self.nodes:
            self.nodes += [p for p in node.parts if isinstance(p, Node)]
        number = {id(x): k for k, x in enumerate(self.nodes)}
        n = len(self.nodes)
        self.up = [-1] + [number[id(x.up)] for x in self.nodes[1:]]
        self.attributes = [x.attributes() for x in self.nodes]
        self.path, self.content, self.length, self.dropped = [0] * n, [0] * n, [0] * n, [False] * n
        top = ["article"] if any(x.tag == "article" for x in self.nodes) else ["main"]
        self.inside, self.tops = [False] * n, []
        for k, node in enumerate(self.nodes[1:], 1):
            a, up = self.attributes[k], self.up[k]
            self.path[k] = _hash(f"{self.path[up]} {node.tag} {_DIGITS.sub('#', a.get('class', ''))} {_DIGITS.sub('#', a.get('id', ''))}")
            main = node.tag in top or (top[0] == "main" and a.get("role") == "main")
            self.dropped[k] = self.dropped[up] or set_apart(node, a, not (self.inside[up] or main))
            if main and not self.inside[up] and not self.dropped[k]:
                self.tops.append(k)
            self.inside[k] = self.inside[up] or (main and not self.dropped[k])
        for k in range(n - 1, -1, -1):
            feed, length = [self.nodes[k].tag, "|", self.nodes[k].attrs, "|"], 0
            for p in self.nodes[k].parts:
                if isinstance(p, Node):
                    feed.append(f"<{self.content[number[id(p)]]}>")
                    length += self.length[number[id(p)]]
                elif t := _SPACE.sub(" ", p).strip():
                    feed.append(t)
                    length += len(t)
            self.content[k], self.length[k] = _hash("".join(feed)), length
        self.number = number

    def counted(self) -> list[int]:
        """The nodes whose subtrees can be template."""
        return [
            k for k, x in enumerate(self.nodes)
            if x.tag in BLOCK and x.tag not in WHOLE and self.length[k] and not (self.inside[k] and x.tag in TEXT_BLOCK)
        ]

    def template(self, hashes: frozenset[int], slots: frozenset[int]) -> set[int]:
        """The nodes that the host's counts tell to be template."""
        half = self.length[self.tops[0]] if self.tops else self.length[0] / 2
        return {
            k for k in self.counted()
            if self.content[k] in hashes or (self.path[k] in slots and self.nodes[k].tag not in TEXT_BLOCK and self.length[k] < max(half, 1))
        }

    def text(self, gone: set[int] = frozenset(), by_tags: bool = True) -> str:
        """Blocks of text without the nodes ``gone``; without ``by_tags`` only these go, and scripts and the like."""
        blocks: list[str] = []
        line: list[str] = []

        def close() -> None:
            found = _SPACE.sub(" ", entities.unescape("".join(line))).strip()
            line.clear()
            if found:
                blocks.append(found)

        for top in (self.tops if by_tags else []) or [0]:
            stack: list = [self.nodes[top]]
            while stack:
                node = stack.pop()
                if node is None:
                    close()
                elif isinstance(node, str):
                    line.append(node)
                elif (k := self.number[id(node)]) in gone or (k != top and (self.dropped[k] if by_tags else node.tag in RAW or node.tag == "head")):
                    if node.tag in BLOCK:
                        close()
                else:
                    if node.tag in BLOCK:
                        close()
                        stack.append(None)
                    elif node.tag == "br":
                        line.append(" ")
                    stack += reversed(node.parts)
            close()
        return "\n\n".join(blocks)


def main_text(page: str | None, hashes: frozenset[int] = frozenset(), slots: frozenset[int] = frozenset()) -> str:
    """The main text of a page, given the template hashes and slots of its host."""
    if not page:
        return ""
    found = Page(page)
    return found.text(found.template(hashes, slots) if hashes or slots else frozenset())


def host_of(url: str) -> F.Column:
    return F.lower(F.regexp_extract(text_or_empty(url), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def subtree_counts(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(host, path, content, pages): on how many different pages of a host a subtree stands at a path; path 0 counts all."""

    @F.pandas_udf("array<struct<path:long,content:long>>")
    def subtrees(texts: pd.Series) -> pd.Series:
        out = []
        for t in texts:
            page = Page(t or "")
            out.append([{"path": p, "content": c} for p, c in {(0, 0), *((page.path[k], page.content[k]) for k in page.counted())}])
        return pd.Series(out, dtype=object)

    rows = pages.select(host_of(url_col).alias("host"), F.xxhash64(html_col).alias("page"), F.explode(subtrees(F.col(html_col))).alias("s"))
    return rows.select("host", "s.path", "s.content", "page").distinct().groupBy("host", "path", "content").agg(F.count("*").alias("pages"))


def site_templates(pages: DataFrame, url_col: str = "url", html_col: str = "html", least_pages: int = LEAST_PAGES, content_share: float = CONTENT_SHARE, slot_share: float = SLOT_SHARE, slot_pages: float = SLOT_PAGES) -> DataFrame:
    """(host, hashes, slots) of hosts with template subtrees."""
    counts = written(subtree_counts(pages, url_col, html_col), "subtrees")
    hosts = counts.where("path = 0").select("host", F.col("pages").alias("of"))
    real = counts.where("path <> 0")
    often = real.groupBy("host", "content").agg(F.sum("pages").alias("n")).where(F.col("n") >= least_pages).join(hosts, "host")
    often = often.where(F.col("n") >= F.col("of") * content_share).select("host", F.col("content").alias("hash"), F.lit(False).alias("slot"))
    paths = real.groupBy("host", "path").agg(F.sum("pages").alias("n"), F.sum(F.when(F.col("pages") > 1, F.col("pages")).otherwise(0)).alias("again")).join(hosts, "host")
    paths = paths.where((F.col("again") >= least_pages) & (F.col("again") >= F.col("n") * slot_share) & (F.col("n") >= F.col("of") * slot_pages))
    found = often.unionByName(paths.select("host", F.col("path").alias("hash"), F.lit(True).alias("slot")))
    both = [F.collect_list(F.when(F.col("slot") == kind, F.col("hash"))).alias(name) for name, kind in (("hashes", False), ("slots", True))]
    return found.groupBy("host").agg(*both)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", **options) -> DataFrame:
    """(page_id, url, text, n_chars) for each page."""
    sites = written(site_templates(pages, url_col, html_col, **options), "templates")
    if (sites.agg(F.sum(F.size("hashes") + F.size("slots"))).first()[0] or 0) <= BROADCAST_HASHES:
        sites = F.broadcast(sites)
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), host_of(url_col).alias("host"))

    @F.pandas_udf("string")
    def text(sources: pd.Series, hashes: pd.Series, slots: pd.Series) -> pd.Series:
        as_set = lambda x: frozenset() if x is None else frozenset(np.asarray(x).tolist())
        return pd.Series([main_text(p, as_set(h), as_set(t)) for p, h, t in zip(sources, hashes, slots, strict=True)], dtype=object)

    out = rows.join(sites, "host", "left").select("page_id", "url", text("html", "hashes", "slots").alias("text"))
    return out.withColumn("n_chars", F.char_length("text").cast("long"))


def op4_html_text(spark, sf_dir: str) -> DataFrame:
    return extract(read_table(spark, sf_dir, "pages"))
