"""HTML extraction by removal of the site's template.

Every page is parsed into a tree. A first pass hashes the subtree of each block element; Spark counts,
for each host, on how many pages with different main text a hash occurs, and at which end of the
article. A second pass deletes the subtrees that recur across many pages of their host, together with
what the markup itself declares to be no article (menus, headers, footers, sidebars, notices, adverts,
forms, scripts, styles, reader comments), and returns the text of what is left: of the explicit
articles of a page if it has any, else of the whole page.

Copies of a page do not make its article a template, as they share one main text. Inside an explicit
article a recurring paragraph may be a passage that several articles quote, so there a block is only
template if no other host has it in an article, and it recurs at one and the same place, one of the
first or last two blocks, of nearly all the articles that have it, of which nearly all are otherwise
different (near copies are not).
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from functools import cache
from html import unescape

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.runtime import map_arrow, settle

#: A subtree is template from this share of a host's pages on, but never on fewer than LEAST_PAGES pages,
#: and always from MOST_NEEDED on, however large the host.
LEAST_PAGES = 4
LEAST_SHARE = 0.05
MOST_NEEDED = 20
#: A block of an article is template if this share of its pages have it at one place near an end, and
#: this share of them differ in what else they hold, among articles of at least LEAST_BLOCKS blocks (so
#: that two or more lie between the ends).
SAME_PLACE = 0.9
EDGE = 2
LEAST_BLOCKS = 2 * EDGE + 2
#: Elements are nested so deep at most; further ones are siblings, as in browsers.
MOST_DEPTH = 512
#: Template hashes are sent to all executors up to this size, else joined to the pages.
BROADCAST_BYTES = 32 << 20

# Element names of the HTML standard by their role here.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe noembed noframes xmp".split())
DROPPED = frozenset("head script style noscript template nav footer aside form button select option textarea title iframe object embed svg canvas dialog menu audio video map applet fieldset datalist".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split())
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre figcaption dd dt".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
CLOSES = {
    "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "td", "th"]),
    "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"]), "option": frozenset(["option"]),
    "thead": frozenset(["tr", "td", "th"]), "tbody": frozenset(["thead", "tbody", "tr", "td", "th"]), "tfoot": frozenset(["tbody", "tr", "td", "th"]),
}
SCOPES = frozenset("ul ol dl table select body html article section div main".split())
# Words in class, id and role that name something other than the article.
NAMES = frozenset(
    "ad ads advert adverts advertisement advertising adsense adslot adbox banner billboard breadcrumb breadcrumbs comment comments commentlist consent "
    "contentinfo complementary cookie cookies copyright dialog discussion disqus footer gdpr header login masthead menu menubar modal nav navbar navigation "
    "newsletter notice notices notification pager pagination paywall popup privacy promo promoted promotion recommendations recommended related replies reply respond "
    "search share sharing sidebar signup sitemap skip social sponsor sponsored subscribe tagcloud toolbar topbar widget".split()
)

_TAG = re.compile(r"/?[a-zA-Z][^\s/>]*")
_QUOTED = re.compile(r"[^>\"']*+(?:>|(\"[^\"]*+\"|'[^']*+'|[\"']))")
_ATTRIBUTE = re.compile(r"([^\s=/\"'<>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
#: Place of a subtree that is template wherever it recurs.
FREE = 9
_NAME = re.compile(r"[a-z]+|[A-Z]+(?![a-z])|[A-Z][a-z]*")


class Node:
    __slots__ = ("tag", "attrs", "kids", "hash", "parent", "links", "size", "block", "depth")

    def __init__(self, tag: str, attrs: str, parent: Node | None):
        self.tag, self.attrs, self.parent = tag, attrs, parent
        self.kids: list[Node | str] = []
        self.depth = parent.depth + 1 if parent is not None else 0
        self.block = self if parent is None or tag in BLOCK else parent.block  # nearest block, itself included

    def attributes(self) -> dict[str, str]:
        return {m[1].lower(): unescape(m[2] or m[3] or m[4] or "") for m in _ATTRIBUTE.finditer(self.attrs)} if self.attrs else {}


def _tokens(html: str) -> Iterator[tuple[int, int, str, str]]:
    """(start, stop, name, attributes) of tags, and of comments and declarations, which have no name.
    A \">\" in a quoted value does not end a tag; where that reading finds no end, or has cost more than
    a few passes over the page, the next \">\" does, so the work is linear in the page."""
    at, end, spare = 0, len(html), 4 * len(html) + 4096
    while True:
        at = html.find("<", at)
        if at < 0:
            return
        if html.startswith("<!--", at):
            stop = html.find("-->", at + 4)
            stop = end if stop < 0 else stop + 3
            yield at, stop, "", ""
            at = stop
            continue
        m = _TAG.match(html, at + 1)
        if not m:
            if html[at + 1: at + 2] in ("!", "?"):
                stop = html.find(">", at)
                stop = end if stop < 0 else stop + 1
                yield at, stop, "", ""
                at = stop
            else:
                at += 1
            continue
        place, stop = m.end(), -1
        while spare > 0:
            q = _QUOTED.match(html, place)
            if q is None:
                spare -= end - place
                break
            spare -= q.end() - place
            if q[1] is None:
                stop = q.end()
                break
            place = q.end()
        if stop < 0:
            stop = html.find(">", m.end()) + 1
            if not stop:
                return
        yield at, stop, m[0], html[m.end(): stop - 1]
        at = stop


def parse(html: str) -> Node:
    """A tree of elements and decoded texts; unclosed and misplaced tags are tolerated."""
    root = Node("#root", "", None)
    here, at, end, skip = root, 0, len(html), 0
    open_: Counter[str] = Counter()

    def close(up: Node) -> Node:
        """up and all that is open in it end; returns what they were in."""
        node = here
        while True:
            open_[node.tag] -= 1
            if node is up:
                return up.parent
            node = node.parent

    for start, stop, name, attrs in _tokens(html):
        if start < skip:
            continue
        if start > at:
            here.kids.append(unescape(html[at: start]))
        at = stop
        if not name:
            continue
        tag = name.lstrip("/").lower()
        if name[0] == "/":
            if open_[tag]:
                up = here
                while up.tag != tag:
                    up = up.parent
                here = close(up)
            continue
        if tag in BLOCK:  # a block ends an open paragraph
            up = here.block
            if up.tag == "p" or (up.tag in HEADINGS and tag in HEADINGS):
                here = close(up)
        if tag in CLOSES:
            up, last = here.block, None
            while up is not root and up.tag not in SCOPES:
                if up.tag in CLOSES[tag]:
                    last = up
                up = up.parent.block
            here = close(last) if last else here
        node = Node(tag, attrs, here)
        here.kids.append(node)
        if tag in VOID:
            continue
        if tag in RAW:
            found = _closing(tag).search(html, at)
            begin = found.start() if found else end
            at = html.find(">", begin) + 1 or end if found else end
            skip = at
            continue
        if not attrs.endswith("/") and node.depth < MOST_DEPTH:
            here = node
            open_[tag] += 1
    if at < end:
        here.kids.append(unescape(html[at:]))
    return root


@cache
def _closing(tag: str) -> re.Pattern:
    return re.compile(rf"</{re.escape(tag)}[\s/>]", re.I)


def _nodes(root: Node) -> list[Node]:
    """Elements, every parent before its children."""
    out = [root]
    for node in out:
        out += [k for k in node.kids if isinstance(k, Node)]
    return out


def _measure(nodes: list[Node]) -> None:
    """Subtree hashes, characters of text, and those of them that are in links."""
    for node in reversed(nodes):
        node.size = node.links = 0
        parts = [node.tag]
        for kid in node.kids:
            if isinstance(kid, str):
                text = " ".join(kid.split())
                if text:
                    node.size += len(text)
                    parts.append(text)
            elif kid.tag not in RAW:
                node.size += kid.size
                node.links += kid.links
                parts.append(f"\x01{kid.hash}")
        if node.tag == "a":
            node.links = node.size
        node.hash = xxhash.xxh64_intdigest("\x00".join(parts).encode("utf-8", "surrogatepass"))


def _named_other(node: Node) -> bool:
    if not node.attrs:
        return False
    a = node.attributes()
    if "hidden" in a or a.get("aria-hidden") == "true" or "display:none" in a.get("style", "").replace(" ", "").lower():
        return True
    return any(w.lower() in NAMES for k in ("class", "id", "role") for w in _NAME.findall(a.get(k, "")))


class Page:
    """A parsed page: its tree, what its markup rules out, and its main elements."""

    def __init__(self, html: str):
        root = parse(html)
        self.nodes = _nodes(root)
        _measure(self.nodes)
        self.out: set[int] = set()
        whole = {id(n) for n in self.nodes if n.tag in ("article", "main")}
        keeps = set()
        for n in self.nodes:
            if id(n) in whole:
                up = n.parent
                while up is not None and id(up) not in keeps:
                    keeps.add(id(up))
                    up = up.parent
        inside = set()
        gone: set[int] = set()
        for n in self.nodes:
            if n.parent is not None and id(n.parent) in inside:
                inside.add(id(n))
            if n.parent is not None and id(n.parent) in gone:
                gone.add(id(n))
                continue
            if n.tag in ("#root", "html", "body"):
                continue
            spared = id(n) in keeps and n.tag not in DROPPED
            if n.tag in DROPPED or n.tag == "header" or (not spared and n.tag != "main" and _named_other(n)):
                self.out.add(id(n))
                if not (id(n) in inside and (n.tag == "header" or "header" in n.attrs)):
                    gone.add(id(n))
            elif id(n) in whole:
                inside.add(id(n))
        self.inside = inside
        self.order = {}
        todo = [root]
        while todo:  # page order
            n = todo.pop()
            self.order[id(n)] = len(self.order)
            todo += [k for k in reversed(n.kids) if isinstance(k, Node)]
        mains = [n for n in self.nodes if n.tag == "article" and id(n) not in gone and id(n) not in self.out] or [n for n in self.nodes if n.tag == "main" and id(n) not in gone]
        tops = []
        taken: set[int] = set()
        for n in mains:
            up = n.parent
            while up is not None and id(up) not in taken:
                up = up.parent
            if up is None:
                taken.add(id(n))
                tops.append(n)
        prose = [n for n in tops if 2 * n.links <= n.size]
        self.explicit = bool(prose)
        self.mains = prose or [root]

    def main_hash(self) -> int:
        return xxhash.xxh64_intdigest("\n".join(self.text(frozenset())).encode("utf-8", "surrogatepass"))

    def _places(self) -> dict[int, int]:
        """Of the innermost blocks with text inside the explicit articles: 1 or 2 for the first two of an
        article, after its headings, -1 or -2 for the last two, else 0. Empty for short articles."""
        out: dict[int, int] = {}
        if not self.explicit:
            return out
        for main in self.mains:
            blocks = [n for n in _nodes(main) if n.tag in PROSE and n.size and id(n) not in self.out]
            text = [n for n in sorted(blocks, key=lambda n: self.order[id(n)]) if n.tag not in HEADINGS]
            if len(text) < LEAST_BLOCKS:
                continue
            for k, n in enumerate(text):
                out[id(n)] = k + 1 if k < EDGE else k - len(text) if len(text) - k <= EDGE else 0
        return out

    def candidates(self) -> list[tuple[int, int, int, int]]:
        """Distinct (hash, place, low, high) of the subtrees that may turn out to be template. The place is
        FREE where a subtree may go wherever it stands; low and high are the least and the greatest hash
        of the blocks between the ends of the articles."""
        place = self._places()
        found = {(n.hash, FREE, 0, 0) for n in self.nodes if n.size and self._may_go(n)}
        if place:
            inner = [n.hash for n in self.nodes if place.get(id(n)) == 0]
            found |= {(n.hash, place[id(n)], min(inner), max(inner)) for n in self.nodes if id(n) in place}
        return sorted(found)

    def _may_go(self, n: Node) -> bool:
        if n.tag in ("#root", "html", "body", "article", "main") or n.tag not in BLOCK:
            return False
        if self.explicit and id(n) in self.inside:
            return n.tag not in PROSE and (2 * n.links > n.size or not any(isinstance(k, Node) and k.tag in PROSE for k in n.kids))
        return True

    def text(self, templates) -> list[str]:
        """Blocks of the main elements without what is ruled out or recurs."""
        blocks: list[str] = []
        run: list[str] = []

        def flush() -> None:
            block = " ".join("".join(run).split())
            if block:
                blocks.append(block)
            run.clear()

        place = self._places() if templates else {}
        todo: list[tuple[object, bool]] = [(n, False) for n in reversed(self.mains)]
        while todo:
            item, headings_only = todo.pop()
            if item is None:
                flush()
                continue
            if isinstance(item, str):
                if not headings_only:
                    run.append(item)
                continue
            if id(item) in self.out:
                if id(item) in self.inside and (item.tag == "header" or "header" in item.attrs) and item.tag not in DROPPED:
                    headings_only = True
                else:
                    continue
            if item.hash in templates and (place.get(id(item)) or self._may_go(item)):
                continue
            if item.tag in HEADINGS:
                headings_only = False
            if item.tag == "br" or item.tag in ("img", "hr"):
                run.append(" ")
            block = item.tag in BLOCK
            if block:
                flush()
                todo.append((None, False))
            todo += [(k, headings_only) for k in reversed(item.kids)]
        flush()
        return blocks


def host(url: str = "url"):
    """Host of a URL in lower case, without port and user; empty if there is none."""
    found = F.regexp_extract(F.lower(F.trim(F.coalesce(F.col(url), F.lit("")))), r"^(?:[a-z][a-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1)
    return found


def templates(pages: DataFrame, least_pages: int = LEAST_PAGES, least_share: float = LEAST_SHARE, most_needed: int = MOST_NEEDED) -> DataFrame:
    """(host, hash): subtrees of pages (url, html) that recur on a host, on at least `least_share` of its
    pages, at least on `least_pages` and always on `most_needed`, counting pages of one main text once.
    Blocks of articles must besides recur at one place near an end (SAME_PLACE), on this host only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hosts, rows, places = [], [], []
            for name, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                page = Page(html or "")
                main = page.main_hash()
                found = [(0, FREE, 0, 0), *page.candidates()]  # 0 stands for the page itself
                hosts += [name] * len(found)
                rows += [(h, main, *((main, main) if p == FREE else (low, high))) for h, p, low, high in found]
                places += [c[1] for c in found]
            hashes = np.array(rows, dtype=np.uint64).reshape(-1, 4)
            columns = [pa.array(np.ascontiguousarray(hashes[:, k]).view(np.int64)) for k in range(4)]
            yield pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), *columns, pa.array(places, pa.int32())], ["host", "hash", "main", "low", "high", "place"])

    rows = map_arrow(pages.select(host().alias("host"), "html"), run, "host string, hash long, main long, low long, high long, place int").distinct()
    counts = settle(rows.groupBy("host", "hash", "place").agg(F.count("*").alias("n"), F.count_distinct("low").alias("low"), F.count_distinct("high").alias("high")), "subtree-counts")
    of_host = counts.filter("hash = 0").select("host", F.col("n").alias("pages"))
    often = counts.filter("hash <> 0").groupBy("host", "hash").agg(F.sum("n").alias("n"), F.max(F.when(F.col("place") != 0, F.least("n", "low", "high"))).alias("same"))
    often = often.filter((F.col("n") >= least_pages) & (F.col("same") >= F.col("n") * SAME_PLACE)).join(of_host, "host")
    shared = counts.filter(f"place <> {FREE}").select("host", "hash").distinct().groupBy("hash").count().filter("count > 1")
    often = often.join(shared.select("hash"), "hash", "left_anti")
    return often.filter(F.col("n") >= F.least(F.col("pages") * least_share, F.lit(float(most_needed)))).select("host", "hash")


def extract(pages: DataFrame, least_pages: int = LEAST_PAGES, least_share: float = LEAST_SHARE) -> DataFrame:
    """page_id, url, text of every row of pages (page_id, url, html).

    Character references are decoded, white space inside a block becomes one space, blocks are
    trimmed and joined by \\n in page order; a null or empty page, or one without article, has an
    empty text. Pages without a host share the host "". Repeated rows give repeated rows.
    """
    known = settle(templates(pages, least_pages, least_share), "templates")
    rows = pages.select("page_id", "url", "html", host().alias("host"))
    if known.count() * 40 <= BROADCAST_BYTES:
        per_host = known.groupBy("host").agg(F.collect_list("hash").alias("hashes")).toPandas()
        shared = pages.sparkSession.sparkContext.broadcast({h: frozenset(int(x) & (1 << 64) - 1 for x in v) for h, v in zip(per_host["host"], per_host["hashes"], strict=True)})
        rows = rows.withColumn("hashes", F.lit(None).cast("array<bigint>"))
    else:  # at most (block elements of a page / least share) hashes a host, or of its pages / MOST_NEEDED
        shared = None
        rows = rows.join(known.groupBy("host").agg(F.collect_list("hash").alias("hashes")), "host", "left").select("page_id", "url", "html", "host", "hashes")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for html, name, own in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True):
                gone = shared.value.get(name, frozenset()) if shared is not None else frozenset(x & (1 << 64) - 1 for x in own or ())
                texts.append("\n".join(Page(html or "").text(gone)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], ["page_id", "url", "text"])

    schema = f"page_id {pages.schema['page_id'].dataType.simpleString()}, url string, text string"
    return map_arrow(rows, run, schema)
