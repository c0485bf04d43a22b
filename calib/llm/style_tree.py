"""Main text of web pages by site style trees.

The DOMs of one host are merged: a node stands for all elements with one path of tags and classes. How evenly
its presentations (orders of child tags) and contents (texts) spread over the pages is an entropy, from which
comes its importance: what looks and reads alike everywhere has little. A branch is removed from every page of
the host if its importance, averaged down the branch, and that of every branch within it stay under a threshold.
Tags, roles and classes are what is known beforehand: some name what is never content, and what stands outside
a page's article has its importance scaled down by how little text there is beside that of the article. All sums are additive, so a host of any size is merged in parts.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.llm.shared import materialize, plus
from calib.llm.url_filter import url_parts

#: Branches under this importance go, if at least so many pages of the host have them.
IMPORTANCE, PAGES = 0.2, 4
#: Importance of a branch outside the article that fewer pages have.
UNKNOWN = 0.4
#: Weight of a level against the one above it.
DECAY = 0.9
#: Bytes of branches to remove up to which they are broadcast; beyond, pages are joined by host.
BROADCAST_BYTES = 32 << 20

VOID = set("area base br col embed hr img input link meta source track wbr".split())
BLOCKS = set("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup html li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split())
NO_CONTENT = set("head script style noscript template iframe object embed svg canvas audio video nav footer aside form button select textarea datalist dialog menu input label fieldset".split())
#: Words of a class, id or role that name something other than the article.
NO_CONTENT_WORDS = set("ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion sidebar menu nav navbar navigation breadcrumb breadcrumbs footer cookie cookies consent gdpr notice alert popup modal overlay subscribe subscription newsletter signup login share sharing social related recommended widget pagination pager comment comments disqus respond replies toolbar masthead copyright disclaimer contentinfo complementary search skip".split())
_CLOSES_P = BLOCKS - {"body", "html", "caption", "tbody", "td", "tfoot", "th", "thead", "tr", "option", "optgroup"}
#: tag: (what it closes, where the search for it ends).
_CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
_WORDS = re.compile(r"[^a-z0-9]+")


@lru_cache(1 << 16)
def _path_hash(path: str) -> int:
    return _hash(path)


def _hash(x: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(x.encode("utf-8", "surrogatepass")) - (1 << 63)


class Node:
    __slots__ = ("children", "main", "no_content", "path", "tag", "up")

    def __init__(self, tag: str, path: str, up: Node | None, main: bool, no_content: bool):
        self.tag, self.path, self.up, self.main, self.no_content, self.children = tag, path, up, main, no_content, []


class Page(HTMLParser):
    """Blocks of text with the node that each stands in; `nodes` are all elements."""

    def __init__(self, html: str):
        super().__init__(convert_charrefs=True)
        self.top = Node("", "", None, False, False)
        self.nodes: list[Node] = []
        self.blocks: list[tuple[Node, str]] = []
        self.here, self.parts, self.owner = self.top, [], self.top
        self.feed(html)
        self.close()
        self.flush()

    def flush(self) -> None:
        if self.parts:
            if text := " ".join("".join(self.parts).split()):
                self.blocks.append((self.owner, text))
            self.parts = []

    def leave(self, node: Node) -> None:
        """Closes everything down to node."""
        self.flush()
        self.here = node.up

    def close_any(self, tags: set[str], stop: set[str]) -> None:
        node = self.here
        while node.up is not None and node.tag not in stop:
            if node.tag in tags:
                return self.leave(node)
            node = node.up

    def handle_starttag(self, tag: str, attrs) -> None:
        if tag == "br":
            self.parts.append("\n")
        if tag in _CLOSES:
            self.close_any(*_CLOSES[tag])
        if tag in _CLOSES_P:
            self.close_any({"p"}, {"table", "td", "th", "button"})
        if tag in BLOCKS or tag in NO_CONTENT:
            self.flush()
        up = self.here
        names = " ".join(v or "" for k, v in attrs if k in ("class", "id", "role")).lower()
        words = {x for x in _WORDS.split(names) if x} if names else set()
        main = up.main or tag in ("article", "main") or "articlebody" in " ".join(v or "" for k, v in attrs if k == "itemprop").lower() or bool(words & {"main", "article"} and tag == "div" and "role" in dict(attrs))
        bad = up.no_content or tag in NO_CONTENT or bool(words & NO_CONTENT_WORDS) or (not main and (tag == "header" or "header" in words)) or any(k == "hidden" for k, _ in attrs)
        node = Node(tag, f"{up.path}/{tag}" + "".join(f".{x}" for x in sorted(words)), up, main and tag != "body", bad)
        up.children.append(tag)
        self.nodes.append(node)
        if tag not in VOID:
            self.here = node

    def handle_startendtag(self, tag: str, attrs) -> None:
        self.handle_starttag(tag, attrs)

    def handle_endtag(self, tag: str) -> None:
        node = self.here
        while node.up is not None and node.tag != tag:
            node = node.up
        if node.up is None:
            if tag in ("p", "br"):
                self.flush()
            return
        if tag in BLOCKS or tag in NO_CONTENT:
            self.leave(node)
        else:
            self.here = node.up

    def handle_data(self, data: str) -> None:
        if not self.here.no_content:
            if not self.parts:
                self.owner = self.here
            self.parts.append(data)


def ancestors(node: Node) -> Iterator[Node]:
    while node.up is not None:
        yield node
        node = node.up


def main_text(html: str | None, peaks: dict[int, float] | None = None) -> str:
    """The blocks of the page, joined by line feeds. peaks: importance by hash of path, of branches that enough pages have.

    Branches of little importance go, wherever they stand. Beside an article or main element with text, a block
    must be important enough in spite of that element: its importance counts by the share of such text to the
    article's, so that a story beside a teaser stays. If removal would leave nothing of a page, it is not done.
    """
    peaks, page = peaks or {}, Page(html or "")
    inside = sum(len(t) for n, t in page.blocks if n.main)
    beside = min(1.0, sum(len(t) for n, t in page.blocks if not n.main) / inside) if inside else 1.0

    def stays(n: Node) -> bool:
        if any(peaks.get(_path_hash(a.path), 1.0) < IMPORTANCE for a in ancestors(n)):
            return False
        return n.main or not inside or beside * peaks.get(_path_hash(n.path), UNKNOWN) >= IMPORTANCE

    return "\n".join([t for n, t in page.blocks if stays(n)] or [t for _, t in page.blocks])


def style_statistics(pages: DataFrame) -> DataFrame:
    """host, path and depth of merged nodes with (kind, feature) sums: pages, occurrences c and c * ln(c).

    Rows of one key are partial sums of different tasks. Nodes inside an article count like all others.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}

        def flush() -> pa.RecordBatch:
            rows = [(*k, *v) for k, v in held.items()]
            held.clear()
            cols = list(zip(*rows)) if rows else [[]] * 8
            kinds = (pa.string(), pa.int64(), pa.list_(pa.int64()), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.float64())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["host", "path", "line", "kind", "feature", "pages", "c", "clogc"])

        for b in batches:
            for host, html in zip(b.column("host").to_pylist(), b.column("html").to_pylist()):
                if not host or not html:
                    continue
                page = Page(html)
                styles: dict[Node, tuple] = {}
                for n in page.nodes:
                    if not n.no_content:
                        styles.setdefault(n.path, (n, set()))[1].add(" ".join(x for x, y in zip(n.children, [None, *n.children]) if x != y))
                line = {p: tuple(_path_hash(a.path) for a in ancestors(n)) for p, (n, _) in styles.items()}
                found = Counter((p, "style", _hash("\n".join(sorted(s)))) for p, (_, s) in styles.items())
                found.update((n.path, "text", _hash(t)) for n, t in page.blocks if n.path in line)
                for (p, kind, feature), c in found.items():
                    x = held.setdefault((host, _path_hash(p), line[p], kind, feature), [0, 0, 0.0])
                    x[0] += 1
                    x[1] += c
                    x[2] += c * math.log(c)
                if len(held) > 100_000:
                    yield flush()
        yield flush()

    rows = url_parts(pages.select("url", "html")).select("host", "html")
    return rows.mapInArrow(run, "host string, path long, line array<long>, kind string, feature long, pages long, c long, clogc double")


def importance(pages: DataFrame) -> DataFrame:
    """host, path, pages and importance (0 to 1) of every branch of every host's style tree, and the peak of importance within it."""
    f = style_statistics(pages).groupBy("host", "path", "line", "kind", "feature").agg(F.sum("pages").alias("pages"), F.sum("c").alias("c"), F.sum("clogc").alias("clogc"))
    style, text = F.col("kind") == "style", F.col("kind") == "text"
    node = f.groupBy("host", "path", "line").agg(
        F.sum(F.when(style, F.col("pages"))).alias("pages"),
        F.sum(F.when(style, F.col("pages") * F.log(F.col("pages")))).alias("plogp"),
        F.sum(F.when(text, F.lit(1))).alias("features"),
        F.sum(F.when(text, F.log(F.col("c")) - F.col("clogc") / F.col("c"))).alias("entropy"),
    )
    m = F.col("pages")
    node = node.withColumn("shape", F.when(m > 1, (F.log(m) - F.col("plogp") / m) / F.log(m)).otherwise(1.0))
    node = node.withColumn("content", F.when(F.col("features") > 0, F.when(m > 1, F.greatest(F.lit(0.0), 1 - F.col("entropy") / F.col("features") / F.log(m))).otherwise(1.0)))
    node = materialize(node, "nodes")
    # a node weighs on itself and, less with each level, on every branch that it is part of
    own = F.greatest(F.coalesce("content", "shape"), F.when(F.col("features").isNull(), F.col("shape")).otherwise(0.0))
    up = node.select("host", "pages", own.alias("own"), F.posexplode("line").alias("level", "branch"))
    weight = F.pow(F.lit(DECAY), F.col("level"))
    found = up.groupBy("host", F.col("branch").alias("path")).agg(F.max("pages").alias("pages"), (F.sum(weight * F.col("own")) / F.sum(weight)).alias("importance"))
    # a root that is alike everywhere may hold the branch that is not
    within = node.select("host", "path", F.explode("line").alias("branch")).join(found.select("host", "path", "importance"), ["host", "path"])
    peak = within.groupBy("host", F.col("branch").alias("path")).agg(F.max("importance").alias("peak"))
    return found.join(peak, ["host", "path"])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every row of pages (page_id, url, html).

    Null html gives an empty text; pages without a host are judged by themselves. Repeated rows count as pages of
    their own and come out one by one. Other columns are not read, so their names may clash.
    """
    known = importance(pages).where(F.col("pages") >= PAGES).groupBy("host").agg(F.collect_list(F.struct("path", F.col("peak").cast("float").alias("peak"))).alias("known"))
    known = materialize(known.select("host", F.col("known.path").alias("paths"), F.col("known.peak").alias("peaks")), "branches")
    size = known.agg(F.sum(F.size("paths") * 12 + F.length("host") + 32)).first()[0] or 0
    if size <= BROADCAST_BYTES:
        known = F.broadcast(known)
    rows = url_parts(pages.select("page_id", "url", "html")).join(known, "host", "left").select("page_id", "url", "html", "paths", "peaks")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            held = (dict(zip(p, x)) if p else None for p, x in zip(b.column("paths").to_pylist(), b.column("peaks").to_pylist()))
            texts = [main_text(h, p) for h, p in zip(b.column("html").to_pylist(), held)]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(run, plus(pages.select("page_id", "url"), text="string", n_chars="long"))
