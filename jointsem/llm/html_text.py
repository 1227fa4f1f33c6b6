"""Main text of web pages by removal of site templates.

Every element outside a page's article is hashed with its tags and text.  A
hash that many pages of one host share is that host's template, and elements
with it are deleted.  Elements that their tag, role, class or id names as a
menu, header, footer, sidebar, notice, advert, form, script, style or reader
comments go without counting.  If a page has an <article> or <main>, its text is
what is left of these; otherwise it is what is left of the body.

Inside an article, block elements are counted over the host's distinct articles, so
pages that carry the same article count once, and one is template from a share of
`within` of them.  An article that would lose over half of its text so keeps it
all; outside, an element with over half of a page's text is kept as well.

An element is template if at least `share` of the host's pages, and at least
`least` of them, hold it.  So a host has a bounded number of template hashes,
whatever its number of pages, and they are one row of its own.

Nulls: a null html is empty, a null url belongs to the host "".  Repeated rows
count as pages of their own.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from jointsem.llm.store import stage
from jointsem.llm.text import slices

SHARE = 0.05
LEAST = 4
WITHIN = 0.5
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*+[^>]*)>", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
# Element names of HTML, by what becomes of them.
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style textarea title noscript template iframe svg math xmp noembed noframes".split())
_GONE = frozenset("nav header footer aside form script style noscript template iframe svg math object embed button select textarea input label dialog menu head title option canvas audio video noembed noframes xmp".split())
_INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
_CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
_SELF = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("table", "tr"), "th": ("table", "tr"), "option": ("select",)}
_BOILER = re.compile(
    r"(?:^|[\s_-])(?:nav|navbar|navigation|menu|header|masthead|footer|sidebar|aside|cookies?|consent|gdpr|notices?|banner|advert\w*|ads?|adsense|promo\w*|sponsor\w*|share|sharing|social|comments?|replies|reply|disqus|related|recommended|newsletter|subscribe|breadcrumbs?|pagination|pager|popup|modal|login|signup|search|skip|toolbar|widget|contentinfo|complementary)(?:$|[\s_-])",
    re.I,
)


@dataclass
class Element:
    """An element as a range of a page's pieces, with the hash of what it holds."""

    tag: str
    start: int
    stop: int = 0
    hash: int = 0
    letters: int = 0
    gone: bool = False
    inside: bool = False
    within: bool = False


class Page:
    """A page as pieces (texts and block breaks, None) and elements over them."""

    def __init__(self, source: str):
        self.pieces: list[str | None] = []
        self.elements: list[Element] = []
        self.letters = 0
        stack: list[Element] = []
        held: list[list[str]] = [[]]
        inside = at = 0

        def text(raw: str) -> None:
            if raw:
                value = entities.unescape(raw) if "&" in raw else raw
                self.pieces.append(value)
                held[-1].append(value)
                self.letters += len(value)

        def close() -> None:
            nonlocal inside
            e = stack.pop()
            e.stop = len(self.pieces)
            own = " ".join("".join(held.pop()).split())
            e.letters = len(own)
            e.hash = xxhash.xxh64_intdigest(f"{e.tag}\0{own}") >> 1
            held[-1].append(f"\1{e.tag}\2{own}\3" if e.tag not in _INLINE else own)
            inside -= e.tag in ("article", "main")
            if e.tag not in _INLINE:
                self.pieces.append(None)

        while m := _TOKEN.search(source, at):
            text(source[at : m.start()])
            at = m.end()
            tag = (m[2] or "").lower()
            if not tag:
                continue
            if m[1]:
                depth = next((k for k in range(len(stack) - 1, -1, -1) if stack[k].tag == tag), -1)
                if depth >= 0:
                    while len(stack) > depth:
                        close()
                elif tag == "p":
                    self.pieces.append(None)
                continue
            if tag in _CLOSES_P:
                self._end(stack, close, "p", ("button", "table", "td", "th", "caption", "object"))
            if tag in _SELF:
                self._end(stack, close, tag, _SELF[tag])
                if tag in ("td", "th"):
                    self._end(stack, close, "th" if tag == "td" else "td", _SELF[tag])
                if tag in ("dt", "dd"):
                    self._end(stack, close, "dd" if tag == "dt" else "dt", _SELF[tag])
            if tag not in _INLINE:
                self.pieces.append(None)
            if tag in _VOID or m[3].endswith("/") and tag in _RAW:
                continue
            named = tag in _GONE or any(_BOILER.search(next(v for v in a[1:] if v is not None)) for a in (x.groups() for x in _ATTRIBUTE.finditer(m[3]) if any(x.groups()[1:])))
            e = Element(tag, len(self.pieces), gone=named and tag not in ("html", "body", "article", "main"), inside=inside > 0, within=inside > 0)
            self.elements.append(e)
            stack.append(e)
            held.append([])
            if tag in ("article", "main"):
                inside += 1
                for x in stack[:-1]:
                    x.inside = x.inside or x.tag not in ("article", "main")
            if tag in _RAW:
                end = re.compile(rf"</{tag}\b[^>]*>", re.I).search(source, at)
                text(source[at : end.start()] if end else source[at:])
                at = end.end() if end else len(source)
                close()
        text(source[at:])
        while stack:
            close()

    @staticmethod
    def _end(stack: list[Element], close, tag: str, fence: tuple[str, ...]) -> None:
        """Close an open element of a tag whose end tag may be left out, unless a fence is nearer."""
        for k in range(len(stack) - 1, -1, -1):
            if stack[k].tag == tag:
                while len(stack) > k:
                    close()
                return
            if stack[k].tag in fence:
                return

    def candidates(self) -> set[int]:
        """Hashes of the elements that may be template."""
        return {e.hash for e in self.elements if not e.inside and not e.gone and e.letters and 2 * e.letters <= self.letters and e.tag not in ("html", "body", "article", "main")}

    def mains(self) -> list[Element]:
        """The outermost articles."""
        return [e for e in self.elements if e.tag in ("article", "main") and not e.inside and not self._under(e)]

    def article_candidates(self) -> tuple[int, list[Element]]:
        """A hash of the articles, and the blocks inside them that may be template."""
        mains = self.mains()
        most = max((e.letters for e in mains), default=0)
        return hash(tuple(e.hash for e in mains)), [e for e in self.elements if e.within and not e.gone and e.letters and 2 * e.letters <= most and e.tag not in _INLINE and e.tag not in ("article", "main") and any(m.start <= e.start and e.stop <= m.stop for m in mains)]

    def text(self, template: frozenset[int] = frozenset()) -> str:
        """The text that is left; white space of a block becomes one space, and blocks are joined by one."""
        open_ = [False] * (len(self.pieces) + 1)
        mains = self.mains()
        for e in mains or [Element("", 0, len(self.pieces))]:
            open_[e.start : e.stop] = [True] * (e.stop - e.start)
        able = self.candidates() if template else set()
        for e in self.elements:
            if e.gone or e.hash in template and e.hash in able and not e.inside and e.tag not in ("html", "body", "article", "main"):
                open_[e.start : e.stop] = [False] * (e.stop - e.start)
        if template and mains:
            size = lambda: sum(len(p) for p, o in zip(self.pieces, open_, strict=False) if o and p is not None)
            kept, whole = open_.copy(), size()
            for e in self.article_candidates()[1]:
                if ~e.hash in template:
                    open_[e.start : e.stop] = [False] * (e.stop - e.start)
            open_ = open_ if 2 * size() >= whole else kept
        return " ".join("".join(" " if p is None else p for p, o in zip(self.pieces, open_, strict=False) if o or p is None).split())

    def _under(self, e: Element) -> bool:
        """Whether an element that goes holds e."""
        return any(g.gone and g.start <= e.start and e.stop <= g.stop for g in self.elements)


def host(url: str = "url") -> Column:
    return F.lower(F.regexp_extract(F.coalesce(F.col(url).cast("string"), F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def templates(pages: DataFrame, url_col: str = "url", text_col: str = "html", share: float = SHARE, least: int = LEAST, within: float = WITHIN) -> DataFrame:
    """(host, hashes): the template of every host that has one; what is one inside articles only has its bits turned."""
    rows = pages.select(host(url_col).alias("host"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches):
            seen: dict[tuple[str, int, int], int] = {}
            for h, t in zip(batch.column(0).to_pylist(), texts, strict=True):
                page = Page(t.decode(errors="replace"))
                article, parts = page.article_candidates()
                for k in (0, *page.candidates()):
                    seen[h, k, 0] = seen.get((h, k, 0), 0) + 1
                for k in {-1, *(~e.hash for e in parts)} if page.mains() else ():
                    seen[h, k, article] = 1
            yield pa.RecordBatch.from_arrays([pa.array([h for h, _, _ in seen]), pa.array([k for _, k, _ in seen], pa.int64()), pa.array([a for _, _, a in seen], pa.int64()), pa.array(list(seen.values()), pa.int64())], names=["host", "hash", "article", "pages"])

    each = rows.mapInArrow(run, "host string, hash long, article long, pages long").groupBy("host", "hash", "article").agg(F.sum("pages").alias("pages"))
    counts = stage(each.groupBy("host", "hash").agg(F.sum(F.when(F.col("hash") < 0, 1).otherwise(F.col("pages"))).alias("pages")).where(F.col("hash").isin(0, -1) | (F.col("pages") >= least)), "elements")
    whole = counts.where("hash in (0, -1)").select("host", F.col("pages").alias("all"), (F.col("hash") < 0).alias("inner"))
    chosen = counts.where("hash not in (0, -1)").withColumn("inner", F.col("hash") < 0).join(whole, ["host", "inner"]).where(F.col("pages") >= F.col("all") * F.when(F.col("inner"), within).otherwise(share))
    return chosen.groupBy("host").agg(F.collect_list("hash").alias("hashes"))


def main_texts(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", text_col: str = "html", share: float = SHARE, least: int = LEAST) -> DataFrame:
    """id, url, text and n_chars of every row of pages."""
    known = stage(templates(pages, url_col, text_col, share, least), "templates")
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"), host(url_col).alias("host")).join(known, "host", "left").select("id", "url", "hashes", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches):
            out = [Page(t.decode(errors="replace")).text(frozenset(k or ())) for k, t in zip(batch.column(2).to_pylist(), texts, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out), pa.array([len(x) for x in out], pa.int64())], names=["id", "url", "text", "n_chars"])

    return rows.mapInArrow(run, "id long, url string, text string, n_chars long").withColumnsRenamed({"id": id_col, "url": url_col})
