"""Text, formulas and image places from web pages."""

from __future__ import annotations

import re
from collections.abc import Iterator
from html.parser import HTMLParser
from urllib.parse import urljoin

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import ensure_importable

SEGMENTS = "array<struct<pos:int,kind:string,text:string,image_url:string>>"
_SUPPRESSED = frozenset("script style nav header footer aside form noscript template iframe svg head".split())
_BLOCKS = frozenset("p div section article main h1 h2 h3 h4 h5 h6 li ul ol table tr blockquote pre figure figcaption dl dt dd hr br body".split())
_VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
_ADVERT = re.compile(r"(?:^|[\s_-])(?:ad|ads|advert|advertisement|banner|sponsor|promo|cookie|sidebar|comments?)(?:$|[\s_-])", re.I)
_TEX = re.compile(r"(?<!\$)\$\$(?!\$)(.+?)(?<!\$)\$\$(?!\$)|\\\[(.+?)\\\]|\\\((.+?)\\\)|(?<![\\$\w])\$(?!\s)([A-Za-z]|[^$\n]+?[^$\n\\\s])\$(?![\w$])", re.S)
MATH_SOURCES = ("delimiter", "mathml", "alt", "script")


class _Walk(HTMLParser):
    """One walk over a page's events: a text buffer is flushed at block borders and before a formula or an image."""

    def __init__(self, base: str, math: bool, images: bool, headings: bool, sources: tuple[str, ...]):
        super().__init__(convert_charrefs=True)
        self.base, self.math, self.images, self.headings, self.sources = base, math, images, headings, sources
        self.out: list[tuple[str, str | None, str | None]] = []
        self.buffer: list[str] = []
        self.off: list[str] = []  # open suppressed elements
        self.tex: list[str] | None = None  # inside a script or annotation of TeX
        self.mathml: list[str] | None = None
        self.noted: str | None = None

    def flush(self) -> None:
        text = " ".join("".join(self.buffer).split())
        self.buffer = []
        if not text:
            return
        if not (self.math and "delimiter" in self.sources):
            self.out.append(("text", text, None))
            return
        at = 0
        for m in _TEX.finditer(text):
            if text[at : m.start()].strip():
                self.out.append(("text", text[at : m.start()].strip(), None))
            self.out.append(("math", next(g for g in m.groups() if g).strip(), None))
            at = m.end()
        if text[at:].strip():
            self.out.append(("text", text[at:].strip(), None))

    def formula(self, text: str, source: str) -> None:
        self.flush()
        if self.math and source in self.sources and text.strip():
            self.out.append(("math", " ".join(text.split()), None))

    def handle_starttag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        a = {k: v or "" for k, v in attrs}
        if tag == "script" and "math/tex" in a.get("type", "") and not self.off:
            self.tex = []
            return
        hint = tag not in ("body", "html", "article", "main") and bool(_ADVERT.search(f"{a.get('class', '')} {a.get('id', '')}"))
        if self.off or tag in _SUPPRESSED or hint or (not self.headings and tag in ("h1", "h2", "h3", "h4", "h5", "h6")):
            if tag in _BLOCKS:
                self.flush()
            if tag not in _VOID:
                if self.off and tag in ("article", "main") and self.off[0] in ("nav", "header", "head"):
                    self.off.clear()  # left open: an article can't lie in a menu
                elif not self.off or tag == self.off[0]:
                    self.off.append(tag)
            return
        if tag == "math":
            self.mathml, self.noted = [], None
        elif tag == "annotation" and "tex" in a.get("encoding", "").lower():
            self.tex = []
        elif tag == "img":
            alt = a.get("alt", "")
            if "alt" in self.sources and ("\\" in alt or alt.startswith("$")):
                self.formula(alt.strip("$"), "alt")
            elif self.images:
                sets = [s.split() for s in a.get("srcset", a.get("data-srcset", "")).split(",") if s.split()]
                largest = [max(sets, key=lambda s: float(s[1][:-1]) if len(s) > 1 and s[1][:-1].replace(".", "", 1).isdigit() else 0)[0]] if sets else []
                usable = [u for u in (a.get("src", ""), a.get("data-src", ""), a.get("data-original", ""), *largest) if u and not u.startswith("data:")]
                if usable:
                    self.flush()
                    self.out.append(("image", None, urljoin(self.base, usable[0]) if self.base else usable[0]))
        elif tag in _BLOCKS:
            self.flush()

    def handle_endtag(self, tag: str) -> None:
        if self.tex is not None and tag in ("script", "annotation"):
            found, self.tex = "".join(self.tex), None
            if self.mathml is not None:
                self.noted = found
            else:
                self.formula(found, "script")
            return
        if self.off:
            if tag == self.off[-1]:
                self.off.pop()
            elif tag in self.off:
                del self.off[self.off.index(tag) :]
            return
        if tag == "math" and self.mathml is not None:
            inside, self.mathml = "".join(self.mathml), None
            self.formula(self.noted if self.noted is not None else inside, "mathml")
        elif tag in _BLOCKS:
            self.flush()

    def handle_data(self, data: str) -> None:
        if self.tex is not None:
            self.tex.append(data)
        elif self.off:
            return
        elif self.mathml is not None:
            self.mathml.append(data)
        else:
            self.buffer.append(data)


def walk(html: str | None, base: str = "", math: bool = True, images: bool = True, headings: bool = True, sources: tuple[str, ...] = MATH_SOURCES) -> list[tuple[str, str | None, str | None]]:
    """Segments (kind, text, image url) of one page; none for null and empty pages. Broken markup is no error."""
    w = _Walk(base, math, images, headings, sources)
    w.feed(html or "")
    w.close()
    w.flush()
    return w.out


def interleaved(pages: DataFrame, id_col: str = "page_id", math: bool = True, images: bool = True, headings: bool = True, sources: tuple[str, ...] = MATH_SOURCES) -> DataFrame:
    """(page_id, url, segments): text, formulas and images at their places. One crossing to Python, map-only."""
    ensure_importable(pages.sparkSession)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            found = [[{"pos": k, "kind": a, "text": b, "image_url": c} for k, (a, b, c) in enumerate(walk(h, u or "", math, images, headings, sources))] for h, u in zip(frame["html"], frame["url"], strict=True)]
            yield pd.DataFrame({id_col: frame[id_col], "url": frame["url"], "segments": found})

    kind = pages.schema[id_col].dataType.simpleString()
    return pages.select(id_col, "url", "html").mapInPandas(run, f"{id_col} {kind}, url string, segments {SEGMENTS}")


def with_text(pages: DataFrame, html: str = "html") -> DataFrame:
    """pages with text in place of html, by the same walk without formulas and images; all other columns stay, map-only."""
    ensure_importable(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index(html)
            texts = ["\n".join(t for k, t, _ in walk(h.as_py(), math=False, images=False) if k == "text") for h in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*(c for k, c in enumerate(batch.columns) if k != at), pa.array(texts, pa.string())], names=[*(n for n in batch.schema.names if n != html), "text"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pages.schema if f.name != html)
    return pages.mapInArrow(run, f"{fields}, text string")


def plain_text(pages: DataFrame, id_col: str = "page_id", min_chars: int = 0, headings: bool = True) -> DataFrame:
    """(page_id, url, text): the same walk without formulas and images; shorter texts go."""
    text = F.array_join(F.transform(F.filter("segments", lambda s: s["kind"] == "text"), lambda s: s["text"]), "\n")
    return interleaved(pages, id_col, math=False, images=False, headings=headings).select(id_col, "url", text.alias("text")).where(F.length("text") >= min_chars)


_ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&"))


def article_text(html: Column, skip_heading: bool = False) -> Column:
    """The text of a well-formed article element, by string functions alone."""
    text = F.regexp_extract(html, r"(?s)<article>(.*?)(?:</article>|\z)", 1)
    if skip_heading:
        text = F.regexp_replace(text, r"(?s)<h1>.*?</h1>", " ")
    text = F.regexp_replace(F.regexp_replace(text, r"(?s)<!--.*?-->", " "), r"<[^>]*>", " ")
    for a, b in _ENTITIES:
        text = F.replace(text, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(text, "[ \t\r\n]+", " "))


def article_text_sql(html: str, skip_heading: bool = False) -> str:
    x = rf"regexp_extract({html}, '(?s)<article>(.*?)(?:</article>|\z)', 1)"
    if skip_heading:
        x = f"regexp_replace({x}, '(?s)<h1>.*?</h1>', ' ', 'g')"
    x = f"regexp_replace(regexp_replace({x}, '(?s)<!--.*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g')"
    for a, b in _ENTITIES:
        b = b.replace("'", "''")
        x = f"replace({x}, '{a}', '{b}')"
    return f"trim(regexp_replace({x}, '[ \\t\\r\\n]+', ' ', 'g'))"


def plain_text_sql(pages: DataFrame) -> DataFrame:
    """(page_id, text) without leaving the JVM, for pages with an article element."""
    return pages.select("page_id", article_text(F.col("html")).alias("text"))


def link_positions(pages: DataFrame) -> DataFrame:
    """(page_id, pos, link): links in page order, made absolute with the page's scheme and host."""
    site, scheme, href = F.regexp_extract("url", "^https?://[^/]*", 0), F.regexp_extract("url", "^https?:", 0), F.col("href")
    full = F.when(href.startswith("http"), href).when(href.startswith("//"), F.concat(scheme, href)).when(href.startswith("/"), F.concat(site, href)).otherwise(F.concat(site, F.lit("/"), href))
    return pages.select("page_id", "url", F.posexplode(F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), F.lit(1))).alias("pos", "href")).select("page_id", F.col("pos").cast("long").alias("pos"), full.alias("link"))


def strip_image_links(text: Column) -> Column:
    """Image links away from negatives, so that both classes have one format."""
    return F.regexp_replace(text, r"!\[[^\]]*\]\([^)]*\)|https?://[^ \n]+\.(?:png|jpe?g|gif|svg|webp)", "")
