"""Main text of web pages by the distribution of text over lines.

Markup is stripped into lines, one for each block of the page; lines of menus, adverts, footers and comments stay in
their places like all others. What a line counts is its characters outside links, and more or less of them by where it
stands (see weights): that is the only say markup has. Counts are summed over windows of lines. Where sums leave zero is
a surge, where they come back to zero a dive, and the lines between are a zone. A zone is text if it rises high enough
against the highest sum of the page; all lines of such zones are kept, all others go.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import ensure_importable

#: Lines of a window; characters that a zone must reach in one window, and the share of the page's highest window. A zone
#: of ordinary lines is text if it reaches the lesser of the two, one of doubtful lines must reach both.
WINDOW, SURGE, SHARE = 3, 86, 0.25
#: What a character counts: in an article element, in an ordinary place, and in a place whose name or kind says boilerplate.
ARTICLE, PLAIN, DOUBTFUL = 64.0, 1.0, 1 / 64
#: The part of a page's ordinary text that a container must hold for the text outside it to count half.
HOME = 2 / 3
#: A quoted value, of any length, begins after an equals sign only; a quote that never ends is a character like others.
_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:=\s*(?:"[^"]*"|'[^']*')|[^>])*+)(?:>|\Z)""", re.S)
_ATTR = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title iframe noframes xmp noembed".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead tr ul".split()
)
CONTAINER = frozenset("article aside body dd details dialog div dl fieldset footer form header li main menu nav ol section table tbody td tr ul blockquote figure".split())
DOUBTED = frozenset("aside dialog footer form head menu nav search".split())
#: Elements whose content is no text of the page: controls, drawings, media, what is shown only without scripts.
UNSEEN = frozenset("audio button canvas datalist embed label map noscript object select svg template video".split())
#: Elements that a start tag ends if they are still open.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
CLOSES_P = BLOCK - {"body", "html", "head", "option", "optgroup"}
_HINT = frozenset(
    "ad ads adbox adsense advert adverts advertisement advertising alert banner breadcrumb breadcrumbs byline-share colophon comment comments consent cookie cookies copyright discussion disqus footer gdpr header infobar login masthead menu modal nav navbar navigation newsletter notice notices notification overlay pager pagination paywall popup popular promo promotion promoted recommendations recommended related replies reply respond search share sharing sidebar signin signup skip tags tagcloud disclaimer social sponsor sponsored subscribe subscription teaser toolbar topbar trending widget widgets side sidenav topnav subnav sitenav mainnav mainmenu commentlist commentthread usercomments adslot adunit adcontainer cookiebar cookiebanner".split()
)
_HINT_ROLES = frozenset("alert alertdialog banner complementary contentinfo dialog form menu menubar navigation search toolbar".split())
_MAIN = re.compile(r"(?:^|\s)(?:article|post|entry|story|main|page)[-_]?(?:body|content|text)(?:$|\s)", re.I)
_LETTER = re.compile(r"\w")
_NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


def _attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): unescape(m[2] or m[3] or m[4] or "") for m in _ATTR.finditer(raw)} if "=" in raw or "hidden" in raw else {}


def _hinted(names: str) -> bool:
    """Whether a class or id says boilerplate: as its first or last word, but not as what a layout has or lacks."""
    for name in names.split():
        words = [w.lower() for w in _NAME.findall(name)]
        if words and not {"has", "no", "with", "without", "layout", "wrapper"} & set(words) and (words[0] in _HINT or words[-1] in _HINT):
            return True
    return False


class _Lines:
    """Lines of a page: text, characters outside links, container, and whether the place is doubtful."""

    def __init__(self) -> None:
        self.lines: list[tuple[str, int, int, bool]] = []
        self.stack: list[tuple[str, bool, int, bool]] = [("#", False, 0, False)]  # name, doubtful, container, silent
        self.parents = [0]
        self.main: set[int] = set()
        self.text: list[str] = []
        self.plain = 0
        self.in_link = False

    def flush(self) -> None:
        if self.text:
            line = " ".join("".join(self.text).split())
            if line:
                self.lines.append((line, min(len(line), self.plain), self.stack[-1][2], self.stack[-1][1]))
            self.text, self.plain = [], 0

    def pop_to(self, at: int) -> None:
        del self.stack[at:]

    def start(self, name: str, raw: str) -> None:
        if name in ENDS:
            for at in range(len(self.stack) - 1, 0, -1):
                if self.stack[at][0] in ENDS[name]:
                    self.pop_to(at)
                    break
                if self.stack[at][0] in CONTAINER and self.stack[at][0] not in ("tbody",):
                    break
        if name in CLOSES_P:
            for at in range(len(self.stack) - 1, 0, -1):
                if self.stack[at][0] == "p":
                    self.pop_to(at)
                    break
                if self.stack[at][0] in BLOCK:
                    break
        attrs = _attributes(raw)
        _, doubtful, container, silent = self.stack[-1]
        hint = unseen = False
        own = name in ("article", "main") or attrs.get("role", "").lower() in ("main", "article") or attrs.get("itemprop", "") == "articleBody"
        if name not in ("html", "body"):
            labels = f"{attrs.get('class', '')} {attrs.get('id', '')}"
            hint = attrs.get("role", "").lower() in _HINT_ROLES
            unseen = name in UNSEEN or "hidden" in attrs or attrs.get("aria-hidden", "").lower() == "true" or "display:none" in attrs.get("style", "").replace(" ", "").lower()
            if labels != " ":
                hint = hint or _hinted(labels)
                own = own or bool(_MAIN.search(labels))
        if own and not hint and doubtful:  # an article can't lie in a menu or page header: that was left open
            for at in range(1, len(self.stack)):
                if self.stack[at][1]:
                    if self.stack[at][0] in ("nav", "header", "menu", "head"):
                        self.pop_to(at)
                        _, doubtful, container, silent = self.stack[-1]
                    elif self.stack[at][0] == "form":  # one form around the whole page
                        self.stack[at:] = [(n, False, c, x) for n, _, c, x in self.stack[at:]]
                        doubtful = False
                    break
        if name == "header":
            hint = hint or not any(c in self.main for c in self._chain(container))
        if name in VOID:
            return
        # A doubtful place inside a line can't be a line of its own: its text is left out, as is what no reader sees.
        silent = silent or unseen or hint and name not in BLOCK
        doubtful = doubtful or hint or name in DOUBTED
        if name in CONTAINER:
            self.parents.append(container)
            container = len(self.parents) - 1
            if own and not doubtful:
                self.main.add(container)
        self.stack.append((name, doubtful, container, silent))

    def _chain(self, container: int) -> Iterator[int]:
        while container:
            yield container
            container = self.parents[container]

    def end(self, name: str) -> None:
        for at in range(len(self.stack) - 1, 0, -1):
            if self.stack[at][0] == name:
                self.pop_to(at)
                return
            if name not in CONTAINER and self.stack[at][0] in CONTAINER or name in CONTAINER and name not in ("article", "main", "body", "html") and self.stack[at][0] in ("article", "main", "body"):
                return  # nothing of that name is open here

    def feed(self, html: str) -> None:
        at, size = 0, len(html)
        lower = None
        while at < size:
            m = _TAG.search(html, at)
            stop = m.start() if m else size
            if stop > at and not self.stack[-1][3]:
                piece = unescape(html[at:stop])
                self.text.append(piece)
                if not self.in_link and _LETTER.search(piece):  # what parts links counts nothing
                    self.plain += len(piece)
            if not m:
                break
            at = m.end()
            if m[2] is None:
                continue
            name = m[2].lower()
            if name in BLOCK:
                self.flush()
            elif name == "br":
                self.text.append(" ")
            if m[1]:
                if name == "a":
                    self.in_link = False
                self.end(name)
                continue
            if name == "a":
                self.in_link = True
            if name in RAW:
                lower = lower or html.lower()
                stop = lower.find(f"</{name}", at) if len(lower) == size else html.find(f"</{name}", at)
                if stop < 0:
                    if name in ("script", "style"):
                        break
                    continue
                at = html.find(">", stop) + 1 or size
                continue
            self.start(name, m[3])
            if name in ("td", "th"):
                self.text.append(" ")
        self.flush()


def zones(lengths: list[float], window: int = WINDOW, least: float = 0.0) -> list[tuple[int, int]]:
    """Ranges of lines from a surge of the window sums out of zero to the dive back to it, if a window between reaches `least`.

    Lines that count nothing end a zone only if they fill a window; a zone begins and ends with lines that count.
    """
    out: list[tuple[int, int]] = []
    held = [i for i, n in enumerate(lengths) if n > 0]
    sums = [0.0]
    for n in lengths:
        sums.append(sums[-1] + n)
    start = 0
    for k, i in enumerate(held):
        if k + 1 == len(held) or held[k + 1] - i > window:  # a whole window of nothing follows
            first, stop = held[start], i + 1
            if max(sums[min(stop, j + window)] - sums[j] for j in range(first, max(first + 1, stop - window + 1))) >= least:
                out.append((first, stop))
            start = k + 1
    return out


def _home(page: _Lines) -> int:
    """The innermost container that holds most of the ordinary text (HOME of it); 0, the page, if only that does."""
    inner: dict[int, int] = {}
    total = 0
    for _, n, c, doubtful in page.lines:
        if n and not doubtful:
            total += n
            for x in page._chain(c):
                inner[x] = inner.get(x, 0) + n
    return max((x for x, n in inner.items() if n >= HOME * total), default=0)  # containers are numbered as they open


def kept_lines(page: _Lines, window: int = WINDOW) -> list[int]:
    """Indices of the lines of all zones that are text.

    Lines of one kind of place make one sequence: what lies in the article (or the container of most text), what else is
    ordinary, by stretches, and doubtful lines, by stretches. So an advert parts no article, and joins none.
    """
    best = 0
    if page.main:
        inner: dict[int, int] = {}
        for _, n, c, doubtful in page.lines:
            if not doubtful and (home := next((x for x in page._chain(c) if x in page.main), 0)):
                inner[home] = inner.get(home, 0) + n + 1
        best = max(inner, key=lambda x: (inner[x], -x), default=0)
    article = bool(best)
    best = best or _home(page)
    own: list[int] = []
    others: list[tuple[bool, list[int]]] = []
    before = None
    for i, (_, _, c, doubtful) in enumerate(page.lines):
        inside = not doubtful and (not best or best in page._chain(c))
        if inside:
            own.append(i)
        elif before == (False, doubtful):
            others[-1][1].append(i)
        else:
            others.append((doubtful, [i]))
        before = (inside, doubtful)

    def count(i: int, inside: bool) -> float:
        line, n, _, doubtful = page.lines[i]
        if inside:  # whole paragraphs that are links belong to an article
            return ARTICLE * len(line) if article else PLAIN * n
        return DOUBTFUL * n if doubtful else PLAIN * n / (1 if article or not best else 2)

    groups = [(False, own, [count(i, True) for i in own]), *((d, g, [count(i, False) for i in g]) for d, g in others)]
    highest = max((sum(m[j : j + window]) for _, _, m in groups for j in range(len(m))), default=0.0)
    out = []
    for doubtful, group, lengths in groups:
        least = (max if doubtful else min)(SURGE, SHARE * highest) if group is own or doubtful else max(1.0, SHARE * highest)
        out += [group[j] for a, b in zones(lengths, window, least) for j in range(a, b)]
    return sorted(out)


def main_text(html: str | None, window: int = WINDOW) -> str:
    """The kept lines, joined by an empty line; empty for null, empty or textless pages."""
    if not html:
        return ""
    page = _Lines()
    page.feed(html)
    return "\n\n".join(page.lines[i][0] for i in kept_lines(page, window))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars), one row for each row of pages, map-only.

    Null, empty and broken html is no error, its text is what can be read of it. Ids pass through as they are, null or
    repeated; columns other than the three named are not read.
    """
    ensure_importable(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(x.as_py()) for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    kind = pages.schema[id_col].dataType.simpleString()
    return pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html")).mapInArrow(run, f"page_id {kind}, url string, text string, n_chars long")
