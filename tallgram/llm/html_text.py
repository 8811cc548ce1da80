"""Main text of web pages by line-block distribution (operator 1).

Markup is cut into lines at block-level tags; scripts, styles, forms and the like
are left out. A boundary of a container (division, section, list of links, footer
...) stands for ``WINDOW`` empty lines, as in indented source. Over the lines a
window slides and sums text lengths, each line less twice its link text. The sum
surges where running text begins and dives to nothing where it ends: between are
the page's blocks. The block with most text is the body, and the blocks whose text
is at least ``SHARE`` of it belong to it; what lies between the first and the last
is kept, but for lines of links.

Element names, roles and class names decide only what the sums leave open. If the
body lies in a marked article, the article's ends replace the ends of the blocks, so
short first and last paragraphs stay. Blocks in menus, side bars, notices, adverts
or reader comments go, unless the body itself lies there. Where no block reaches
``DECISIVE`` characters, the sums say little, and a marked article wins over them.

Defined results: null and empty html give an empty text; html without tags is one
line of text; an unclosed tag ends with its page; repeated pages are repeated.
"""

from __future__ import annotations

import html as markup
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from tallgram.llm.common import blocks

#: Lines that a window sums, and the sum at which running text begins.
WINDOW, SURGE = 3, 80
#: Share of the body's text that another block needs, and the text from which the sums alone decide.
SHARE, DECISIVE = 0.15, 500

# fixed values: elements and names by the HTML standard and common usage
RAW = {"script", "style", "noscript", "template", "textarea", "iframe", "title", "svg", "math", "object", "select", "button", "option", "xmp", "noembed", "noframes", "canvas", "audio", "video", "datalist"}
FORMS = {"form", "fieldset", "dialog"}
CHROME = {"nav", "footer", "aside", "menu", "search"}
CONTAINERS = set("address article aside body blockquote center details dir div dl figure footer header hgroup main menu nav ol search section table ul".split())
BLOCK = set("address article aside blockquote body br center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup p pre search section summary table tbody td tfoot th thead tr ul".split())
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
CHROME_NAMES = set(
    "nav navbar navigation menu menubar footer sidebar side aside ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices notification popup modal overlay newsletter subscribe subscription signup login register share sharing social related recommended recommendations breadcrumb breadcrumbs pagination pager comment comments commentlist respond reply replies disqus widget toolbar masthead topbar skip search copyright legal disclaimer".split()
)
HEADER_NAMES = {"header", "head"}
ARTICLE_NAMES = set("article content post entry story main maincontent articlebody postbody hentry".split())
CHROME_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alertdialog", "alert", "menu", "menubar", "form", "note"}

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role|hidden|style|itemprop)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_NAME = re.compile(r"[A-Za-z][a-z]*|[A-Z]+")


def _kind(tag: str, attributes: str, inside: bool) -> str:
    """'chrome', 'article' or '' for an opening tag; inside: the page's article is open."""
    if tag in CHROME or (tag == "header" and not inside):
        return "chrome"
    names: set[str] = set()
    if attributes and "=" in attributes or "hidden" in attributes:
        for name, a, b, c in _ATTRIBUTE.findall(attributes):
            value, name = a or b or c, name.lower()
            if name == "hidden" and tag not in ("body", "html"):
                return "chrome"
            if name == "style":
                if re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
                    return "chrome"
            elif name == "role":
                if value.lower() in CHROME_ROLES:
                    return "chrome"
                if value.lower() in ("main", "article"):
                    return "article"
            elif name == "itemprop":
                if value.lower() == "articlebody":
                    return "article"
            else:
                names.update(x.lower() for x in _NAME.findall(value))
    if tag in ("article", "main"):
        return "chrome" if names & {"comment", "comments", "reply"} else "article"
    if tag in ("body", "html"):
        return ""
    if names & CHROME_NAMES:
        return "chrome"
    if names & HEADER_NAMES:
        return "" if inside or names & ARTICLE_NAMES else "chrome"
    if names & ARTICLE_NAMES and tag in ("div", "section", "td"):
        return "article"
    return ""


class Lines:
    """Lines of a page: text, length, link length, and the innermost mark (an element that names itself; 0: none)."""

    def __init__(self, page: str):
        self.text: list[str] = []
        self.size: list[int] = []
        self.link: list[int] = []
        self.mark: list[int] = []
        self.parents: dict[int, int] = {}
        self.kinds: dict[int, str] = {0: ""}
        self._buffer: list[str] = []
        self._links = 0
        self._read(page)

    def _end_line(self, mark: int, empty: int = 0) -> None:
        """End the current line if it has text, and put empty lines after it."""
        text = " ".join("".join(self._buffer).split())
        if text:
            self.text.append(text)
            self.size.append(len(text))
            self.link.append(self._links)
            self.mark.append(mark)
        self._buffer, self._links = [], 0
        for _ in range(empty):
            self.text.append("")
            self.size.append(0)
            self.link.append(0)
            self.mark.append(mark)

    def _read(self, page: str) -> None:
        at, n = 0, len(page)
        lowered = None
        open_marks: list[tuple[str, int, int]] = []  # tag, id, depth of the same tag
        depth: dict[str, int] = {}
        links = serial = articles = 0
        while at < n:
            m = _TAG.search(page, at)
            piece = page[at : m.start()] if m else page[at:]
            if piece:
                piece = markup.unescape(piece)
                self._buffer.append(piece)
                if links:
                    self._links += len(piece)
            if not m:
                break
            at = m.end()
            tag = (m[2] or "").lower()
            if not tag:
                continue
            here = open_marks[-1][1] if open_marks else 0
            if m[1]:
                if tag == "a":
                    links = max(0, links - 1)
                if tag in BLOCK:
                    self._end_line(here, WINDOW if tag in CONTAINERS else 0)
                if tag in depth:
                    depth[tag] = max(0, depth[tag] - 1)
                    k = next((k for k in range(len(open_marks) - 1, -1, -1) if open_marks[k][0] == tag and depth[tag] < open_marks[k][2]), -1)
                    if k >= 0:  # marks inside that were never closed end with it
                        articles -= sum(self.kinds[o[1]] == "article" for o in open_marks[k:])
                        del open_marks[k:]
                continue
            if tag in RAW:
                if m[3].endswith("/") and tag in ("svg", "math"):
                    continue
                lowered = page.lower() if lowered is None else lowered
                end = lowered.find(f"</{tag}", at)
                at = n if end < 0 else (page.find(">", end) + 1 or n)
                continue
            if tag in VOID:
                if tag in BLOCK:
                    self._end_line(here)
                continue
            if tag in FORMS:
                self._end_line(here, WINDOW)
                at = self._skip(page, tag, at)
                continue
            if tag in BLOCK:
                self._end_line(here, WINDOW if tag in CONTAINERS else 0)
            if tag == "a":
                links += 1
            depth[tag] = depth.get(tag, 0) + 1
            kind = _kind(tag, m[3], articles > 0)
            if kind:
                serial += 1
                self.parents[serial], self.kinds[serial] = here, kind
                open_marks.append((tag, serial, depth[tag]))
                articles += kind == "article"
        self._end_line(open_marks[-1][1] if open_marks else 0)

    @staticmethod
    def _skip(page: str, tag: str, at: int) -> int:
        """The place after the element's end; nested elements of its name are passed over."""
        inner = re.compile(rf"<!--.*?(?:-->|\Z)|<script\b.*?(?:</script|\Z)|<(/?){re.escape(tag)}(?=[\s/>])(?:[^>\"']|\"[^\"]*\"|'[^']*')*>", re.S | re.I)
        level = 1
        for m in inner.finditer(page, at):
            if m[1] is None:
                continue
            level += -1 if m[1] else 1
            if not level:
                return m.end()
        return len(page)

    def around(self, mark: int) -> list[int]:
        """The mark and the marks around it, inner ones first."""
        out = []
        while mark:
            out.append(mark)
            mark = self.parents[mark]
        return out


def surge_and_dive(sizes: list[int], links: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int, int]]:
    """(first line, line after the last, text length) of each run of lines between a surge and a dive."""
    n = len(sizes)
    value = [max(0, s - 2 * k) for s, k in zip(sizes, links, strict=True)]
    total = [0]
    for v in value:
        total.append(total[-1] + v)
    sums = [total[min(n, i + window)] - total[i] for i in range(n)]
    runs, i = [], 0
    while i < n:
        if sums[i] < surge or not value[i]:
            i += 1
            continue
        first = i
        while first and sizes[first - 1] and value[first - 1]:  # a short title above
            first -= 1
        j = i
        while j < n and sums[j] > 0:
            j += 1
        runs.append((first, j, total[j] - total[first]))
        i = j + 1
    return runs


def _widest_article(lines: Lines, filled: list[int]) -> int:
    """The article mark with most text that no chrome lies around (0: none); of equals the outermost."""
    total: dict[int, int] = {}
    for i in filled:
        for k in lines.around(lines.mark[i]):
            total[k] = total.get(k, 0) + lines.size[i]
    total = {k: v for k, v in total.items() if lines.kinds[k] == "article" and not any(lines.kinds[o] == "chrome" for o in lines.around(k))}
    return min(total, key=lambda k: (-total[k], k)) if total else 0


def main_text(page: str | None, window: int = WINDOW, surge: int = SURGE) -> tuple[str, int, int]:
    """Text of the page's article, and its surge and dive lines (-1, -1 without text)."""
    if not page:
        return "", -1, -1
    lines = Lines(page)
    filled = [i for i, t in enumerate(lines.text) if t]
    if not filled:
        return "", -1, -1
    running = lambda i: lines.size[i] > 2 * lines.link[i]
    runs = surge_and_dive(lines.size, lines.link, window, surge)
    body = max(runs, key=lambda r: (r[2], -r[0]), default=None)
    if body and body[2] >= DECISIVE:
        heaviest = max(range(body[0], body[1]), key=lambda i: lines.size[i])
        around = lines.around(lines.mark[heaviest])
        article = next((k for k in reversed(around) if lines.kinds[k] == "article"), 0)
    else:  # the sums say little: an article mark decides
        article = _widest_article(lines, filled)
        around = lines.around(article)
    own = set(around)
    # chrome that doesn't hold the body itself
    chrome = lambda i: any(lines.kinds[k] == "chrome" and k not in own for k in lines.around(lines.mark[i]))
    if article:
        kept = [i for i in filled if article in lines.around(lines.mark[i]) and not chrome(i)]
    elif body:
        strong = [r for r in runs if r[2] >= SHARE * body[2] and not chrome(max(range(r[0], r[1]), key=lambda i: lines.size[i]))] or [body]
        kept = [i for i in range(strong[0][0], strong[-1][1]) if lines.text[i] and running(i) and not chrome(i)]
    else:  # nothing surges: a short page, all of which is kept but lists of links
        kept = [i for i in filled if running(i) and not chrome(i)]
    return " ".join(lines.text[i] for i in kept), (kept or [-1])[0], (kept or [-2])[-1] + 1


def extract_main_text(pages: DataFrame, window: int = WINDOW, surge: int = SURGE) -> DataFrame:
    """page_id, url, text, n_chars, surge_line, dive_line of every page (page_id, url, html). Narrow: no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "html"):
            found = [main_text(p, window, surge) for p in batch.column("html").to_pylist()]
            texts, first, last = zip(*found, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64()), pa.array(first, pa.int32()), pa.array(last, pa.int32())], names=["page_id", "url", "text", "n_chars", "surge_line", "dive_line"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long, surge_line int, dive_line int")
