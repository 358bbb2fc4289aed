"""Main text of web pages by line-block distribution.

The page is stripped to block lines (one for each block element). Text lengths are summed over windows of lines; where
the sum surges the article begins, where it dives it ends, and the heaviest such run is the region. Elements that declare
themselves as boilerplate (navigation, footer, aside, form, advert, notice, comments) never enter the distribution, nor do lines
outside a declared article or main. Every line between surge and dive stays. Short first and last lines join them as far
as the article or main around the region reaches, or else the innermost container that holds all of the region; there, lines that
are links only stay out. If that container is the page itself, all runs between surge and dive are kept.

Defined results: null or empty html gives the empty text; a page without any text line gives the empty text; broken
markup (unclosed or stray tags, open quotes) is read to its end; repeated rows give equal results and every page gives one
row. A page is one task's work and takes time and memory in proportion to its length, however deep its elements nest.
"""

from __future__ import annotations

import html as entities
import re

from pyspark.sql import DataFrame

from . import common

# Element names by role.
RAW = ("script", "style", "noscript", "template", "iframe", "textarea", "head", "object", "canvas")
DROPPED = {"nav", "aside", "footer", "form", "menu", "dialog", "button", "select", "fieldset", "input", "option"}
CONTAINERS = {"html", "body", "main", "article", "section", "div", "header", "ul", "ol", "dl", "table", "tbody", "thead", "tr", "td", "th", "blockquote", "figure", "figcaption", "details", "center"} | DROPPED
LINES = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "dt", "dd", "pre", "hr", "address", "caption", "summary", "title", "legend"}
VOID = {"br", "hr", "img", "input", "meta", "link", "area", "base", "col", "embed", "source", "track", "wbr"}
# Words of class, id and role that mark boilerplate.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notification popup modal overlay newsletter subscribe subscription signup signin login "
    "sidebar sidebars side rail widget widgets menu menus nav navbar navigation breadcrumb breadcrumbs pagination pager footer masthead header topbar toolbar share sharing social related recommended recommendations "
    "comment comments commentlist disqus respond reply replies discussion hidden search skip complementary contentinfo alert toc copyright legal disclaimer".split()
)
HEADINGS = {"h1", "h2", "h3"}

_OPEN = re.compile(r"<(?:(/?)([A-Za-z][A-Za-z0-9:-]*)|!--|!\[CDATA\[|[!?])")
_STOP = re.compile(r"""[>"']""")
_DRAWN = re.compile(r"<text\b[^>]*>([^<]*(?:<(?!/text)[^<]*)*)</text", re.I)
_TAG = re.compile(r"<[^>]*>")
_MARKED = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""(?i)(?:^|\s)hidden(?=\s|=|/|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none""")
_WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


def _boilerplate(tag: str, attrs: str, heads: bool) -> bool:
    if tag in DROPPED or (tag == "header" and not heads):
        return True
    if not attrs:
        return False
    if _HIDDEN.search(attrs):
        return True
    if tag in ("html", "body", "main") or (tag == "article" and not heads):  # an article in an article may be a comment
        return False
    for m in _MARKED.finditer(attrs):
        value = m.group(2) or m.group(3) or m.group(4) or ""
        if any(w.lower() in MARKS for w in _WORDS.findall(value)):
            return True
    return False


class Reader:
    """A page with searches that remember what does not come again, so that each stretch is read a bounded number of times."""

    def __init__(self, page: str) -> None:
        self.page, self.gone = page, set()

    def find(self, text: str, at: int) -> int:
        """Where text comes next, or -1."""
        if text in self.gone:
            return -1
        found = self.page.find(text, at)
        if found < 0:
            self.gone.add(text)
        return found

    def after(self, tag: str, at: int) -> int:
        """The end of the next closing tag of that name, or -1."""
        if "/" + tag in self.gone:
            return -1
        m = re.compile(rf"</{tag}\s*>" + (r"|(?=<body\b)" if tag == "head" else ""), re.I).search(self.page, at)
        if not m:
            self.gone.add("/" + tag)
        return m.end() if m else -1

    def tag_end(self, at: int) -> int:
        """Where the tag whose attributes begin at `at` closes; quoted values may hold any sign. -1 if it does not close."""
        first = self.find(">", at)
        while first >= 0 and (m := _STOP.search(self.page, at)):
            if m.group() == ">":
                return m.start()
            over = self.find(m.group(), m.end()) if self.page[m.start() - 1] in "= \t\r\n" else -1
            at = over + 1 if over >= 0 else m.end()
        return first


class Lines:
    """Block lines of a page in order, and for each container the lines it holds."""

    def __init__(self) -> None:
        self.text: list[str] = []
        self.links: list[int] = []  # of it in links
        self.inside: list[int] = []  # innermost container
        self.parent, self.first, self.stop = [-1], [0], [0]  # of each container; 0 is the page
        self.article = [-1]  # innermost article or main at or above it


def block_lines(page: str, lenient: bool = False) -> Lines:
    """lenient: class words of a container do not count for an article or main in it."""
    out, reader = Lines(), Reader(page)
    stack: list[tuple[str, int, bool]] = []  # name, id, whether it is dropped
    opened: dict[str, int] = {}
    hidden: list[int] = []  # drops outside each open article or main that are set aside
    parts: list[str] = []
    links = dropped = heading = 0
    link = False

    def flush() -> None:
        nonlocal links
        text = " ".join("".join(parts).split())
        if text:
            out.text.append(text)
            out.links.append(links)
            out.inside.append(stack[-1][1] if stack else 0)
        parts.clear()
        links = 0

    def close(to: int) -> None:
        nonlocal dropped
        while len(stack) > to:
            name, number, drop = stack.pop()
            out.stop[number] = len(out.text)
            opened[name] -= 1
            dropped -= drop
            if lenient and name in ("article", "main"):
                dropped += hidden.pop()

    pos, end = 0, len(page)
    while pos < end:
        m = _OPEN.search(page, pos)
        stop = m.start() if m else end
        if stop > pos and not dropped and (not opened.get("header") or heading):
            piece = entities.unescape(page[pos:stop])
            parts.append(piece)
            if link:
                links += len(piece.strip())
        if not m:
            break
        tag = (m.group(2) or "").lower()
        if not tag:
            closer = {"<!--": "-->", "<![CDATA[": "]]>"}.get(m.group(), ">")
            over = reader.find(closer, m.end() if closer != "-->" else m.start() + 2)
            pos = over + len(closer) if over >= 0 else (end if closer == "-->" else m.end())
            continue
        over = reader.tag_end(m.end())
        if over < 0:  # a sign that begins no tag
            parts.append(page[m.start() : m.end()] if not dropped else "")
            pos = m.end()
            continue
        closing, attrs, pos = m.group(1), page[m.end() : over], over + 1
        selfclosed = attrs.rstrip().endswith("/")
        if tag == "svg" and not closing and not selfclosed:
            after = reader.after("svg", pos)
            if not dropped and after >= 0:
                parts += [f" {entities.unescape(_TAG.sub('', t.group(1)))} " for t in _DRAWN.finditer(page, pos, after)]
            pos = after if after >= 0 else pos
        elif not closing and tag in RAW and not selfclosed:
            after = reader.after(tag, pos)
            pos = after if after >= 0 else (end if tag != "head" else pos)
        elif tag == "a":
            link = not closing
        elif tag == "br":
            parts.append(" ")
        elif tag in CONTAINERS:
            flush()
            if closing:
                if opened.get(tag):
                    close(next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag))
            elif tag not in VOID and not selfclosed:
                within = bool(opened.get("article") or opened.get("main"))
                drop = _boilerplate(tag, attrs, within)
                above, number = (stack[-1][1] if stack else 0), len(out.parent)
                out.parent.append(above)
                out.first.append(len(out.text))
                out.stop.append(-1)
                out.article.append(number if tag in ("article", "main") else out.article[above])
                if lenient and tag in ("article", "main"):
                    hidden.append(dropped)
                    dropped = 0
                stack.append((tag, number, drop))
                opened[tag] = opened.get(tag, 0) + 1
                dropped += drop
        elif tag in LINES:
            flush()
            if tag in HEADINGS:
                heading = 0 if closing else 1
            elif tag in ("p", "li", "dd", "dt", "pre"):
                heading = 0
                if not closing and attrs and _boilerplate(tag, attrs, True):  # a marked paragraph ends with the next block
                    after = reader.after(tag, pos)
                    pos = after if after >= 0 else pos
    flush()
    close(0)
    out.stop[0] = len(out.text)
    return out


def distribution(lengths: list[int], window: int) -> list[int]:
    """Sum of the text lengths of each line and the window-1 that follow."""
    return [sum(lengths[i : i + window]) for i in range(len(lengths))]


def region(lengths: list[int], window: int = 3, surge: int = 86) -> tuple[int, int]:
    """First and last line of the heaviest run between a surge point and the dive point after it; (0, -1) if none."""
    return max(runs(lengths, window, surge), key=lambda r: sum(lengths[r[0] : r[1] + 1]), default=(0, -1))


def runs(lengths: list[int], window: int = 3, surge: int = 86) -> list[tuple[int, int]]:
    """First and last line of each run between a surge point and the dive point after it."""
    sums = distribution(lengths, window)
    if not sums or not any(lengths):
        return []
    level = min(surge, max(sums))
    found, i = [], 0
    while i < len(sums):
        if sums[i] < level:
            i += 1
            continue
        first = i
        while i < len(sums) and sums[i] >= level:
            i += 1
        last = i - 1
        if i < len(sums):  # the window still reaches lines after the last start that holds enough
            last = max((j for j in range(last, min(last + window, len(lengths))) if lengths[j] * window >= level), default=last)
        while first < last and lengths[first] * window * 2 < level and lengths[first] <= lengths[first + 1]:
            first += 1
        found.append((first, last))
    return found


def main_text(page: str | None, window: int = 3, surge: int = 86, link_share: float = 0.6) -> str:
    if not page:
        return ""
    lines = block_lines(page)
    if all(lines.article[c] < 0 for c in lines.inside) and re.search(r"<(?:article|main)\b", page, re.I):
        again = block_lines(page, lenient=True)  # an article inside a container whose class reads like boilerplate
        lines = again if any(again.article[c] >= 0 for c in again.inside) else lines
    declared = [lines.article[c] >= 0 for c in lines.inside]
    rows = [i for i, d in enumerate(declared) if d] or range(len(declared))
    lengths = [0 if lines.links[i] >= link_share * len(lines.text[i]) else len(lines.text[i]) for i in rows]
    first, last = region(lengths, window, surge)
    if last < first:
        return ""
    first, last = _solid(lengths, first, last)
    low, high = rows[first], rows[last]
    core = _around(lines, low, high, declared[low])
    solid = dict(zip(rows, lengths, strict=True))
    if core > 0 and (declared[low] or lines.stop[core] - lines.first[core] < len(lines.text)):
        kept = [i for i in range(lines.first[core], lines.stop[core]) if low <= i <= high or declared[i] or solid.get(i)]
    elif declared[low]:  # articles without a container around them
        kept = list(rows)
    else:  # the container holds all there is: its runs of text
        spans = [_solid(lengths, a, b) for a, b in runs(lengths, window, surge)]
        kept = [rows[i] for a, b in spans for i in range(a, b + 1)]
    return "\n".join(lines.text[i] for i in kept)


def _solid(lengths: list[int], first: int, last: int) -> tuple[int, int]:
    """A run without the lines of links at its ends: their windows reach into it, but they are none of it."""
    inner = [i for i in range(first, last + 1) if lengths[i]]
    return (inner[0], inner[-1]) if inner else (first, last)


def _around(lines: Lines, low: int, high: int, declared: bool) -> int:
    """The innermost article or main that holds the lines low to high, or else the innermost container; 0 is the page."""
    at = lines.article[lines.inside[low]] if declared else lines.inside[low]
    while at > 0 and lines.stop[at] <= high:
        above = lines.parent[at]
        at = lines.article[above] if declared else above
    if at > 0 or not declared:
        return max(at, 0)
    at = lines.inside[low]
    while at > 0 and lines.stop[at] <= high:
        at = lines.parent[at]
    return at


def extract(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", keep: tuple = ("url",), window: int = 3, surge: int = 86) -> DataFrame:
    """One row a page: id, kept columns, text. Narrow: no shuffle."""

    def run(cols: dict) -> dict:
        texts = [main_text(h, window, surge) for h in cols["html"]]
        return {k: v for k, v in cols.items() if k != "html"} | {"text": texts}

    kinds = {c: pages.schema[c].dataType.simpleString() for c in (id_col, *keep)}
    schema = ", ".join([f"page_id {kinds[id_col]}", *(f"{c} {kinds[c]}" for c in keep), "text string"])
    return common.map_columns(pages, [pages[id_col].alias("page_id"), *(pages[c] for c in keep), pages[html_col].cast("string").alias("html")], run, schema, text="html")
