"""Main text of web pages by the distribution of text over blocks of lines.

Markup is stripped first: every block element ends a line, and elements that never hold an article (navigation,
headers and footers, asides, forms, scripts, styles, and those whose class or id names such a part or reader
comments) leave a gap. Tags shape a line's weight and no more: words inside links count nothing, lines that an element
declares as main text weigh ``DECLARED`` times their length, and where there are such lines all others weigh nothing.
Then weights are summed over sliding windows of lines, on every page alike; a window that surges above a threshold
opens the main text, the first empty window after it is the dive that closes it, and all lines between are kept. Gaps
are as wide as a window, so no window looks across one; stretches without a surge that gaps cut off from the main text
stay in it where they lie between two parts of it, or next to one in its container.
"""

from __future__ import annotations

import html
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

WINDOW = 3  # lines in a block
SURGE = 80  # weight of a block that opens the main text
DECLARED = 10  # weight of a character that an element declares as main text
LINK_SHARE = 0.5  # lines with more of their text in links count nothing

# Elements of HTML by their part in a page.
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split()
)
RAW = frozenset("script style title textarea noscript template iframe noembed noframes xmp svg math object select datalist canvas audio video".split())
NEVER = frozenset("nav header footer aside form menu dialog head button fieldset".split())
MAIN = frozenset({"article", "main"})
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HINTS = regex.compile(
    r"ads?|adverts?|advertisements?|adsense|banner|promo(?:tion)?|sponsor(?:ed)?|sidebar|side-?bar|widget|menu|nav(?:bar|igation)?|breadcrumbs?|footer|masthead|site-?header|page-?header|cookies?|consent|notice|alert|popup|modal|overlay|newsletter|subscribe|signup|sign-?up|login|social|share|sharing|related|recommended|comments?|disqus|replies|respond|discussion|pagination|pager|toolbar|skip-?link|hidden"
)
COMMENTS = regex.compile(r"comments?|disqus|replies|respond|discussion")
# Words of class names: those that say how a page is laid out around a part, and those that may follow a part's name.
LAYOUT = frozenset("with without no has not show hide".split())
AFTER = frozenset("ad ads area bar block body box btn button buttons card column container content form group holder icons inner item items link links list main module outer panel place placeholder row section slot space thread top bottom left right unit widget wrap wrapper zone".split())
LOOSE = {"p": BLOCKS, "li": {"li"}, "tr": {"tr"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}}  # what ends them, where their own end is left out
INLINE = frozenset("h1 h2 h3 h4 h5 h6 blockquote pre address center figure figcaption dl dir".split())  # blocks of the text around them

_TAG = regex.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+>|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>", regex.S)
_CLASS = regex.compile(r"(?:class|id|role|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", regex.I)


def _names(hint: str, parts: regex.Pattern) -> bool:
    """Does a class or id name one of ``parts``: as a whole, as its last words, or followed by words such as "box"?"""
    for token in hint.split():
        words = [x for x in regex.split(r"[-_:]+", token) if x]
        if LAYOUT.intersection(words):
            continue
        end = len(words)
        while end and (words[end - 1] in AFTER or words[end - 1].isdigit()):
            end -= 1
        for last in range(end, len(words) + 1):
            if any(parts.fullmatch("-".join(words[i:last])) for i in range(max(0, last - 2), last)):
                return True
    return False


def _hint(attributes: str) -> str:
    return " ".join("".join(x) for x in _CLASS.findall(attributes)).lower() if attributes else ""


class _Page:
    """Lines of a page: text, characters outside links, and whether an element declares them as main text.

    ``within`` has the containers of each line, innermost last; none are those of the body itself."""

    def __init__(self) -> None:
        self.lines: list[tuple[str, int, bool]] = []
        self.within: list[tuple[int, ...]] = []
        self.containers: tuple[int, ...] = ()
        self.parts: list[str] = []
        self.linked = 0
        self.breaks = 0

    def end_line(self, inside: bool) -> None:
        text = " ".join("".join(self.parts).split())
        if text:
            free = len(text) - self.linked
            self.lines.append((text, free if free >= (1 - LINK_SHARE) * len(text) else 0, inside))
            self.within.append(self.containers)
        self.parts, self.linked, self.breaks = [], 0, 0

    def gap(self) -> None:
        if self.lines and self.lines[-1][0]:
            self.lines += [("", 0, False)] * WINDOW
            self.within += [()] * WINDOW


def strip_markup(page: str) -> list[tuple[str, int, bool]]:
    """Lines of a page with gaps (empty lines) where parts that hold no article stood."""
    return _strip(page).lines


def _strip(page: str) -> _Page:
    out, at, size = _Page(), 0, len(page)
    stack: list[tuple[str, bool, bool, bool, int]] = []  # name, left out, main, a gap at its end, place in the page
    skip = inside = False
    links = 0
    while at < size:
        tag = _TAG.search(page, at)
        if (end := tag.start() if tag else size) > at and not skip:
            text = html.unescape(page[at:end])
            out.parts.append(text)
            if text.strip():
                out.breaks = 0
                if links:
                    out.linked += len(" ".join(text.split()))
        if not tag:
            break
        at = tag.end()
        name = (tag[2] or tag[5] or "").lower()
        if not name:
            continue
        closing, attributes = tag[1] or tag[4], tag[3] or tag[6] or ""
        if name == "a":
            links = 0 if closing else 1
        if name not in BLOCKS and name not in NEVER and name not in RAW and name not in VOID:
            if closing and stack and stack[-1][0] == name:
                stack.pop()
                skip = any(x[1] for x in stack)
            elif not closing and not attributes.endswith("/") and (skip or (attributes and not any(x[0] == "pre" for x in stack) and _names(_hint(attributes), HINTS))):
                stack.append((name, True, False, False, at))
                skip = True
        elif name == "br":
            out.parts.append(" ")
            out.breaks += 1
            if out.breaks > 1 and not skip:
                out.end_line(inside)
        elif name in RAW:
            if not closing and not attributes.endswith("/"):
                stop = regex.compile(rf"</{regex.escape(name)}(?=[\s/>])", regex.I).search(page, at)
                if stop:
                    at = page.find(">", stop.start()) + 1 or size
                elif name in ("script", "style", "title", "textarea"):
                    at = size
            if name in BLOCKS and not skip:
                out.end_line(inside)
        elif name in BLOCKS or name in NEVER:
            if not skip:
                out.end_line(inside)
            while stack and not closing and name in LOOSE.get(stack[-1][0], ()):
                stack.pop()
            skip = any(x[1] for x in stack)
            if closing:
                while stack and stack[-1][0] not in BLOCKS and stack[-1][0] not in NEVER:  # inline parts that were never closed
                    stack.pop()
                places = [i for i, x in enumerate(stack) if x[0] == name]
                if places:
                    if any(x[3] for x in stack[places[-1] :]):
                        out.gap()
                    del stack[places[-1] :]
            elif name in LOOSE:
                if skip or (attributes and _names(_hint(attributes), HINTS)):
                    stack.append((name, True, False, False, at))
            elif name not in VOID and name not in ("html", "body"):
                hint = _hint(attributes)
                main = (name in MAIN or bool(regex.search(r"(?<![a-z])articlebody(?![a-z])", hint))) and not _names(hint, COMMENTS)
                left = (name in NEVER and not (name == "header" and inside)) or (name != "article" and name != "main" and _names(hint, HINTS)) or _names(hint, COMMENTS)
                if main and skip and stack and not any(x[1] and (x[0] in NEVER) for x in stack):
                    stack = [x for x in stack if not x[1]]  # an advert or notice that was never closed
                if left or main:
                    out.gap()
                stack.append((name, left, main, left or main, at))
            out.containers = tuple(x[4] for x in stack if x[0] not in INLINE and x[0] not in LOOSE)
            skip, inside = any(x[1] for x in stack), any(x[2] for x in stack)
    if not skip:
        out.end_line(inside)
    return out


def weights(lines: list[tuple[str, int, bool]]) -> list[int]:
    """What each line adds to its windows."""
    if any(x[2] for x in lines):
        return [DECLARED * max(n, 1) if text and declared else 0 for text, n, declared in lines]
    return [n if text else 0 for text, n, _ in lines]


def surges(weight: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int]]:
    """(first, end) of the lines between each surge and its dive.

    A line opens a run if it weighs something and the window from it on reaches ``surge``, or the page's largest
    window where that is less. The run goes on to the first window of weight 0 and ends after its last line with weight.
    """
    upto = [0, *accumulate([*weight, *[0] * window])]
    blocks = [upto[i + window] - upto[i] for i in range(len(weight))]
    threshold = min(surge, max([1, *blocks]))
    runs, i = [], 0
    while i < len(weight):
        if blocks[i] < threshold or not weight[i]:
            i += 1
            continue
        end = i
        while end < len(weight) and blocks[end]:
            end += 1
        last = max(j for j in range(i, min(end + 1, len(weight))) if weight[j])
        runs.append((i, last + 1))
        i = last + 1
    return runs


def _joined(lines: list[tuple[str, int, bool]], weight: list[int], within: list[tuple[int, ...]], runs: list[tuple[int, int]]) -> set[int]:
    """Numbers of the lines of the runs and of the stretches without a surge that gaps cut off from them: between two
    runs, lines with weight; and next to kept lines each line whose container is their container, or holds it or lies
    in it and is not the body. Of lines before a surge in its own stretch, and of declared pages' other lines, none."""
    kept = {i for a, b in runs for i in range(a, b)}
    stretches, at = [], []
    for i, x in enumerate(lines):
        if x[0]:
            at.append(i)
        elif at:
            stretches.append(at)
            at = []
    stretches += [at] if at else []
    declared = any(x[2] for x in lines)
    may = {i for s in stretches for i in s if not declared or lines[i][2]}
    for s in stretches:
        mine = [i for i in s if i in kept]
        may -= set(s[: s.index(mine[0])]) if mine else set()
        if runs and not mine and runs[0][0] < s[0] < runs[-1][1]:
            kept |= {i for i in s if weight[i]}

    def near(i: int, j: int) -> bool:
        a, b = within[i], within[j]
        return a == b or bool(a and b and (a == b[: len(a)] or b == a[: len(b)]))

    text = [i for s in stretches for i in s]
    for order, leading in ((text, False), (text[::-1], True)):
        last = None
        for i in order:
            if i in kept:
                last = i
            elif last is not None and i in may and near(i, last) and not (leading and not weight[i]):
                kept.add(i)
            else:
                last = None
    return kept


def main_lines(lines: list[tuple[str, int, bool]], window: int = WINDOW, surge: int = SURGE, within: list[tuple[int, ...]] | None = None) -> list[str]:
    """Lines between surges and dives; with the containers of the lines, ``within``, stretches that gaps cut off are joined."""
    weight, declared = weights(lines), any(x[2] for x in lines)
    runs = surges(weight, window, surge)
    kept = {i for a, b in runs for i in range(a, b)} if within is None else _joined(lines, weight, within, runs)
    return [x[0] for i, x in enumerate(lines) if i in kept and x[0] and (weight[i] or not declared)]


def main_text(page: str | None, window: int = WINDOW, surge: int = SURGE) -> str:
    """Blocks of the main text, each with single spaces, joined by two line feeds; empty for null or none."""
    if not page:
        return ""
    stripped = _strip(page)
    return "\n\n".join(main_lines(stripped.lines, window, surge, stripped.within))


def extract(pages: DataFrame, html_column: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every row of ``pages``; each page is read whole, in one pass over its tags.

    Null and empty pages, and pages without main text, have an empty text. Repeated rows come out each. Other columns
    are left out. No row is shuffled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x) for x in batch["html"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["page_id"], batch["url"], pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.selectExpr("page_id", "url", f"`{html_column}` as html")
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
