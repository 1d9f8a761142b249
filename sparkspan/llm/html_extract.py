"""Main-text extraction by the distribution of text over line blocks.

Markup is stripped into lines, one per block element. The text length of a sliding window of lines is
the block distribution; where it surges above the threshold main text begins, where it dives below it
ends, as often as a page does so. Elements that hold no main text (menus, forms, adverts, ...) are dropped before,
unless size, links and the articles within tell that a mark misleads. The spans found decide; they are widened to the whole of each article or main element that they
reach, so that short closing paragraphs are not lost, and never narrowed to one.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Elements whose text is always dropped, and by how readily other elements are (see
#: ``doubt``); elements that have no end tag, elements that begin a line.
DROPPED = frozenset("menu button select option textarea label iframe object noscript template svg canvas head title".split())
TAGS = {"form": 0, "header": 0, "fieldset": 0, "aside": 1, "figure": 1, "figcaption": 1, "nav": 3, "footer": 3, "dialog": 3}
RAW = frozenset("script style textarea title noscript template iframe".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
HOLDERS = frozenset("article main".split())
#: Words of class, id and role attributes that mark an element as no main text.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertisements advertising banner banners sponsor sponsored promo promos promotion comment comments commentlist respond replies reply discussion disqus "
    "nav navbar navigation menu menus breadcrumb breadcrumbs pagination pager sidebar side aside widget widgets header masthead footer foot topbar notice notices cookie cookies consent gdpr alert popup modal overlay "
    "newsletter subscribe signup login search share sharing social related recommended recommendations toolbar skip tags copyright legal disclaimer contentinfo complementary".split()
)
REPLIES = frozenset("comment comments commentlist respond replies reply discussion disqus".split())
#: Words that make a header one of the text (article-header), not of the site.
HEADED = frozenset("article post entry content story text title".split())
NAME, QUOTED, TAG_LIKE = re.compile(r"/?([a-zA-Z][\w:-]*)"), re.compile(r"[>\"']"), re.compile(r"<[a-zA-Z/!?]")
ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|display\s*:\s*none|aria-hidden\s*=\s*[\"']?true", re.I)
#: Lines of one window, and the characters of a window at which the text surges.
WINDOW, SURGE = 3, 80


def doubt(tag: str, attributes: str, inside: bool) -> int:
    """How readily an element is dropped, -1 if not at all: 0 if small or mostly links (a mark within a
    longer name, some tags), 1 unless it holds the main text (a mark as a whole name), 2 unless there
    is no other text (replies), 3 unless it holds the main article (tags of navigation)."""
    found = [] if tag == "header" and inside else [TAGS.get(tag, -1)]
    for _, *values in ATTRIBUTE.findall(attributes):
        for name in " ".join(values).lower().split():
            runs = set(re.split(r"[^a-z]+", name))
            if "header" in runs and (inside or runs & HEADED):
                runs, name = runs - {"header"}, ""
            found.append(2 if name in REPLIES else 1 if name in MARKS else 0 if runs & MARKS else -1)
    return max(found, default=-1)


class Markup:
    """The tags of a page, one after another, each place of it read a bounded number of times. A quote within a
    tag hides what it holds; once a quoted tag has met the page's end, quotes hide nothing more, so that no later
    one looks that far again."""

    def __init__(self, page: str):
        self.page, self.quotes, self.endless = page, True, set()

    def next(self, at: int) -> tuple[int, int, str, str, bool] | None:
        """(start, end, name or nothing for comments and the like, attributes, whether it closes) of the first tag
        at or behind ``at``; None if no more ends."""
        page = self.page
        while (start := page.find("<", at)) >= 0:
            mark = page[start + 1 : start + 2]
            if mark in ("!", "?") and mark:
                closing = "-->" if page.startswith("<!--", start) else "]]>" if page.startswith("<![CDATA[", start) else ""
                end = page.find(closing or ">", start + 4 if closing == "-->" else start)
                if end >= 0 or closing:
                    return start, end + len(closing or ">") if end >= 0 else len(page), "", "", False
                at = start + 1
                continue
            if (name := NAME.match(page, start + 1)) is None:
                at = start + 1
                continue
            if (end := self._end(name.end())) < 0:
                return None
            return start, end, name[1].lower(), page[name.end() : end - 1], mark == "/"
        return None

    def _end(self, at: int) -> int:
        """Behind the > of a tag whose attributes begin at ``at``."""
        page, place = self.page, at
        while self.quotes:
            m = QUOTED.search(page, place)
            if m is not None and m[0] == ">":
                return m.end()
            place = page.find(m[0], m.end()) + 1 if m is not None else 0
            if not place:
                self.quotes = False
        return page.find(">", at) + 1 or -1

    def behind(self, tag: str, at: int) -> int:
        """Behind the end tag of a raw element whose content begins at ``at``, -1 if none comes."""
        if tag not in self.endless:
            m = re.compile(rf"</{tag}\b", re.I).search(self.page, at)
            end = self.page.find(">", m.end()) + 1 if m else 0
            if end:
                return end
            self.endless.add(tag)
        return -1


class Page:
    """Lines of a page, one per block: pieces (text, innermost doubtful element, in a link, innermost
    holder) and the outermost holder, or -1. Holders are article and main elements."""

    def __init__(self, page: str):
        self.rows: list[tuple[list, int]] = []
        self.doubts: list[tuple[int, int]] = []  # of each doubtful element, the next one outside and its degree
        self.holders: list[int] = []  # of each holder, the innermost doubtful element around it
        self._read(page)

    def _read(self, page: str) -> None:
        parts: list[tuple[str, int, bool, int]] = []
        stack: list[tuple] = []  # open elements, and what held outside each
        drop_from, outer, holder, mark, link, at = -1, -1, -1, -1, False, 0

        def end_line() -> None:
            if parts:
                if any(x[0].strip() for x in parts):
                    self.rows.append((parts.copy(), outer))
                parts.clear()

        def close(depth: int) -> None:
            for x in stack[depth:]:
                now_open[x[0]] -= 1
            del stack[depth:]

        n, markup, now_open = len(page), Markup(page), Counter()
        while at < n:
            found = markup.next(at)
            if found is None:
                rest = page[at:]
                cut = TAG_LIKE.search(rest)  # a tag that never ends
                if drop_from < 0:
                    parts.append((rest[: cut.start()] if cut else rest, mark, link, holder))
                break
            start, end, tag, attributes, closes = found
            if start > at and drop_from < 0:
                parts.append((page[at:start], mark, link, holder))
            at = end
            if not tag:
                continue
            if tag == "body" and drop_from >= 0 and stack[drop_from][0] == "head":
                close(drop_from)  # a head ends where the body begins
                drop_from = -1
            if tag in BLOCKS and drop_from < 0:
                end_line()
            if closes:
                if now_open[tag]:
                    depth = next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag)
                    _, outer, holder, mark, link = stack[depth]
                    close(depth)
                    if drop_from >= depth:
                        drop_from = -1
                continue
            if tag in RAW:
                end = markup.behind(tag, at)
                if end < 0 and tag in ("script", "style"):
                    break
                at = end if end >= 0 else at
                continue
            if tag in VOID or attributes.endswith("/") and tag not in BLOCKS:
                continue
            if tag in ("p", "li", "dt", "dd", "tr", "td", "th", "option") and stack and stack[-1][0] == tag:
                _, outer, holder, mark, link = stack[-1]  # these end where the next begins
                close(len(stack) - 1)
                if drop_from >= len(stack):
                    drop_from = -1
            stack.append((tag, outer, holder, mark, link))
            now_open[tag] += 1
            if drop_from >= 0 or tag in ("html", "body"):
                continue
            if tag in DROPPED or tag not in HOLDERS and HIDDEN.search(attributes):
                drop_from = len(stack) - 1
                continue
            link = link or tag == "a"
            if tag in HOLDERS:
                holder = len(self.holders)
                outer = holder if outer < 0 else outer
                self.holders.append(mark)
            elif (degree := doubt(tag, attributes, holder >= 0)) >= 0:
                self.doubts.append((mark, degree))
                mark = len(self.doubts) - 1
        end_line()

    def outwards(self, sizes: list[int]) -> None:
        """Adds the size of each doubtful element to that of the one outside."""
        for i in range(len(sizes) - 1, -1, -1):
            if (out := self.doubts[i][0]) >= 0:
                sizes[out] += sizes[i]

    def text(self, kept: list[bool]) -> list[tuple[str, int]]:
        """(text, outermost holder) of the lines: references decoded, white space made one blank, empty
        lines left out. kept: of each doubtful element, whether its text counts."""
        stays: list[bool] = []  # no element around it goes either; the one outside has the lower number
        for (out, _), k in zip(self.doubts, kept, strict=True):
            stays.append(k and (out < 0 or stays[out]))
        whole = [(own, "".join(t for t, mark, _, _ in parts if mark < 0 or stays[mark])) for parts, own in self.rows]
        return [(text, own) for own, raw in whole if (text := " ".join(entities.unescape(raw).split()))]

    def keep(self, window: int, surge: int) -> list[bool]:
        """Which doubtful elements are no clutter. Those around the largest article or main stay, and those
        with most of the heaviest span if that is more text than this article; if then no text is
        left, all but those of navigation stay."""
        degree = [d for _, d in self.doubts]
        worst: list[int] = []
        for out, d in self.doubts:
            worst.append(max(d, worst[out] if out >= 0 else -1))
        worse = lambda mark: worst[mark] if mark >= 0 else -1
        chars, links, own = [0] * len(degree), [0] * len(degree), [0] * len(self.holders)
        open_sizes, pieces = [], []
        for row, (parts, _) in enumerate(self.rows):
            open_sizes.append(0)
            for t, mark, link, holder in parts:
                if not (size := len(" ".join(entities.unescape(t).split()))):
                    continue
                if mark >= 0:
                    chars[mark] += size
                    links[mark] += size * link
                if holder >= 0 and not link:
                    own[holder] += size
                if worse(mark) < 2 and not link:
                    open_sizes[row] += size
                    pieces.append((row, mark, size))
        self.outwards(chars)
        self.outwards(links)
        kept = [degree[i] == 0 and chars[i] >= window * surge and 2 * links[i] <= chars[i] for i in range(len(degree))]
        # Replies and navigation hold the main article only where no other could surge.
        able = [h for h in range(len(own)) if own[h] and worse(self.holders[h]) < 2]
        if not any(own[h] >= surge for h in able):
            able = [h for h in range(len(own)) if own[h] >= surge] or able
        main = max(able, key=lambda h: own[h], default=-1)
        mark = self.holders[main] if able else -1
        while mark >= 0:
            kept[mark], mark = True, self.doubts[mark][0]
        start, end = max(spans(open_sizes, window, surge), key=lambda s: sum(open_sizes[slice(*s)]), default=(0, 0))
        within = [0] * len(degree)
        for row, mark, size in pieces:
            if mark >= 0 and start <= row < end:
                within[mark] += size
        self.outwards(within)
        least = max(surge - 1, own[main] if able else 0, sum(open_sizes[start:end]) // 2)
        kept = [k or w > least for k, w in zip(kept, within, strict=True)]
        if not self.text(kept):
            kept = [k or d < 3 for k, d in zip(kept, degree, strict=True)]
        return kept


def lines(page: str, window: int = WINDOW, surge: int = SURGE) -> list[tuple[str, int]]:
    """(text, holder) of each block in page order that is no clutter; holder numbers the outermost
    article or main element, or is -1."""
    read = Page(page)
    return read.text(read.keep(window, surge))


def spans(sizes: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int]]:
    """First and last line (one past) of every stretch between a surge and a dive of the windowed sums. A
    stretch holds all lines of its windows, so that short first and last lines stay. Two of them are one
    if the gap between holds less text than either. Where nothing surges no dive can be told: all
    lines are one stretch; none if no line has text."""
    if not sizes or not max(sizes):
        return []
    sums = np.convolve(np.array(sizes), np.ones(window, np.int64))[window - 1 :]  # of lines i .. i + window - 1
    upto = np.append(0, np.cumsum(sizes)).tolist()
    high = np.flatnonzero(sums >= surge)
    if not len(high):
        return [(0, len(sizes))]
    out: list[tuple[int, int]] = []
    for part in np.split(high, np.flatnonzero(np.diff(high) > window) + 1):
        start, end = int(part[0]), min(len(sizes), int(part[-1]) + window)
        while out and upto[start] - upto[out[-1][1]] < min(upto[out[-1][1]] - upto[out[-1][0]], upto[end] - upto[start]):
            start = out.pop()[0]
        out.append((start, end))
    return out


def main_text(page: str | None, window: int = WINDOW, surge: int = SURGE) -> str:
    """The main text: one line per block. Empty for null, empty and text-free pages."""
    found = lines(page or "", window, surge)
    sizes = [len(t) for t, _ in found]
    kept: set[int] = set()
    held: set[int] = set()
    for start, end in spans(sizes, window, surge):
        reached = {h for _, h in found[start:end]} - {-1}
        if reached:  # an element gives the edge: short lines outside it, at the ends of the span, are the windows' slack
            slack = lambda i: found[i][1] < 0 and sizes[i] < surge
            while slack(start):
                start += 1
            while slack(end - 1):
                end -= 1
        held |= reached
        kept.update(range(start, end))
    return "\n".join(t for i, (t, h) in enumerate(found) if i in kept or h in held)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: id, url, text and n_chars (its code points, long).

    Null and empty pages have an empty text; pages of any length are read whole; repeated rows come back
    as often; an empty table gives an empty result. Other columns are not read.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(x).encode("utf-8", "replace").decode() for x in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["i", "u", "text", "n_chars"])

    out = pages.select(F.col(id_col).cast("bigint").alias("i"), F.col(url_col).alias("u"), F.col(html_col).alias("h")).mapInArrow(run, "i bigint, u string, text string, n_chars bigint")
    return out.withColumnsRenamed({"i": id_col, "u": url_col})
