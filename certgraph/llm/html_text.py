"""Main text of raw web pages.

The standard library's parser streams events; text is gathered into lines, one for each block of the page. A line's
text-to-tag ratio is its characters for each tag met in it. The ratios, in page order, are smoothed with a
Gaussian kernel and split at a threshold; runs of high lines are the content regions, on every page. Markup is a
weight: lines of a marked article count several times their ratio, and a region in one reaches as far as its mark; any
other region reaches over neighbouring lines of the element that its lines stand in. A marked part without a high line
is left out, and an unmarked region that is high beside it is taken. Links count from where they open to where they close;
one that never closes counts for nothing. Blocks that the markup names as menu, header, footer, sidebar, notice, advert, form or reader comments never count.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element names and name parts of HTML.
_BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
_UNSEEN = frozenset("applet audio button canvas datalist embed head iframe input map math noembed noframes noscript object script select style svg template textarea title video".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_NEVER = frozenset("nav aside form footer menu dialog".split())
_MAIN = frozenset(("article", "main"))
_HOLDS = frozenset("article aside blockquote body center div fieldset figure footer form header main nav section table td".split())
_NAMED = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion breadcrumb breadcrumbs menu nav navbar navigation pager pagination sidebar widget related recommended share sharing social comment comments disqus respond cookie cookies consent gdpr notice banner popup modal overlay newsletter subscribe subscription signup login footer".split())
_NAMED_OUTSIDE = frozenset("header masthead topbar toolbar".split())
_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog menu menubar".split())
_PART = re.compile(r"[a-z0-9]+")

#: Width of the smoothing kernel in lines, its reach, and the share of link text above which a line is a menu.
SIGMA, REACH, LINK_SHARE = 1.0, 3, 0.6
#: How much more the ratio of a line counts that the page marks as part of an article.
MARK_WEIGHT = 4.0


class _Lines(HTMLParser):
    """Gathers (text, tags, first and last character read, excluded, article, holder) for each block."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.lines: list[tuple[str, int, int, int, bool, int, int]] = []
        self.stack: list[tuple[str, bool, int, bool, int]] = []  # name, excluded, article number, unseen, holder
        self.parts: list[str] = []
        self.links: list[tuple[int, int]] = []  # characters read when a link opened, and when it closed
        self.link_from: int | None = None
        self.tags = self.articles = self.holders = self.read = self.line_from = 0

    def _now(self) -> tuple[bool, int, bool, int]:
        return self.stack[-1][1:] if self.stack else (False, 0, False, 0)

    def _end_line(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text:
            excluded, article, _, holder = self._now()
            self.lines.append((text, self.tags, self.line_from, self.read, excluded, article, holder))
            self.tags = 0
        self.parts, self.line_from = [], self.read

    def _excluded(self, tag: str, attrs: dict[str, str], inside: bool) -> bool:
        if tag in _NEVER or (tag == "header" and not inside):
            return True
        if "hidden" in attrs or attrs.get("aria-hidden") == "true" or "display:none" in attrs.get("style", "").replace(" ", "").lower():
            return True
        role = attrs.get("role", "").lower()
        if role in _ROLES and not (inside and role == "banner"):
            return True
        if tag in ("body", "html") or tag in _MAIN:
            return False
        named = set(_PART.findall(f"{attrs.get('class', '')} {attrs.get('id', '')}".lower()))
        return bool(named & _NAMED) or (not inside and bool(named & _NAMED_OUTSIDE))

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if tag in _BLOCK:
            self._end_line()
        if tag == "br":
            self.parts.append(" ")
        if tag in _VOID:
            return
        own = {k: v or "" for k, v in attrs}
        if tag == "p":  # a paragraph ends the one before it
            self._close("p", stop=_BLOCK - {"p"})
        excluded, article, unseen, holder = self._now()
        if tag in _HOLDS:
            self.holders += 1
            holder = self.holders
        if not article and (tag in _MAIN or own.get("role", "").lower() == "main"):
            self.articles += 1
            article = self.articles
        elif tag == "article" and article:
            self.articles += 1
            article = self.articles
        self.stack.append((tag, excluded or self._excluded(tag, own, bool(article)), article, unseen or tag in _UNSEEN, holder))
        if tag == "a":
            self.link_from = self.read

    def _close(self, tag: str, stop: frozenset = frozenset()) -> None:
        for k in range(len(self.stack) - 1, -1, -1):
            if self.stack[k][0] == tag:
                del self.stack[k:]
                return
            if self.stack[k][0] in stop:
                return

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in _VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in _BLOCK:
            self._end_line()
        if tag == "a" and self.link_from is not None:
            self.links.append((self.link_from, self.read))
            self.link_from = None
        if tag not in _VOID:
            self._close(tag)

    def handle_data(self, data):
        if self._now()[2]:
            return
        self.parts.append(data)
        self.read += len(data)

    def finish(self):
        self.close()
        self._end_line()
        return self.lines

    def linked(self) -> np.ndarray:
        """Share of each line's characters that stand in closed links."""
        first, last = (np.array([x[k] for x in self.lines]) for k in (2, 3))
        edges = np.array([0, *(x for pair in self.links for x in pair)])
        sums = np.concatenate([[0], np.cumsum(np.diff(edges) * (np.arange(len(edges) - 1) % 2))])
        return (np.interp(last, edges, sums) - np.interp(first, edges, sums)) / np.maximum(1, last - first)


def smoothed(values: np.ndarray) -> np.ndarray:
    """Gaussian smoothing, with the kernel cut and renewed at the ends."""
    at = np.arange(-REACH, REACH + 1)
    kernel = np.exp(-(at**2) / (2 * SIGMA**2))
    n = len(values)
    reach = np.convolve(values, kernel)[REACH : REACH + n]
    return reach / np.convolve(np.ones(n), kernel)[REACH : REACH + n]


def main_text(html: str | None) -> str:
    """The article of a page: its blocks in page order, one to a line; empty if there is none."""
    if not html:
        return ""
    parser = _Lines()
    parser.feed(html)
    if not parser.finish():
        return ""
    seen = np.array([not x[4] for x in parser.lines])
    if not seen.any():
        return ""
    lines = [x for x in parser.lines if not x[4]]
    articles, holders = np.array([x[5] for x in lines]), np.array([x[6] for x in lines])
    ratio = smoothed(np.array([len(x[0]) / max(1, x[1]) for x in lines]) * np.where(articles > 0, MARK_WEIGHT, 1.0))
    high = ratio >= min(float(ratio.std()), float(ratio.max()))
    dense = parser.linked()[seen] > LINK_SHARE
    found = high & ~dense
    keep = np.zeros(len(lines), dtype=bool)
    if not found.any():
        keep = (articles > 0) if (articles > 0).any() else ~dense
    # an unmarked part ends where another element's lines, an excluded block or an article begins
    places = np.flatnonzero(seen)
    runs = np.concatenate([[0], np.cumsum((np.diff(articles) != 0) | ((np.diff(holders) != 0) | (np.diff(places) > 1)) & (articles[1:] == 0))])
    for part in [np.flatnonzero(articles == a) for a in np.unique(articles[articles > 0])] + [np.flatnonzero(runs == r) for r in np.unique(runs[articles == 0])]:
        inside = np.flatnonzero(found[part])
        if len(inside):  # mark or element set how far the region reaches, but for menus at its ends
            between = (np.arange(len(part)) >= inside[0]) & (np.arange(len(part)) <= inside[-1])
            keep[part[(between & (articles[part[0]] > 0)) | ~dense[part]]] = True
    return "\n".join(line[0] for line, k in zip(lines, keep, strict=True) if k)


def _extracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [main_text(h) for h in batch.column(2).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Return page_id, url, text, n_chars (code points), one row for each row of `pages`.

    A null or empty page gives an empty text, as does one without text outside excluded blocks; broken or cut-off markup is
    read as far as it goes; ids and urls are passed through, null or repeated; an empty table gives an empty result; other
    columns are not read.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return rows.mapInArrow(_extracted, "page_id long, url string, text string, n_chars long")
