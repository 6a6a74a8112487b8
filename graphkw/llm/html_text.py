"""Main text of web pages by text-to-tag ratios (operator 10).

The standard library's parser streams a page's events. Text between block-level
tags is one line; its ratio is its characters over its tags, link text not
counted. Lines inside menus, headers, footers, asides, forms, scripts and
containers whose class, id or role says so have ratio zero. The ratios are
smoothed with a Gaussian, and lines above a threshold (a share of their standard
deviation) form content clusters. Where the page marks an article or main
element, the clusters choose among those elements and the chosen ones are taken
whole, so that headings and short paragraphs stay; elsewhere the clusters
themselves are taken, with the lines between and the heading before them.

Edge cases: null or empty html, and pages without content, give an empty text;
unclosed and stray tags are tolerated; a null ``page_id`` or url stays null;
repeated rows are treated each; further columns are ignored. One task holds one
page at a time.
"""

from __future__ import annotations

import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .base import map_batches, table, text_of

SCHEMA = "page_id long, url string, text string, n_chars long"
#: Elements by their part in a page.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIP = frozenset("head title script style noscript template nav header footer aside form button select option textarea iframe object svg canvas dialog menu audio video map datalist".split())
CONTENT = frozenset(("article", "main"))
HEADINGS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))
SKIP_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar toolbar form".split())
SKIP_WORDS = frozenset(
    "ad ads adbox adsense advert adverts advertisement advertising sponsor sponsored promo promoted promotion banner cookie cookies consent gdpr notice notices alert popup modal overlay "
    "sidebar menu navbar nav navigation breadcrumb breadcrumbs pagination pager toolbar footer header masthead comment comments disqus replies respond share sharing social related "
    "recommended recommendations newsletter subscribe subscription signup login search widget skip".split()
)
_WORDS = re.compile(r"[a-z0-9]+")
#: An open one of these ends at the next of its group.
_ENDS_AT = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}


class Lines(HTMLParser):
    """Lines of a page: (text, tags, link characters, skipped, number of the outermost content element or -1, is a heading)."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.lines: list[tuple[str, int, int, bool, int, bool]] = []
        self.open: list[tuple[str, bool, int]] = []  # tag, skipped, content element
        self.elements = 0
        self._fresh()

    def _fresh(self) -> None:
        self.parts: list[str] = []
        self.tags = self.linked = 0
        self.heading = False

    def _end_line(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text or self.tags:
            _, skipped, element = self.open[-1] if self.open else ("", False, -1)
            self.lines.append((text, self.tags, self.linked, skipped, element, self.heading))
        self._fresh()

    def _close(self, depth: int) -> None:
        del self.open[depth:]

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if tag in VOID:
            if tag == "br":
                self.parts.append(" ")
            elif tag not in INLINE:
                self._end_line()
            return
        if tag not in INLINE:
            self._end_line()
            for k in range(len(self.open) - 1, max(-1, len(self.open) - 6), -1):
                if self.open[k][0] in _ENDS_AT.get(tag, ()) or self.open[k][0] == "p" and tag not in INLINE:
                    self._close(k)
                    break
                if self.open[k][0] not in INLINE:
                    break
        _, skipped, element = self.open[-1] if self.open else ("", False, -1)
        skipped = skipped or self._is_aside(tag, attrs, element)
        if tag in CONTENT and element < 0 and not skipped:
            element = self.elements
            self.elements += 1
        self.open.append((tag, skipped, element))
        self.heading = self.heading or tag in HEADINGS

    @staticmethod
    def _is_aside(tag: str, attrs, element: int) -> bool:
        if tag in SKIP:
            return not (tag == "header" and element >= 0)
        if tag in ("html", "body"):
            return False
        for name, value in attrs:
            if name == "hidden" or value and (name == "role" and value.strip().lower() in SKIP_ROLES or name == "aria-hidden" and value.strip().lower() == "true"):
                return True
            if value and name in ("class", "id") and not SKIP_WORDS.isdisjoint(_WORDS.findall(value.lower())):
                return True
        return False

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in VOID:
            return
        if tag not in INLINE:
            self._end_line()
        for k in range(len(self.open) - 1, -1, -1):
            if self.open[k][0] == tag:
                self._close(k)
                break
            if tag in INLINE and self.open[k][0] not in INLINE:
                break

    def handle_data(self, data):
        self.parts.append(data)
        if any(x[0] == "a" for x in self.open[-6:]):
            self.linked += len(data.strip())

    def close(self):
        super().close()
        self._end_line()


def smooth(ratios: np.ndarray, sigma: float = 1.0) -> np.ndarray:
    """Gaussian smoothing with mirrored ends."""
    reach = int(np.ceil(3 * sigma))
    kernel = np.exp(-0.5 * (np.arange(-reach, reach + 1) / sigma) ** 2)
    return np.convolve(np.pad(ratios, reach, "symmetric" if len(ratios) >= reach else "edge"), kernel / kernel.sum(), "valid")


def main_text(html: str | None, share: float = 0.5) -> str:
    """The text of a page's content regions."""
    if not html:
        return ""
    parser = Lines()
    parser.feed(html)
    parser.close()
    lines = parser.lines
    if not any(x[0] and not x[3] for x in lines):
        return ""
    ratios = np.array([0.0 if x[3] else max(0, len(x[0]) - x[2]) / max(1, x[1]) for x in lines])
    flat = smooth(ratios)
    chosen = (flat > share * flat.std()) & (ratios > 0)
    if parser.elements:
        mass = np.zeros(parser.elements)
        for x, r, c in zip(lines, ratios, chosen, strict=True):
            if x[4] >= 0 and c:
                mass[x[4]] += r
        taken = set(np.flatnonzero(mass >= 0.1 * mass.max()).tolist())
        keep = [not x[3] and x[4] in taken for x in lines]
    else:
        keep = chosen.tolist()
        own = np.flatnonzero(chosen)
        if len(own):
            for k in range(own[0], own[-1] + 1):
                keep[k] = keep[k] or not lines[k][3] and 2 * lines[k][2] <= len(lines[k][0])
            k = own[0] - 1
            while k >= 0 and not lines[k][3] and (lines[k][5] or not lines[k][0]):
                keep[k] = True
                k -= 1
        else:
            keep = [not x[3] and 2 * x[2] <= len(x[0]) for x in lines]
    return "\n\n".join(x[0] for x, k in zip(lines, keep, strict=True) if k and x[0])


def extract_text(pages: DataFrame) -> DataFrame:
    """One row per page: its main text and that text's length in code points."""

    def make():
        def work(batch):
            texts = [main_text(h.as_py()) for h in batch.column(2)]
            columns = [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, ["page_id", "url", "text", "n_chars"])

        return work

    return map_batches(pages.select(pages["page_id"].cast("long").alias("page_id"), "url", text_of("html").alias("html")), make, SCHEMA)


def op10_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(table(spark, sf_dir, "pages"))
