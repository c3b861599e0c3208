"""Main text of web pages.

The standard library's parser streams events; each block-level element is one line with its text,
the tags inside it and the share of its text that stands in links. Boilerplate containers are
left out by tag, role, class and id. On every page the lines' text-to-tag ratios are smoothed with
a Gaussian and split in two clusters; the upper one is the core of the text. A mark of the page
(article, main) is a prior only: it says on which side of its border the text stands, if most of
the core agrees. Containers that are mostly core give their short lines too.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from html.parser import HTMLParser

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element kinds of the HTML standard.
BLOCKS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SILENT = frozenset("script style noscript template svg math head title iframe object canvas audio video map applet".split())
#: Never article text: menus, page furniture, forms.
FURNITURE = frozenset("nav footer aside form menu button select textarea dialog fieldset datalist".split())
REGIONS = frozenset(("article", "main"))
#: Containers that hold a run of lines.
GROUPS = REGIONS | {"div", "section"}
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar".split())
#: Parts of class and id names that mark page furniture.
MARKS = frozenset("ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu submenu breadcrumb breadcrumbs sidebar side rail footer masthead cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended recommendations comment comments commentlist disqus reply replies respond widget toolbar pagination pager skip toc search".split())
#: Elements whose end an opening of the same kind implies.
SELF_CLOSING = frozenset("p li dt dd option tr td th".split())
_part = re.compile(r"[a-z]+")
_hidden = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)


@dataclass
class Line:
    parts: list[str] = field(default_factory=list)
    tags: int = 0
    linked: int = 0
    region: int = 0  # 2 in an article, 1 in main alone
    group: int = 0  # number of the innermost container, 0 for the page's body
    heading: bool = False

    @property
    def mostly_links(self) -> bool:
        return 2 * self.linked > len(self.text)

    @property
    def text(self) -> str:
        return " ".join("".join(self.parts).split())


class LineReader(HTMLParser):
    """Lines of a page, furniture left out. Unclosed and stray tags are taken as a browser would: an end tag closes what stands open above its start, one without a start is passed over."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.lines: list[Line] = []
        self.line = Line()
        self.open: list[tuple[str, bool, bool, bool]] = []  # tag, leaves text out, is a region, is a link
        self.out = self.regions = self.articles = self.links = self.headings = 0
        self.groups, self.groups_seen = [0], 0

    def _break(self):
        if self.line.parts:
            self.lines.append(self.line)
        self.line = Line()
        self._place()

    def _place(self):
        self.line.region = 2 if self.articles else 1 if self.regions else 0
        self.line.group = self.groups[-1]
        self.line.heading = self.headings > 0

    def _drops(self, tag: str, attrs: dict) -> bool:
        if tag in SILENT or tag in FURNITURE or tag == "header" and not self.regions:
            return True
        if tag in ("html", "body"):
            return False
        if "hidden" in attrs or (attrs.get("aria-hidden") or "").lower() == "true" or _hidden.search(attrs.get("style") or "") or (attrs.get("role") or "").lower() in ROLES:
            return True
        if tag in REGIONS and not (attrs.get("class") or attrs.get("id")):
            return False
        names = set(_part.findall(f"{attrs.get('class') or ''} {attrs.get('id') or ''}".lower()))
        return bool(names & MARKS)

    def handle_starttag(self, tag, attrs):
        self.line.tags += 1
        if tag in VOID:
            if tag == "hr":
                self._break()
            elif not self.out:
                self.line.parts.append(" " if tag == "br" else "")
            return
        if tag in BLOCKS:
            self._break()
        if self.open and (tag in SELF_CLOSING and self.open[-1][0] == tag):
            self.handle_endtag(tag)
        elif tag in BLOCKS and tag != "p":
            while self.open and self.open[-1][0] == "p":
                self.handle_endtag("p")
        drops = self._drops(tag, dict(attrs)) if not self.out else False
        region = tag in REGIONS and not self.out and not drops
        self.open.append((tag, drops, region, tag == "a"))
        self.out += drops
        self.regions += region
        self.articles += region and tag == "article"
        self.links += tag == "a"
        self.headings += tag in HEADINGS
        if tag in GROUPS:
            self.groups_seen += 1
            self.groups.append(self.groups_seen)
        if tag in BLOCKS:
            self._place()

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID and tag in ("svg", "math"):
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        if tag in VOID:
            return
        at = next((i for i in range(len(self.open) - 1, -1, -1) if self.open[i][0] == tag), None)
        if at is None:
            return
        if tag not in BLOCKS and any(name in BLOCKS for name, *_ in self.open[at + 1 :]):
            self.open[at] = ("", *self.open[at][1:3], False)  # a stray end of an inline element across a block
            self.links -= tag == "a"
            return
        if any(name in BLOCKS for name, *_ in self.open[at:]):
            self._break()
        for name, drops, region, link in self.open[at:]:
            self.out -= drops
            self.regions -= region
            self.articles -= region and name == "article"
            self.links -= link
            self.headings -= name in HEADINGS
            if name in GROUPS:
                self.groups.pop()
        del self.open[at:]
        if not self.line.parts:
            self._place()

    def handle_data(self, data):
        if not self.out:
            if not self.line.parts:
                self._place()
            self.line.parts.append(data)
            if self.links:
                self.line.linked += len(data.strip())

    def finish(self) -> list[Line]:
        self.close()
        self._break()
        return [x for x in self.lines if x.text]


def smooth(values: np.ndarray, sigma: float = 1.0) -> np.ndarray:
    """Gaussian smoothing over neighbouring lines; the weights are renewed at the ends."""
    radius = max(1, int(3 * sigma))
    kernel = np.exp(-0.5 * (np.arange(-radius, radius + 1) / sigma) ** 2)
    total = np.convolve(values, kernel)[radius : radius + len(values)]
    return total / np.convolve(np.ones(len(values)), kernel)[radius : radius + len(values)]


def upper_cluster(values: np.ndarray) -> np.ndarray:
    """Which values belong to the upper of two clusters (two means in one dimension); all, if they hardly differ."""
    low, high = float(values.min()), float(values.max())
    if high <= 2 * low + 1e-9:
        return np.ones(len(values), dtype=bool)
    for _ in range(50):
        cut = (low + high) / 2
        new = float(values[values <= cut].mean()), float(values[values > cut].mean())
        if new == (low, high):
            break
        low, high = new
    return values > (low + high) / 2


def main_lines(lines: list[Line], sigma: float = 1.0) -> list[Line]:
    """The lines of the text, chosen by their smoothed text-to-tag ratios on every page.

    Core: lines of the upper cluster that are not mostly links. Marks are a prior: articles that
    hold less than half of the core are teasers and are left out; of the rest, where marks hold
    half of the core or more, the lines outside are left out. A container at least half of whose
    text is core gives all lines but lists of links; elsewhere core lines stay, and headings right
    above them. Without any core the marked lines are the text.
    """
    if not lines:
        return []
    size = np.array([max(0, len(x.text) - x.linked) for x in lines])
    upper = upper_cluster(smooth(np.log1p(size / (np.array([x.tags for x in lines]) + 1)), sigma))
    links = np.array([x.mostly_links for x in lines])
    region, group, heading = (np.array([getattr(x, name) for x in lines]) for name in ("region", "group", "heading"))
    core = upper & ~links
    if not core.any():
        return [x for x in lines if x.region]
    text = size * core
    allowed = np.ones(len(lines), dtype=bool)
    if 2 * text[region == 2].sum() < text.sum():
        allowed &= region != 2
    if 2 * text[allowed & (region > 0)].sum() >= text[allowed].sum():
        allowed &= region > 0
    core &= allowed
    keep = core.copy()
    for g in set(group[core].tolist()) - {0}:
        own = allowed & (group == g)
        if 2 * size[own & core].sum() >= size[own].sum():
            keep |= own & (upper | heading | ~links)
    for i in range(len(lines) - 2, -1, -1):
        keep[i] |= heading[i] and allowed[i] and keep[i + 1] and group[i] == group[i + 1]
    return [x for x, k in zip(lines, keep, strict=True) if k]


def extract(html: str | None) -> str:
    """Main text of one page: blocks in page order, joined by newlines. Null, empty or only furniture: the empty string."""
    if not isinstance(html, str) or not html:
        return ""
    reader = LineReader()
    reader.feed(html)
    return "\n".join(x.text for x in main_lines(reader.finish()))


def extract_pages(pages: DataFrame, *, html_col: str = "html", out_col: str = "text") -> DataFrame:
    """Every row with its main text; one narrow pass. An old column of that name is replaced."""

    @F.pandas_udf("string")
    def read(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for pages in batches:
            yield pages.map(extract)

    return pages.withColumn(out_col, read(F.col(html_col)))


def op6(spark, sf_dir: str) -> DataFrame:
    from llm.store import table

    pages = extract_pages(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return pages.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
