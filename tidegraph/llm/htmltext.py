"""Main text of web pages: parser events, text-to-tag ratio by line, Gaussian smoothing and threshold clustering."""

from __future__ import annotations

import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from tidegraph.runtime import ship

#: Elements that never hold main text.
_DEAD = frozenset("script style noscript template svg math iframe object canvas audio video select button textarea nav footer aside menu dialog head title input label".split())
#: Elements that start and end a line.
_BREAKS = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split()
)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_HOLDERS = frozenset(("article", "main"))
#: Words of a class, id or role that mark page furniture.
_FURNITURE = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|adverti[sz]ement|banner|breadcrumbs?|comments?|comment-?list|cookies?|consent|disqus|footer|legal|login|masthead|menu|modal|nav|navbar|navigation|newsletter|notice|pagination|popup|promo\w*|related|replies|reply|share|sharing|sidebar|social|sponsor\w*|subscribe|toolbar|widget)(?:$|[\s_-])",
    re.I,
)
#: Elements whose lines are running text, however short.
_PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre".split())
_CLOSES_P = _BREAKS - {"option", "legend", "summary"}


class _Lines(HTMLParser):
    """Cuts a page into lines at block elements: (text, tags, holder, form, block), where holder and form count the article or
    main element and the form around the line, or are -1, and block is the tag of its element. Tags of dead elements don't count."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open: list[tuple[str, bool, int, int]] = []
        self.dead = 0
        self.holder, self.holders = -1, 0
        self.form, self.forms = -1, 0
        self.whole: set[int] = set()  # forms with an article or main element inside
        self.opened: dict[str, int] = {}
        self.blocks = [""]
        self.lines: list[tuple[str, int, int, int, str]] = []
        self.text: list[str] = []
        self.tags = 0

    def _flush(self) -> None:
        if self.text:
            joined = " ".join("".join(self.text).split())
            if joined:
                self.lines.append((joined, self.tags, self.holder, self.form, self.blocks[-1]))
                self.tags = 0
            self.text = []

    def handle_starttag(self, tag, attrs):
        self.tags += not self.dead
        if tag == "br":
            self.text.append(" ") if not self.dead else None
            return
        if tag in _BREAKS:
            self._flush()
            if tag in _CLOSES_P:
                self._end_paragraph()
        if tag in _VOID:
            return
        if tag == "li":
            self._end_item()
        marked = any(k in ("class", "id", "role") and v and _FURNITURE.search(v) for k, v in attrs) or any(k == "hidden" or (k == "aria-hidden" and v == "true") for k, v in attrs)
        dead = tag in _DEAD or (marked and tag not in ("html", "body", "article", "main")) or (tag == "header" and self.holder < 0)
        self.open.append((tag, dead, self.holder, self.form))
        self.opened[tag] = self.opened.get(tag, 0) + 1
        if tag in _BREAKS:
            self.blocks.append(tag)
        self.dead += dead
        if tag in _HOLDERS and not self.dead:
            self.whole.add(self.form)
            self.holder, self.holders = (self.holder, self.holders) if self.holder >= 0 else (self.holders, self.holders + 1)
        if tag == "form" and self.form < 0:
            self.form, self.forms = self.forms, self.forms + 1

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)

    def _close_to(self, at: int) -> None:
        for tag, dead, holder, form in reversed(self.open[at:]):
            self.dead -= dead
            self.holder, self.form = holder, form
            self.opened[tag] -= 1
            if tag in _BREAKS:
                self.blocks.pop()
        del self.open[at:]

    def _end_paragraph(self) -> None:
        """A block element ends an open paragraph, with what is open inside it."""
        for at in range(len(self.open) - 1, -1, -1):
            tag = self.open[at][0]
            if tag == "p":
                self._close_to(at)
                return
            if tag in _BREAKS:
                return

    def _end_item(self) -> None:
        """A list item ends the one before it."""
        for at in range(len(self.open) - 1, -1, -1):
            tag = self.open[at][0]
            if tag == "li":
                self._close_to(at)
                return
            if tag in ("ul", "ol", "menu"):
                return

    def handle_endtag(self, tag):
        self.tags += not self.dead
        if tag in _BREAKS:
            self._flush()
        if not self.opened.get(tag):
            return
        for at in range(len(self.open) - 1, -1, -1):
            if self.open[at][0] == tag:
                self._close_to(at)
                return
            if self.open[at][0] in ("article", "main", "body") and tag not in _BREAKS:
                return

    def handle_data(self, data):
        if not self.dead:
            self.text.append(data)

    def finish(self) -> list[tuple[str, int, int, str]]:
        """(text, tags, holder, block) of the lines outside forms. A form that wraps an article, or most of the page's text, is no form to fill in: its lines stay."""
        self.close()
        self._flush()
        sizes: dict[int, int] = {}
        for text, _, _, form, _ in self.lines:
            sizes[form] = sizes.get(form, 0) + len(text)
        kept = self.whole | {f for f, n in sizes.items() if 2 * n > sum(sizes.values())} | {-1}
        return [(*line[:3], line[4]) for line in self.lines if line[3] in kept]


def smoothed(ratios: np.ndarray, radius: int = 2) -> np.ndarray:
    """Gaussian smoothing over neighbouring lines; the ends repeat."""
    kernel = np.exp(-0.5 * (np.arange(-radius, radius + 1) / max(radius / 2, 0.5)) ** 2)
    return np.convolve(np.pad(ratios, radius, mode="edge"), kernel / kernel.sum(), mode="valid")


def _regions(lines: list[tuple[str, int, int, str]]) -> list[list[int]]:
    """Line numbers of each candidate: the lines of an article or main element, and each run of lines outside of all."""
    out: list[list[int]] = []
    held: dict[int, list[int]] = {}
    before = None
    for i, (_, _, holder, _) in enumerate(lines):
        if holder >= 0 and holder in held:
            held[holder].append(i)
        elif holder < 0 and before == holder:
            out[-1].append(i)
        else:
            out.append([i])
            if holder >= 0:
                held[holder] = out[-1]
        before = holder
    return out


def content_lines(lines: list[tuple[str, int, int, str]]) -> list[str]:
    """The lines of the page's content regions, in the order of the page.

    Lines outside furniture get their text-to-tag ratio, smoothed within their candidate region; ratios above the page's
    threshold (their standard deviation, or half their mean if that is less) are content. Every region with content is
    kept: of an article or main element all lines, short ones too, of text outside the lines from the first to the last
    content line that is a paragraph or heading, or is content by its own ratio too: smoothing alone would take in the
    menu entries next to a text.
    """
    if not lines:
        return []
    ratios = np.array([len(t) / max(1, k) for t, k, *_ in lines], dtype=np.float64)
    regions = _regions(lines)
    smooth = np.empty_like(ratios)
    for own in regions:
        smooth[own] = smoothed(ratios[own])
    limit = min(smooth.std(), smooth.mean() / 2)
    content = smooth >= limit
    sure = content & ((ratios >= limit) | np.array([block in _PROSE for *_, block in lines]))
    kept: list[int] = []
    for own in regions:
        good = np.flatnonzero(sure[own])
        if len(good):
            kept += own if lines[own[0]][2] >= 0 else own[good[0] : good[-1] + 1]
    return [lines[i][0] for i in sorted(kept)]


def main_text(html: str | None) -> str:
    """The main text of a page, its blocks joined by line feeds; empty for null, empty or bare markup."""
    if not html:
        return ""
    parser = _Lines()
    parser.feed(html)
    return "\n".join(content_lines(parser.finish()))


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``(page_id, url, text, n_chars)`` of every page; null html gives an empty text. Other columns are not read."""
    ship(pages.sparkSession)

    def run(batches):
        for batch in batches:
            texts = [main_text(x) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    chosen = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    return chosen.mapInArrow(run, "page_id long, url string, text string, n_chars long")
