"""Main text of web pages: parser events, text-to-tag ratio per line, Gaussian smoothing, threshold clustering.

The standard library's parser streams over the page; every block of text is a
line with its characters, its tags and the characters inside links. Smoothed
ratios above a threshold form content regions; lines of the region's container
are then kept whole. Markup that names page furniture takes the pieces of text
inside it, and no others; a name on an element that the page's text is wrapped
in means nothing.
"""

from __future__ import annotations

import heapq
import re
from collections import Counter
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Elements that end a block (fixed values).
BLOCKS = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
#: Elements without content (fixed values).
EMPTY = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose text is never shown as content (fixed values).
SILENT = frozenset("script style noscript template head title svg iframe object canvas audio video select textarea button option".split())
#: Elements that are page furniture (fixed values).
FURNITURE = frozenset("nav footer aside form menu dialog header".split())
#: Roles and words of classes and ids that name furniture (fixed values).
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar toolbar".split())
NAMES = re.compile(
    r"(?:^|[-_\s])(?:ad|ads|advert|adverts|advertisement|advertising|banner|sponsor|sponsored|promo|promotion|nav|navbar|navigation|menu|breadcrumb|breadcrumbs|sidebar|side|aside|widget|footer|header|masthead|cookie|cookies|consent|gdpr|notice|popup|modal|overlay|newsletter|subscribe|signup|login|share|sharing|social|related|recommended|trending|comment|comments|commentlist|disqus|replies|reply|respond|pagination|pager|copyright|legal|skip|toolbar)(?:$|[-_\s\d])",
    re.I,
)
#: Names of what readers wrote, which stays furniture however long it is (fixed values).
READERS = re.compile(r"(?:^|[-_\s])(?:comment|comments|commentlist|disqus|replies|reply|respond)(?:$|[-_\s\d])", re.I)
#: Names of the head of an article, which is content (fixed values).
HEADS = re.compile(r"(?:^|[-_\s])(?:header|masthead)(?:$|[-_\s\d])", re.I)
OWN_HEAD = re.compile(r"(?:^|\s)(?:post|article|entry|story|content)[-_]{1,2}header(?:$|\s)", re.I)
#: An open element that the next one of its kind closes, and what closes it (fixed values).
CLOSES = {"p": BLOCKS, "li": frozenset({"li"}), "dt": frozenset({"dt", "dd"}), "dd": frozenset({"dt", "dd"}), "tr": frozenset({"tr"}), "td": frozenset({"td", "th", "tr"}), "th": frozenset({"td", "th", "tr"}), "option": frozenset({"option"})}
#: What an implied end does not reach past (fixed values).
FENCES = frozenset("table ul ol dl article section div body html main nav aside header footer form blockquote".split())
SPACE = re.compile(r"\s+")
SIGMA = 1.0


def _furniture_name(a: dict[str, str], content: bool) -> tuple[bool, bool]:
    """Whether an element's attributes name furniture, and whether they name what readers wrote."""
    named = a.get("role", "").lower() in ROLES or "hidden" in a or a.get("aria-hidden") == "true"
    readers = False
    for x in (a.get("class", ""), a.get("id", "")):
        if NAMES.search(x):
            # the head of an article is part of it
            plain = HEADS.sub(" ", x) if content else OWN_HEAD.sub(" ", x)
            named = named or bool(NAMES.search(plain))
            readers = readers or bool(READERS.search(plain))
    return named, readers


class Lines(HTMLParser):
    """Blocks of a page in order: [pieces, tags, container]; a piece is (text, characters in links, furniture element).

    ``marks`` tells of each furniture element its parent mark, whether only a
    name makes it so, whether readers wrote it, and the characters inside it.
    Every event costs a constant, apart from the elements that it closes.
    """

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open: list[tuple] = []  # tag, silent, mark before, container before
        self.counts: Counter = Counter()  # open elements by tag
        self.inner: list[Counter] = [Counter()]  # the same, since each open fence
        self.lines: list[list] = []
        self.marks: list[list] = [[-1, False, False, 0]]  # parent, name only, readers, characters; 0 is no furniture
        self.mark = 0
        self.silent = self.container = self.containers = 0
        self.now = [[], 0, 0]

    def _cut(self) -> None:
        if self.now[0]:
            self.lines.append(self.now)
            self.now = [[], 0, 0]

    def handle_starttag(self, tag, attrs):
        if tag in BLOCKS:
            self._cut()
        self.now[1] += 1
        if tag in EMPTY:
            if tag == "br":
                self.handle_data(" ")
            return
        while self.open and tag in CLOSES.get(self.open[-1][0], ()):
            self._pop()
        content = bool(self.counts["article"] or self.counts["main"])
        self.open.append((tag, tag in SILENT, self.mark, self.container))
        self.counts[tag] += 1
        if tag in FENCES:
            self.inner.append(Counter())
        else:
            self.inner[-1][tag] += 1
        self.silent += tag in SILENT
        if tag == "main":
            self.mark = 0  # content, whatever wraps it
        elif tag not in ("html", "body"):
            named, readers = _furniture_name({k: v or "" for k, v in attrs}, content) if attrs else (False, False)
            tagged = tag in FURNITURE and not (tag == "header" and content)
            if named or tagged:
                self.marks.append([self.mark, not tagged, readers, 0])
                self.mark = len(self.marks) - 1
        if tag in ("article", "main"):
            self.containers += 1
            self.container = self.containers

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in EMPTY:
            self.handle_endtag(tag)

    def _pop(self) -> str:
        tag, silent, self.mark, self.container = self.open.pop()
        if tag in BLOCKS:
            self._cut()
        self.counts[tag] -= 1
        if tag in FENCES:
            self.inner.pop()
        else:
            self.inner[-1][tag] -= 1
        self.silent -= silent
        return tag

    def handle_endtag(self, tag):
        if tag in BLOCKS:
            self._cut()
        self.now[1] += 1
        if self.counts[tag] if tag in FENCES else self.inner[-1][tag]:
            while self._pop() != tag:
                pass

    def handle_data(self, data):
        if self.silent or not data:
            return
        size = len(data.strip())
        self.now[0].append((data, size if self.counts["a"] else 0, self.mark))
        self.marks[self.mark][3] += size
        self.now[2] = self.container


def _shown(marks: list[list]) -> list[bool]:
    """For each mark whether text directly under it is content.

    A name takes the text under it, unless next to nothing would be left of the
    page: then the element is a wrapper, and its name means nothing.
    """
    whole = [m[3] for m in marks]  # with all marks inside
    inside: list[list[int]] = [[] for _ in marks]
    for i in range(len(marks) - 1, 0, -1):
        whole[marks[i][0]] += whole[i]
        inside[marks[i][0]].append(i)
    shown = [True] + [False] * (len(marks) - 1)
    left, at = marks[0][3], 0
    edge: list[tuple[int, int]] = []  # named elements right under what is shown, the largest first
    while True:
        for i in inside[at]:
            if marks[i][1] and not marks[i][2]:
                heapq.heappush(edge, (-whole[i], i))
        if not edge:
            return shown
        size, at = heapq.heappop(edge)
        if -2 * size <= whole[0] or 5 * left >= -size:
            return shown
        shown[at] = True
        left += marks[at][3]


def _regions(ratio: np.ndarray) -> np.ndarray:
    """Lines whose smoothed ratio lies in the upper of two clusters (split at the mean, moved to the midpoint of the means until it rests)."""
    reach = np.arange(-3, 4)
    kernel = np.exp(-(reach**2) / (2 * SIGMA**2))
    smooth = np.convolve(np.pad(ratio, 3, mode="edge"), kernel / kernel.sum(), "valid")
    at = smooth.mean()
    for _ in range(50):
        low, high = smooth[smooth <= at], smooth[smooth > at]
        if not len(low) or not len(high):
            break
        new = (low.mean() + high.mean()) / 2
        if abs(new - at) < 1e-9:
            break
        at = new
    return smooth >= at


def main_text(html: str | None) -> str:
    """Content blocks in page order, joined by a blank line; empty if the page has none.

    Where a page has an article or main element, its lines that are not
    furniture are the candidates, else all lines that are not. The candidates'
    upper cluster decides which container or run of lines is content; inside
    it nothing is dropped, however short.
    """
    parser = Lines()
    parser.feed(html or "")
    parser.close()
    parser._cut()
    shown = _shown(parser.marks)
    lines = []
    for pieces, tags, container in parser.lines:
        own = [p for p in pieces if shown[p[2]]]
        text = SPACE.sub(" ", "".join(p[0] for p in own)).strip()
        furniture = not text
        if furniture:
            text = SPACE.sub(" ", "".join(p[0] for p in pieces)).strip()
        if text:
            lines.append((text, max(1, tags), sum(p[1] for p in (pieces if furniture else own)), furniture, container))
    candidates = [x for x in lines if not x[3]]
    if not candidates:
        return ""
    marked = [x for x in candidates if x[4]]
    content = _regions(np.array([0.0 if x[3] else (len(x[0]) - min(x[2], len(x[0]))) / x[1] for x in lines]))
    if marked:
        # the containers that hold content lines; all of them when none does
        chosen = {x[4] for x, c in zip(lines, content, strict=True) if c and x[4] and not x[3]}
        return "\n\n".join(x[0] for x in marked if not chosen or x[4] in chosen)
    where = [i for i, (x, c) in enumerate(zip(lines, content, strict=True)) if c and not x[3]]
    if not where:
        return "\n\n".join(x[0] for x in candidates)
    # from the first to the last line of the cluster, with the headings right before it
    first, last = where[0], where[-1]
    while first > 0 and not lines[first - 1][3] and 2 * lines[first - 1][2] < len(lines[first - 1][0]):
        first -= 1
    while last + 1 < len(lines) and not lines[last + 1][3] and 2 * lines[last + 1][2] < len(lines[last + 1][0]):
        last += 1
    return "\n\n".join(x[0] for x in lines[first : last + 1] if not x[3])


def extract_main_text(df: DataFrame, html_col: str = "html", keep: list[str] | None = None) -> DataFrame:
    """+text, n_chars of every page (null or empty html: empty text). No shuffle; clashing columns are replaced."""
    from pyspark.sql.types import LongType, StringType, StructField, StructType

    keep = [c for c in df.columns if c not in ("text", "n_chars", html_col)] if keep is None else keep
    rows = df.select(*[F.col(f"`{c}`") for c in keep], F.col(html_col).alias("_html"))
    fields = rows.schema.fields[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(h) for h in b.column("_html").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], names=[*b.schema.names[:-1], "text", "n_chars"])

    return rows.mapInArrow(run, StructType([*fields, StructField("text", StringType()), StructField("n_chars", LongType())]))
