"""Main text of HTML pages by composite text density.

A page becomes a flat tree of nodes in page order.  Every node gets a density: its characters for each
tag, adjusted by how much of it stands in links.  A node's density sum adds those of its children, and
the node with the largest sum is the core of the article.  From there the choice widens to a parent as
long as what the parent adds is dense enough beside the thinnest node on the path to the body.

Tags and names adjust densities and never choose: navigation, page headers, footers, asides and what
class, id or role call an advert, notice, menu or comment area weigh next to nothing; headings weigh
more; leaving an ``article`` or ``main`` needs more density, entering one less.  A part with such a
name that turns out to hold the article is a wrapper, and its name is ignored.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_MARKUP = re.compile(
    r"<!--(?:.*?-->|.*\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+'|))*+)(?:>|\Z)",
    re.DOTALL,
)
_ATTRIBUTE = re.compile(r"(?:^|\s)(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]*)))?", re.IGNORECASE)
_NAME = re.compile(r"[a-z0-9]+")

# HTML's element kinds.
_RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes template svg math".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_NOT_TEXT = frozenset("head script style noscript iframe template svg math button select option textarea object embed canvas audio video dialog title xmp noembed noframes input".split())
_FURNITURE = frozenset("nav footer aside header menu form fieldset label".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_BLOCK = frozenset(
    "html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr legend li main menu nav ol p pre search section summary table tbody thead tfoot tr td th caption ul option select".split()
)
_ENDS_P = _BLOCK - frozenset("td th tr tbody thead tfoot caption html body option".split())
_SPACING = frozenset(["br", "img", "td", "th"])
_NEVER_BY_NAME = frozenset(["html", "body", "main"]) | _HEADINGS
# Words in class, id or role that mark what is not article text.
_NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription signup login nav navbar navigation menu menubar submenu breadcrumb breadcrumbs masthead header footer sidebar comment comments disqus replies reply respond social share sharing sharebar related recommended widget toolbar pagination pager copyright complementary contentinfo search dialog alert alertdialog skip".split()
)
# Of those, the ones that mark a comment or an advert.
_STRONG = frozenset("ad ads adv advert adverts advertisement sponsored comment comments disqus replies reply respond".split())
# Words that turn the name they stand beside around (has-comments, ad-free, with-sidebar).
_TURNED = frozenset("has have with without no not free enabled disabled".split())
#: What furniture weighs, headings weigh, and by how much leaving or entering an article changes a density.
_FAINT, _HEAVY, _STEP = 0.02, 8, 5.0
#: Share of the threshold on the body's path that a parent's added part must reach.
_ENOUGH = 0.5
_SAME_LEVEL = {"li": ("li", ("ul", "ol", "menu")), "dt": ("dt dd", ("dl",)), "dd": ("dt dd", ("dl",)), "tr": ("tr td th", ("table", "tbody", "thead", "tfoot")), "td": ("td th", ("tr", "table")), "th": ("td th", ("tr", "table")), "option": ("option", ("select",))}


def _suspicion(tag: str, attributes: str, inside_article: bool) -> int:
    """0: text; 1 or 2: furniture by a weak or strong name, 3: by its tag; 4: no text at all."""
    if tag in _NOT_TEXT:
        return 4
    worst = 3 if tag in _FURNITURE and not (tag == "header" and inside_article) else 0
    for name, a, b, c in _ATTRIBUTE.findall(attributes) if attributes else ():
        value, name = (a or b or c).lower(), name.lower()
        if name == "hidden" or name == "aria-hidden" and value == "true":
            return 4
        if name in ("class", "id", "role") and tag not in _NEVER_BY_NAME:
            for token in value.split():
                words = set(_NAME.findall(token))
                if not _STRONG.isdisjoint(words) and _TURNED.isdisjoint(words):
                    worst = max(worst, 2)
                elif tag != "article" and not _NAMES.isdisjoint(words) and _TURNED.isdisjoint(words):
                    worst = max(worst, 1)
    return worst


class _Page:
    """Nodes in page order, and pieces of text with the block that each stands in."""

    def __init__(self, source: str) -> None:
        self.tag, self.parent, self.last = ["#page"], [-1], [0]
        self.gone, self.faint, self.link, self.article = [False], [False], [False], [False]
        self.suspects: list[tuple[int, int]] = []
        self.pieces: list[tuple[int, int, str]] = []
        self._block, self._open = 0, [0]
        self._read(source)

    def _read(self, source: str) -> None:
        at, lower, skip_to = 0, None, -1
        for m in _MARKUP.finditer(source):
            if m.start() < skip_to:
                continue
            self._text(source[max(at, skip_to) : m.start()])
            at = m.end()
            name = m[2]
            if name is None:
                continue
            tag = name.lower()
            if m[1]:
                self._close(tag)
                continue
            self._start(tag, m[3])
            if tag in _RAW and not m[3].endswith("/"):
                lower = lower if lower is not None else source.lower()
                end = lower.find(f"</{tag}", at)
                skip_to = at = len(source) if end < 0 else end
        if at < len(source) and skip_to < len(source):
            rest = source[max(at, skip_to) :]
            self._text(rest)
        while len(self._open) > 1:
            self._pop()

    def _text(self, text: str) -> None:
        if text and not self.gone[self._open[-1]]:
            self.pieces.append((self._open[-1], self._block, text))

    def _start(self, tag: str, attributes: str) -> None:
        if tag in _ENDS_P:
            self._close_open("p", ("td", "th", "table", "button", "caption", "object"))
        if tag in _SAME_LEVEL:
            for x in _SAME_LEVEL[tag][0].split():
                self._close_open(x, _SAME_LEVEL[tag][1])
        if tag in _BLOCK:
            self._block += 1
        if tag in _VOID:
            if tag in _SPACING:
                self._text(" ")
            return
        up, node = self._open[-1], len(self.tag)
        self.tag.append(tag)
        self.parent.append(up)
        self.last.append(node)
        self.article.append(self.article[up] or tag in ("article", "main"))
        suspicion = _suspicion(tag, attributes, self.article[up])
        self.gone.append(self.gone[up] or suspicion == 4)
        self.faint.append(False)
        if 0 < suspicion < 4 and not self.gone[up]:
            self.suspects.append((node, suspicion))
        self.link.append(self.link[up] or tag == "a")
        if not attributes.endswith("/") or tag not in ("path", "g"):
            self._open.append(node)

    def _pop(self) -> None:
        self.last[self._open.pop()] = len(self.tag) - 1

    def _close_open(self, tag: str, walls: tuple[str, ...]) -> None:
        """Close an open element of this name, unless one of the walls stands before it."""
        for i in range(len(self._open) - 1, 0, -1):
            name = self.tag[self._open[i]]
            if name == tag:
                while len(self._open) > i:
                    self._pop()
                return
            if name in walls:
                return

    def _close(self, tag: str) -> None:
        if tag in _BLOCK:
            self._block += 1
        elif tag == "br":
            self._text(" ")
        walls = () if tag in _BLOCK or tag in _RAW else ("td", "th", "table", "article", "section", "div", "body")
        self._close_open(tag, walls)


def main_text(source: str | None) -> str:
    """The article's text: blocks in page order, one line each; empty if there is none."""
    if not source:
        return ""
    page = _Page(source)
    top = next((i for i in range(len(page.tag)) if page.tag[i] == "body" and not page.gone[i]), 0)
    plain = _Counts(page, top)
    if not plain.chars[plain.top]:
        plain = _Counts(page, 0)
    if not plain.chars[plain.top]:
        return ""
    _judge(page, plain)
    counts = _Counts(page, plain.top)
    if not counts.chars[counts.top]:  # all of it is furniture: there is no article
        return ""
    return _blocks(page, _choose(page, counts), counts)


class _Counts:
    """Characters, linked characters, heading characters, tags and links of each node, furniture apart, and densities."""

    def __init__(self, page: _Page, top: int) -> None:
        n = len(page.tag)
        self.page, self.top = page, top
        self.chars, self.linked, self.heading, self.tags, self.links = ([0] * n for _ in range(5))
        for node, _, text in page.pieces:
            k = len(text) - text.count(" ") if len(text) < 4 else len(text.strip())
            self.chars[node] += k
            if page.link[node]:
                self.linked[node] += k
        for i in range(n - 1, 0, -1):
            if page.gone[i]:
                continue
            self.links[i] += page.tag[i] == "a"
            if page.tag[i] in _HEADINGS:
                self.heading[i] = self.chars[i] - self.linked[i]
            up = page.parent[i]
            if page.faint[i] and not page.faint[up]:
                continue  # furniture has densities of its own and adds nothing to its parent's
            self.tags[up] += 1
            for each in (self.chars, self.linked, self.heading, self.tags, self.links):
                each[up] += each[i]
        self.page_facts = self.chars[top], self.linked[top]
        self.density = [self._of(i) for i in range(n)]
        self.sums = [0.0] * n
        for i in range(1, n):
            self.sums[page.parent[i]] += self.density[i]

    def _of(self, i: int) -> float:
        if self.page.gone[i] or not self.chars[i]:
            return 0.0
        return _density(self.chars[i], self.linked[i], self.tags[i], self.links[i], *self.page_facts) * (_FAINT if self.page.faint[i] else 1.0)

    def added(self, parent: int, inner: int) -> float:
        """Density of what ``parent`` has beside ``inner``."""
        extra = [x[parent] - x[inner] for x in (self.chars, self.linked, self.heading, self.tags, self.links)]
        chars = extra[0] + (_HEAVY - 1) * extra[2]
        return _density(chars, extra[1], max(1, extra[3] - 1), extra[4], *self.page_facts) if extra[0] > 0 else 0.0

    def largest(self) -> int:
        """The node with the largest density sum; the outermost of equals."""
        top, page = self.top, self.page
        inside = range(top, page.last[top] + 1 if top else len(page.tag))
        return max(inside, key=lambda i: (self.sums[i] if self.chars[i] and not page.faint[i] else -1.0, -i))


def _density(chars: int, linked: int, tags: int, links: int, page_chars: int, page_linked: int) -> float:
    """Composite text density: characters for each tag, times a logarithm that falls as links take their share.

    The logarithm's base has a floor, so that tiny nodes do not win.
    """
    plain = max(1, chars - linked)
    base = 1.0 + math.log(math.log(chars * linked / plain + page_linked * chars / max(1, page_chars) + math.e))
    ratio = max(chars / max(1, linked) * max(1, tags) / max(1, links), 1.0 + 1e-9)
    return chars / max(1, tags) * math.log(ratio) / base


def _judge(page: _Page, plain: _Counts) -> None:
    """Mark as faint the suspects that are furniture: all of them, but for wrappers that hold the article."""
    suspects, n = list(page.suspects), len(page.tag)
    fixed = [x for x, s in suspects if page.tag[x] in ("nav", "footer", "aside", "header", "menu", "label") and s == 3]
    under = [False] * n
    for x in fixed:
        under[x : page.last[x] + 1] = [True] * (page.last[x] + 1 - x)
    open_ones = [(x, s) for x, s in suspects if not under[x]]
    signs = [i for i in range(n) if page.tag[i] in ("article", "main", "h1") and not under[i] and not page.gone[i]]
    while open_ones:
        outer, end = [], -1
        for x, s in open_ones:
            if x > end:
                outer.append((x, s))
                end = page.last[x]
        inside = lambda i: any(x <= i <= page.last[x] for x, _ in outer)  # noqa: B023, E731
        text = sum(plain.chars[x] - plain.linked[x] for x, _ in outer)
        whole = plain.chars[plain.top] - plain.linked[plain.top] - sum(plain.chars[x] - plain.linked[x] for x in fixed if not under[page.parent[x]])
        free = any(not inside(i) for i in signs) if signs else whole - text > text / 2
        if free:
            break
        # All that looks like the article lies in suspects: the one with most text, strong names last, is a wrapper.
        keep = max(outer, key=lambda o: (any(o[0] < i <= page.last[o[0]] for i in signs), o[1] != 2, plain.chars[o[0]] - plain.linked[o[0]]))
        if keep[1] == 2 and not any(keep[0] < i <= page.last[keep[0]] for i in signs):
            break
        open_ones.remove(keep)
    for x in [*fixed, *(x for x, _ in open_ones)]:
        page.faint[x : page.last[x] + 1] = [True] * (page.last[x] + 1 - x)


def _choose(page: _Page, counts: _Counts) -> int:
    """The largest density sum, widened along the path to the body while what is added reaches the path's threshold."""
    chosen = counts.largest()
    path = [chosen]
    while path[-1] != counts.top and page.parent[path[-1]] >= 0:
        path.append(page.parent[path[-1]])
    least = min(counts.density[i] for i in path) * _ENOUGH
    for i in path[1:]:
        leaves = any(page.tag[x] in ("article", "main") for x in path[path.index(chosen) : path.index(i)]) and not page.article[i]
        bar = least * _STEP if leaves else least / _STEP**2 if page.article[i] else least
        if counts.added(i, chosen) >= bar:
            chosen = i
    return chosen


def _blocks(page: _Page, chosen: int, counts: _Counts) -> str:
    """Blocks of the chosen subtree, without furniture and lists of links in it."""
    chars, linked, links = counts.chars, counts.linked, counts.links
    end = page.last[chosen] if chosen else len(page.tag) - 1
    menus = {i for i in range(chosen + 1, end + 1) if page.tag[i] in ("ul", "ol", "table", "div", "section") and links[i] >= 3 and 3 * linked[i] > 2 * chars[i]}
    hidden: set[int] = set()
    for i in range(chosen + 1, end + 1):
        if i in menus or page.faint[i] or page.parent[i] in hidden:
            hidden.add(i)
    out, block, parts = [], None, []
    for node, serial, text in page.pieces:
        if not chosen <= node <= end or node in hidden:
            continue
        if serial != block:
            out.append("".join(parts))
            block, parts = serial, []
        parts.append(text)
    out.append("".join(parts))
    lines = (" ".join(html.unescape(x).split()) for x in out if x and not x.isspace())
    return "\n".join(x for x in lines if x)


def extract_text(pages: DataFrame, column: str = "html") -> DataFrame:
    """``pages`` with ``text`` (empty if none) and ``n_chars`` (its code points); every row stays.

    Works row by row on whole pages: nothing is shuffled, a page's size bounds the memory.  A null or
    empty page gives an empty text; unclosed, overlapping and cut-off markup is closed as browsers
    do.  Repeated rows give repeated results.  Columns named ``text`` or ``n_chars`` are replaced.
    """
    kept = [c for c in pages.columns if c not in ("text", "n_chars", column)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [main_text(x.as_py()) for x in batch.column("__html")]
            arrays = [batch.column(c) for c in names] + [pa.array(found, pa.string())]
            yield pa.RecordBatch.from_arrays(arrays, names=[*names, "__text"])

    renamed = pages.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(kept)], F.col(f"`{column}`").alias("__html"))
    names = [f"c{i}" for i in range(len(kept))]
    schema = ", ".join([f"{n} {t}" for n, t in renamed.dtypes if n != "__html"] + ["__text string"])
    done = renamed.mapInArrow(run, schema)
    back = [F.col(f"c{i}").alias(c) for i, c in enumerate(kept)]
    return done.select(*back, F.col("__text").alias("text"), F.char_length("__text").cast("long").alias("n_chars"))
