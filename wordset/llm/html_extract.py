"""Main text of web pages by tag-path ratios.

A page is read as a run of text nodes, each with its root-to-leaf tag path. Per path, text length and punctuation are
summed over its nodes: long texts with many sentence marks are content, short ones without are not. The two
ratios are smoothed along the blocks of a container, so that a short paragraph between long ones gains and a lone caption loses, fused by
multiplication, and averaged over the path. Paths that reach a share of the page's deviation are content, and their blocks are selected.

What belongs to the selected blocks stays with them: all of a container that holds all of them and hardly anything else, items, cells,
captions and code in their container, short paragraphs of a container that is mostly content, what stands between two of them in one container,
and headings before them. Beside an ``article`` or ``main`` that holds most of the selected text nothing is selected.

Marked parts (menus, headers, footers, sidebars, notices, adverts, forms, comments, scripts, styles) are known by
element name, role, or a word of their class or id, and never take part. A word marks by its place in a class or id (``sidebar``, ``post-footer``, not
``has-sidebar``), never what contains the article, and weak words give way to scores like the article's.

Edge cases: null and empty pages and an empty table have no text; very long pages are read in one pass, in time and memory in proportion to their length;
other columns of the table play no part, whatever their names; unclosed and crossed tags are closed as browsers do for blocks;
text outside any element counts; a page whose text is all in parts marked by name or role has an empty text; repeated rows are
answered each.
"""

from __future__ import annotations

import html
import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.functions.worker import on_worker

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*+(?:>|\Z)|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*+)(?P<attrs>(?:[^>\"']|\"[^\"]*+\"|'[^']*+')*+)>|(?P<text>[^<]++|<)",
    re.S,
)
ATTR = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe object noframes canvas audio video annotation annotation-xml".split())
#: Elements of formulas and drawings whose texts are words of their own.
PIECES = frozenset("mi mn mo ms mtext text tspan desc".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html li main menu nav ol option p pre section select summary table tbody td tfoot th thead tr ul".split()
)
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table", "tr"}, "th": {"table", "tr"}, "option": {"select"}}
MARKED = frozenset("nav header footer aside form button select menu dialog head label fieldset".split())
MARKED_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
#: Words of a class or id that mark a part as something other than the article, as the whole token, its first or its last part.
STRONG = frozenset(
    """ad ads advert adverts advertisement advertising sponsor sponsored promo promoted nav navbar submenu breadcrumb breadcrumbs masthead widget widgets disqus
    cookie cookies gdpr popup newsletter signup login sharing toolbar pagination pager""".split()
)
#: Words that mark as the whole token or its last part, or before a mere number or place.
WEAK = frozenset(
    """banner promotion navigation menu header footer sidebar aside related recommended recommendations discussion consent notice notices alert modal overlay subscribe subscription
    share social copyright legal form search tags skip comment comments reply replies respond""".split()
)
#: Weak words of texts by readers, which read like an article.
READERS = frozenset("comment comments reply replies respond discussion".split())
#: Parts after which a word tells what an element has, not what it is, and parts that only place or count it.
HAS = frozenset("has have with no not without show hide under inner".split())
PLACE = re.compile(r"\d+|left|right|top|bottom|main|primary|secondary|list|area|box|wrapper|wrap|container|block|section|widget|bar|links|buttons|item|items|inner|outer|content")
ANCHORED = frozenset("section h1 h2 h3 h4 h5 h6".split())
#: Elements that can be an article's root; others are its paragraphs, lists, rows and words.
CONTAINERS = frozenset("html body main article section div td center".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Parts of a text that are short and without marks by nature.
ITEMS = frozenset("li dt dd td th caption figcaption pre code address summary".split())
STOPS = re.compile(r"[.,;:!?…]")
#: Share of the standard deviation of fused scores that a content node reaches.
LEVEL = 0.5
#: Share of the article's mean score from which a weak word other than readers' is overruled.
OVERRULE = 0.5
#: Of the ways in which an element is marked: not at all, by weak words, by readers' words, beyond doubt.
NOT, BY_WORD, BY_READERS, SURELY = range(4)


def _by_word(token: str) -> int:
    parts = [w.lower() for w in re.split(r"[-_]+|(?<=[a-z])(?=[A-Z])", token) if w]
    if not parts or not HAS.isdisjoint(parts):
        return NOT
    ends = {parts[0], parts[-1]}
    if not STRONG.isdisjoint(ends):
        return BY_READERS
    while len(parts) > 1 and PLACE.fullmatch(parts[-1]):
        parts.pop()
    return NOT if parts[-1] not in WEAK else BY_READERS if parts[-1] in READERS else BY_WORD


def _is_marked(name: str, attrs: str) -> int:
    if name in MARKED:
        return SURELY
    if name in ("html", "body", "main", "article") or "=" not in attrs:
        return SURELY if "hidden" in attrs.split() else NOT
    found = NOT
    for key, *values in ATTR.findall(attrs):
        value = next(filter(None, values), "")
        key = key.lower()
        if key == "role" and value.lower() in MARKED_ROLES or key == "aria-hidden" and value.lower() == "true":
            return SURELY
        if key == "class" or key == "id" and name not in ANCHORED:
            found = max([found, *map(_by_word, value.split())])
        if key == "style" and re.search(r"display\s*:\s*none", value, re.I):
            return SURELY
    return SURELY if "hidden" in attrs.split() else found


class _Page:
    """Blocks of text in page order, each with the open elements it stands in."""

    def __init__(self, source: str):
        self.blocks: list[tuple[str, tuple[int, ...], list[tuple[str, int, int]]]] = []
        self.stack: list[tuple[str, int]] = []  # name and number of each open element
        self.marked = 0  # depth of the outermost marked element, 0 if none
        self.names: list[str] = []
        self.doubtful: dict[int, int] = {}  # elements marked by a word, and how
        self.articles: list[set[int]] = []  # for each article and main: the doubtful elements it stands in
        self.text: list[str] = []
        self.nodes: list[tuple[str, int, int]] = []  # of the open block: path, length, marks
        self.at: tuple[int, ...] = ()
        self._read(source)
        self._flush()

    def _flush(self) -> None:
        if self.text:
            if said := " ".join("".join(self.text).split()):
                self.blocks.append((said, self.at, self.nodes))
            self.text, self.nodes = [], []

    def _add(self, raw: str, unescape: bool = True) -> None:
        if self.marked:
            return
        said = html.unescape(raw) if unescape and "&" in raw else raw
        if not self.text:
            self.at = tuple(k for _, k in self.stack)
        self.text.append(said)
        if not said.isspace():
            self.nodes.append((">".join(n for n, _ in self.stack), len(said), len(STOPS.findall(said))))

    def _pop_to(self, depth: int) -> None:
        if any(n in BLOCK for n, _ in self.stack[depth:]):
            self._flush()
        del self.stack[depth:]
        if self.marked > depth:
            self.marked = 0

    def _open(self, name: str, attrs: str) -> None:
        if name in BLOCK:
            self._flush()
            for depth in range(len(self.stack) - 1, -1, -1):  # a block ends an open paragraph
                if (n := self.stack[depth][0]) == "p":
                    self._pop_to(depth)
                    break
                if n in BLOCK:
                    break
        if name in CLOSES:
            for depth in range(len(self.stack) - 1, -1, -1):
                n = self.stack[depth][0]
                if n in CLOSES[name]:
                    self._pop_to(depth)
                elif n in SCOPE[name]:
                    break
        if name in VOID:
            if name == "br" and self.text:
                self.text.append(" ")
            return
        if attrs.rstrip().endswith("/") and any(n in ("svg", "math") for n, _ in self.stack):
            return
        self.names.append(name)
        self.stack.append((name, len(self.names)))
        if not self.marked and (how := _is_marked(name, attrs)):
            if how == SURELY:
                self.marked = len(self.stack)
            else:
                self.doubtful[len(self.names)] = how
        if not self.marked and name in ("article", "main"):
            self.articles.append({k for _, k in self.stack if k in self.doubtful})

    def _close(self, name: str) -> None:
        if name in PIECES and self.text:
            self.text.append(" ")
        for depth in range(len(self.stack) - 1, -1, -1):
            if self.stack[depth][0] == name:
                self._pop_to(depth)
                return
            if name not in BLOCK and self.stack[depth][0] in BLOCK:
                return  # a stray end of an inline element

    def _read(self, source: str) -> None:
        at, find = 0, TOKEN.match
        low = None
        while at < len(source) and (m := find(source, at)):
            at = m.end()
            if (said := m["text"]) is not None:
                self._add(said)
            elif (name := m["name"]) is not None:
                name = name.lower()
                if m["end"]:
                    self._close(name)
                elif name in RAW:
                    if not m["attrs"].rstrip().endswith("/"):
                        low = source.lower() if low is None else low
                        stop = low.find(f"</{name}", at) if len(low) == len(source) else _find_end(source, name, at)
                        at = len(source) if stop < 0 else source.find(">", stop) + 1 or len(source)
                else:
                    self._open(name, m["attrs"])
            elif m["cdata"] is not None:
                self._add(m["cdata"], False)


def _find_end(source: str, name: str, at: int) -> int:
    m = re.compile(f"</{name}", re.I).search(source, at)
    return m.start() if m else -1


def _ratios(blocks) -> tuple[np.ndarray, np.ndarray]:
    """Mean text and marks of a block's paths, by block."""
    length, marks, count = defaultdict(int), defaultdict(int), defaultdict(int)
    for _, _, nodes in blocks:
        for path, n, k in nodes:
            length[path] += n
            marks[path] += k
            count[path] += 1
    text = np.array([sum(n * length[p] / count[p] for p, n, _ in nodes) / sum(n for _, n, _ in nodes) for _, _, nodes in blocks])
    stops = np.array([sum(n * marks[p] / count[p] for p, n, _ in nodes) / sum(n for _, n, _ in nodes) for _, _, nodes in blocks])
    return text, stops


def _unmarked(page: _Page) -> list:
    """Blocks that aren't in parts marked by a word; a mark doesn't hold for what contains the article, and a weak one not for what
    scores like the article."""
    blocks, doubtful = page.blocks, dict(page.doubtful)
    if not doubtful or not blocks:
        return blocks
    size: dict[int, int] = defaultdict(int)
    for said, at, _ in blocks:
        for k in at:
            size[k] += len(said)
    total = sum(len(said) for said, _, _ in blocks)
    for k in page.doubtful:
        if all(k in around for around in page.articles) if page.articles else 10 * size[k] >= 9 * total:
            del doubtful[k]
    plain = [doubtful.keys().isdisjoint(at) for _, at, _ in blocks]
    if all(plain) or not any(plain):
        return [b for b, p in zip(blocks, plain, strict=True) if p]
    text, stops = _ratios(blocks)
    score = text * (1 + stops)
    weight = np.array([len(said) for said, _, _ in blocks])
    mean = float(np.average(score[plain], weights=weight[plain]))
    for k in [k for k, how in doubtful.items() if how == BY_WORD]:
        within = [k in at for _, at, _ in blocks]
        if any(within) and np.average(score[within], weights=weight[within]) >= OVERRULE * mean:
            del doubtful[k]
    return [b for b in blocks if doubtful.keys().isdisjoint(b[1])]


def _near(at: tuple[int, ...], names: list[str]) -> int:
    """The innermost container of a block that isn't a cell."""
    return next((k for k in reversed(at) if names[k - 1] in CONTAINERS and names[k - 1] != "td"), 0)


def path_scores(blocks, names: list[str]) -> np.ndarray:
    """For each block the score of its tag paths: text and marks per node of the path, smoothed among the blocks of a container,
    multiplied, and averaged over the path."""
    text_ratio, mark_ratio = _ratios(blocks)
    own: dict[int, list[int]] = defaultdict(list)
    for i, (_, at, _) in enumerate(blocks):
        own[next((k for k in reversed(at) if names[k - 1] in CONTAINERS), 0)].append(i)
    fused = np.zeros(len(blocks))
    for i in own.values():
        fused[i] = _smooth(text_ratio[i]) * (1 + _smooth(mark_ratio[i]))
    total, weight = defaultdict(float), defaultdict(int)
    for (_, _, nodes), f in zip(blocks, fused.tolist(), strict=True):
        for path, n, _ in nodes:
            total[path] += n * f
            weight[path] += n
    return np.array([sum(n * total[p] / weight[p] for p, n, _ in nodes) / sum(n for _, n, _ in nodes) for _, _, nodes in blocks])


def selected(blocks, names: list[str]) -> np.ndarray:
    """Which blocks have paths that reach the threshold."""
    score = path_scores(blocks, names)
    return score >= LEVEL * score.std()


def content_blocks(blocks, names: list[str]) -> list[bool]:
    """Which blocks are content: those whose paths reach the threshold, and what belongs to them."""
    chosen = selected(blocks, names)
    size = np.array([len(t) for t, _, _ in blocks])
    kind = [{names[k - 1] for k in at} for _, at, _ in blocks]
    for name in ("main", "article"):  # what stands beside the article is no part of it
        within = np.array([name in k for k in kind])
        if 2 * size[chosen & within].sum() > size[chosen].sum():
            chosen &= within
            break
    keep = chosen.copy()
    linked = np.array([all("a" in p.split(">") for p, _, _ in nodes) for _, _, nodes in blocks])
    near = [_near(at, names) for _, at, _ in blocks]
    # a container that holds all content and hardly anything else is content as a whole
    alike = set.intersection(*(set(blocks[i][1]) for i in np.flatnonzero(chosen)))
    root = max((k for k in alike if names[k - 1] in CONTAINERS), default=0)
    if root and names[root - 1] not in ("html", "body"):
        inside = np.array([root in at for _, at, _ in blocks])
        if 10 * size[chosen].sum() >= 9 * size[inside & ~linked].sum():
            keep |= inside & ~linked
    # items, cells, captions and code have low ratios by nature and belong to the content of their container; so do short
    # paragraphs where most of the container's text is content
    held, full = defaultdict(int), defaultdict(int)
    for home, n, c, link in zip(near, size.tolist(), chosen.tolist(), linked.tolist(), strict=True):
        held[home] += n * c
        full[home] += n * (not link)
    keep |= np.array([held[home] > 0 and (not k.isdisjoint(ITEMS) or 2 * held[home] >= full[home]) for k, home in zip(kind, near, strict=True)]) & ~linked
    # so does what stands between two blocks of content of one container, and the headings before content
    last: dict[int, int] = {}
    for i in np.flatnonzero(keep).tolist():
        if (before := last.get(near[i])) is not None:
            for j in range(before + 1, i):
                keep[j] = keep[j] or near[i] in blocks[j][1] or not near[i]
        last[near[i]] = i
    for i in range(len(blocks) - 2, -1, -1):
        keep[i] = keep[i] or keep[i + 1] and not kind[i].isdisjoint(HEADINGS)
    return keep.tolist()


def extract(source: str | None) -> str:
    page = _Page(source or "")
    blocks = _unmarked(page)
    if not blocks:
        return ""
    return "\n\n".join(t for (t, _, _), k in zip(blocks, content_blocks(blocks, page.names), strict=True) if k)


def _smooth(x: np.ndarray) -> np.ndarray:
    """Weighted mean of each value and its two neighbours on either side."""
    kernel = np.array([1, 2, 4, 2, 1.0])
    pad = np.convolve(x, kernel)[2 : len(x) + 2]
    return pad / np.convolve(np.ones(len(x)), kernel)[2 : len(x) + 2]


def extract_batches(batches):
    for b in batches:
        texts = [extract(h.as_py()) for h in b.column("html")]
        yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], ["page_id", "url", "text", "n_chars"])


def main_text(pages: DataFrame) -> DataFrame:
    """``page_id, url, text, n_chars`` of every page."""
    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), "html").mapInArrow(on_worker(__name__, "extract_batches"), "page_id long, url string, text string, n_chars long")
