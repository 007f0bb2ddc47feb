"""Main-text extraction from web pages with a host suffix array.

A page is read into blocks of text, each with a zone from its markup: marked as
furniture (menus, headers, footers, asides, notices, adverts, forms, comments),
inside an article or another content container, or unmarked.  All text of a page, its
article too, forms a token stream; those of a host are concatenated, by groups of about
``pages_per_array`` pages, and sorted into a suffix array.  A run of ``min_run`` or more
tokens that stands on distinct pages is repeated, and what the array does not cover are
the unique runs.  Where a host takes several arrays they meet in two steps.  Seeds, each the
least hash of the shorter grams of a window, name the windows that may stand in another
array, as equal windows have equal seeds; the 64-bit hashes of these windows then meet with
the pages that hold them, and each array gets back those that another page holds too:
results do not depend on how pages are dealt to arrays.

Unmarked text loses its covered runs.  In a marked article their share of the text is
``repeated_share``, and the mark stands against the array: an article may be copied, or
quote what stands elsewhere as an advert or a notice.  With ``cut_marked`` an article loses
the runs of the host's template, runs that stand outside the articles of distinct pages, on
``template_share`` of the host's pages or more, but for headings, which other pages list as
links; that share is a proven bound on what is sent to the arrays of a host.

Defined results: null or empty html gives the empty text; pages that are equal
count as one page in the array, and a repeated row is another page with the same text;
a page almost wholly covered is a copy and keeps its text; a url without a host, or
null, is the host ""; an empty table gives no rows; unclosed tags are text, and pages of
any length are read whole, in linear time.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from html import unescape

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import materialize, small_batches

MIN_RUN, PAGES_PER_ARRAY, COPY_SHARE, TEMPLATE_SHARE = 8, 128, 0.9, 0.01
_HEAVY_LIMIT = 200_000

_MARK = re.compile(
    r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>|<(?P<end>/?)(?P<tag>[A-Za-z][^\s/>]*)(?P<attr>[^>"']*(?:"[^"]*"[^>"']*|'[^']*'[^>"']*)*)>|</?(?P<tag2>[A-Za-z][^\s/>]*)[^>]*>""",
    re.S,
)
_ATTR = re.compile(r"""([A-Za-z:_-]+)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""")
_PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")

# Element and attribute names.
RAW = {"script", "style", "textarea", "title", "noscript", "iframe", "noembed", "noframes", "xmp", "template"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
BLOCK = {
    "address", "article", "aside", "blockquote", "body", "br", "caption", "center", "dd", "details", "dialog", "dir", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form",
    "h1", "h2", "h3", "h4", "h5", "h6", "head", "header", "hgroup", "hr", "html", "li", "main", "menu", "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "tfoot", "thead", "tr", "ul",
}
FURNITURE_TAGS = {"head", "nav", "footer", "aside", "form", "button", "select", "option", "dialog", "menu", "svg", "math", "canvas", "object", "audio", "video", "fieldset", "label", "input"}
FURNITURE_WORDS = {
    "ad", "ads", "adsense", "advert", "advertisement", "advertising", "adverts", "banner", "breadcrumb", "breadcrumbs", "comment", "comments", "consent", "cookie", "cookies", "copyright", "disclaimer", "disqus",
    "foot", "footer", "gdpr", "login", "masthead", "menu", "modal", "nav", "navbar", "navigation", "newsletter", "notice", "notices", "notification", "overlay", "pager", "pagination", "popup", "promo", "promoted",
    "promotion", "recommend", "recommended", "related", "replies", "respond", "search", "share", "sharing", "sidebar", "signup", "skip", "social", "sponsor", "sponsored", "subscribe", "subscription", "toolbar", "topbar", "widget",
}
FURNITURE_ARTICLES = {"ad", "advert", "comment", "comments", "promo", "related", "reply", "sponsored", "teaser"}
FURNITURE_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
CONTENT_NAMES = {"content", "article", "post", "entry", "story", "maincontent", "mainbody", "articlebody", "postbody", "posttext", "entrycontent", "postcontent", "articlecontent", "articletext", "storybody", "maintext"}
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
_CLOSED_BY = {"p": BLOCK - {"br"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "option": {"option"}, "tr": {"tr", "tbody", "tfoot"}}

_CLOSES = {t: [o for o, closers in _CLOSED_BY.items() if t in closers] for t in set().union(*_CLOSED_BY.values())}
_RAW_ENDS = {t: re.compile(rf"</{t}\b[^>]*>", re.I) for t in RAW}
_OPEN_END = re.compile(r"<!--.*|<!\[CDATA\[.*", re.S)

#: Zones: article, main container, named content container, unmarked, furniture.
ARTICLE, MAIN, NAMED, UNMARKED, FURNITURE = "amcnx"


def _zone(tag: str, attrs: str, current: str) -> str:
    """Zone of an element inside a zone; furniture holds for all below it."""
    if current == FURNITURE or tag in FURNITURE_TAGS:
        return FURNITURE
    names, role = set(), ""
    if attrs and attrs.strip("/ "):
        for key, value in _ATTR.findall(attrs):
            key, value = key.lower(), value.strip("\"'")
            if key in ("class", "id"):
                names |= {x.lower() for x in _PART.findall(value)} | {re.sub(r"[^a-z]", "", x.lower()) for x in value.split()}
            elif key == "role":
                role = value.lower()
            elif key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none", value):
                return FURNITURE
            elif key == "itemprop" and value.lower() == "articlebody":
                return ARTICLE
    words = FURNITURE_WORDS if tag not in ("article", "main") else FURNITURE_ARTICLES
    if role in FURNITURE_ROLES or tag not in ("body", "html") and names & words:
        return FURNITURE
    if tag == "header" or "header" in names:
        return current if current in (ARTICLE, MAIN) else FURNITURE
    if tag == "article" or role == "article":
        return ARTICLE
    if current in (ARTICLE, MAIN):
        return current
    if tag == "main" or role == "main":
        return MAIN
    return NAMED if current == NAMED or tag not in ("body", "html") and names & CONTENT_NAMES else current


class _Open:
    """The open elements of a page; finding one costs no more than closing what is above."""

    def __init__(self):
        self.stack: list[tuple[str, str]] = []
        self.count: dict[str, int] = {}
        self.headings = 0
        self.blocks: list[int] = []  # places of elements that stop or end a closing by another tag

    def zone(self) -> str:
        return self.stack[-1][1] if self.stack else UNMARKED

    def push(self, tag: str, zone: str) -> None:
        if tag in BLOCK or tag in _CLOSED_BY:
            self.blocks.append(len(self.stack))
        self.stack.append((tag, zone))
        self.count[tag] = self.count.get(tag, 0) + 1
        self.headings += tag in HEADINGS

    def depth(self, tag: str) -> int:
        """Place of the innermost open element of the tag, -1 if there is none."""
        if not self.count.get(tag):
            return -1
        return next(i for i in range(len(self.stack) - 1, -1, -1) if self.stack[i][0] == tag)

    def cut(self, depth: int) -> None:
        for tag, _ in self.stack[depth:]:
            self.count[tag] -= 1
            self.headings -= tag in HEADINGS
        del self.stack[depth:]
        while self.blocks and self.blocks[-1] >= depth:
            self.blocks.pop()

    def ended_by(self, tag: str) -> int:
        """Place of the element that a start tag ends without an end tag, or -1."""
        for open_ in _CLOSES.get(tag, ()):
            if self.count.get(open_):
                for i in reversed(self.blocks):
                    if self.stack[i][0] == open_:
                        return i
                    if self.stack[i][0] in BLOCK:
                        break
        return -1


def read_blocks(html: str | None) -> list[tuple[str, str]]:
    """(zone, text) of the blocks of a page in order, white space folded; the zone of a
    heading is in upper case."""
    html = html or ""
    blocks: list[tuple[str, str]] = []
    opened = _Open()
    zone, parts, linked, in_link = UNMARKED, [], 0, 0

    def flush():
        nonlocal linked
        text = " ".join("".join(parts).split())
        if text:
            links = zone in (UNMARKED, NAMED) and linked >= 0.8 * len(text)
            heading = opened.headings > 0
            blocks.append((FURNITURE if links else zone.upper() if heading else zone, text))
        parts.clear()
        linked = 0

    at, n, last = 0, len(html), html.rfind(">")
    while at < n:
        # Behind the last ">" only a comment can begin, or text that ends the page.
        mark = _MARK.search(html, at) if at <= last else _OPEN_END.search(html, at)
        stop = mark.start() if mark else n
        if stop > at:
            piece = unescape(html[at:stop])
            parts.append(piece)
            linked += len(piece.strip()) if in_link else 0
        if not mark:
            break
        at = mark.end()
        if mark.re is _OPEN_END:
            if mark[0].startswith("<![CDATA["):
                parts.append(mark[0][9:])
            continue
        tag = (mark["tag"] or mark["tag2"] or "").lower()
        if not tag:
            if mark[0].startswith("<![CDATA["):
                parts.append(mark[0][9:-3] if mark[0].endswith("]]>") else mark[0][9:])
            continue
        if mark["end"] or html.startswith("</", mark.start()):
            depth = opened.depth(tag)
            if tag in BLOCK or depth >= 0 and opened.stack[depth][1] != zone:
                flush()
            if tag == "a":
                in_link = max(0, in_link - 1)
            if depth >= 0:
                opened.cut(depth)
                zone = opened.zone()
            continue
        if tag in RAW:
            close = _RAW_ENDS[tag].search(html, at)
            at = close.end() if close else n
            continue
        while (depth := opened.ended_by(tag)) >= 0:
            flush()
            opened.cut(depth)
            zone = opened.zone()
        inner = _zone(tag, mark["attr"] or "", zone)
        if tag in BLOCK or inner != zone:
            flush()
        elif tag in ("td", "th", "img"):
            parts.append(" ")
        if tag in VOID or (mark["attr"] or "").endswith("/"):
            continue
        if tag == "a":
            in_link += 1
        opened.push(tag, inner)
        zone = inner
    flush()
    return blocks


def _ranked(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The rank of each value among the distinct ones, and an order by it."""
    order = np.argsort(values)
    now = values[order]
    rank = np.empty(len(values), dtype=np.int64)
    rank[order] = np.cumsum(np.concatenate(([0], now[1:] != now[:-1])))
    return rank, order


def repeated_positions(streams: list[np.ndarray], min_run: int = MIN_RUN) -> list[np.ndarray]:
    """For each token stream, which tokens lie in a run of ``min_run`` shared with another.

    The streams are concatenated and their suffixes sorted by prefix doubling as far
    as ``min_run`` tokens; suffixes of equal rank there have a common prefix of that
    length, and a rank that occurs in two streams covers the run at each place.
    """
    lengths = [len(s) for s in streams]
    total = sum(lengths)
    covered = np.zeros(total, dtype=bool)
    if total:
        owner = np.repeat(np.arange(len(streams)), lengths)
        left = np.repeat(np.cumsum(lengths), lengths) - np.arange(total)  # tokens to the end of the stream
        (rank, array), have = _ranked(np.concatenate(streams)), 1
        while have < min_run:
            step = min(have, min_run - have)
            after = np.full(total, -1, dtype=np.int64)
            after[: total - step] = rank[step:]
            after[left <= step] = -1
            rank, array = _ranked(rank * np.int64(total + 1) + after + 1)
            have += step
        array = array[left[array] >= min_run]
        if len(array):
            first = np.flatnonzero(np.concatenate(([True], np.diff(rank[array]) != 0)))
            spread = np.maximum.reduceat(owner[array], first) != np.minimum.reduceat(owner[array], first)
            begin = array[np.repeat(spread, np.diff(np.append(first, len(array))))]
            edge = np.zeros(total + 1, dtype=np.int64)
            np.add.at(edge, begin, 1)
            np.add.at(edge, begin + min_run, -1)
            covered = np.cumsum(edge[:-1]) > 0
    return np.split(covered, np.cumsum(lengths)[:-1]) if streams else []


def _runs_in_block(cover: np.ndarray, min_run: int) -> np.ndarray:
    """Covered words of a block, without ends of runs that reach in from a neighbour."""
    if cover.all() or not cover.any():
        return cover
    edge = np.flatnonzero(np.diff(np.concatenate(([0], cover.astype(np.int8), [0]))))
    out = np.zeros(len(cover), dtype=bool)
    for a, b in zip(edge[::2], edge[1::2], strict=True):
        out[a:b] = b - a >= min_run
    return out


def _marked(zone: str) -> bool:
    return zone.lower() in (ARTICLE, MAIN)


def _level(zones) -> str:
    """The zone that holds a page's main text."""
    here = {z.lower() for z in zones}
    return next((z for z in (ARTICLE, MAIN, NAMED, UNMARKED) if z in here), FURNITURE)


class _Page:
    """The blocks of a page with the hashes of their words, if these are not at hand."""

    def __init__(self, blocks: str, words: np.ndarray | None = None):
        lines = blocks.split("\n") if blocks else []
        self.zones, self.texts = [x[0] for x in lines], [x[1:] for x in lines]
        self.level = _level(self.zones)
        self.sizes = [t.count(" ") + 1 for t in self.texts]
        self.words = K.text_words(" ".join(self.texts)) if words is None else words

    def outside(self) -> np.ndarray:
        """The words outside articles."""
        return self.words[np.repeat(np.array([not _marked(z) for z in self.zones], dtype=bool), self.sizes)]

    def _template_cover(self, template: np.ndarray, min_run: int) -> np.ndarray:
        """Words of the article's blocks that lie in runs of the template within a block."""
        texts = [t for z, t in zip(self.zones, self.texts, strict=True) if z.lower() == self.level]
        sizes = [t.count(" ") + 1 for t in texts]
        cover = np.zeros(sum(sizes), dtype=bool)
        if len(template) and len(cover) >= min_run:
            grams = K.ngram_hashes(K.text_words(" ".join(texts)), min_run)
            at = np.flatnonzero(template[np.minimum(np.searchsorted(template, grams), len(template) - 1)] == grams)
            if len(at):
                block = np.repeat(np.arange(len(sizes)), sizes)
                heading = np.repeat([z.isupper() for z in self.zones if z.lower() == self.level], sizes)
                at = at[(block[at] == block[at + min_run - 1]) & ~heading[at]]
                for i in range(min_run):
                    cover[at + i] = True
        return cover

    def main_text(self, covered: np.ndarray, template: np.ndarray, copy_share: float, min_run: int, cut_marked: bool) -> tuple[str, float]:
        """The text, without covered runs or in an article those of the sorted template, and
        the share of its words in covered runs."""
        if self.level == FURNITURE:
            return "", 0.0
        ends = np.cumsum(self.sizes)
        mine = [i for i, z in enumerate(self.zones) if z.lower() == self.level]
        texts = [self.texts[i] for i in mine]
        share, covers = 0.0, [covered[ends[i] - self.sizes[i] : ends[i]] for i in mine]
        if covered.any():
            covers = [_runs_in_block(c, min_run) for c in covers]
            share = sum(int(c.sum()) for c in covers) / max(sum(len(c) for c in covers), 1)
        if _marked(self.level):
            if not cut_marked:
                return "\n".join(texts), share
            covers = np.split(self._template_cover(template, min_run), np.cumsum([self.sizes[i] for i in mine])[:-1])
        if sum(int(c.sum()) for c in covers) <= copy_share * sum(len(c) for c in covers):
            texts = [" ".join(w for w, c in zip(t.split(" "), cover, strict=True) if not c) if cover.any() else t for t, cover in zip(texts, covers, strict=True)]
        return "\n".join(x for x in texts if x), share


def _by_window(window: np.ndarray, page: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct windows, the page of each, 0 where there are several, and their counts."""
    order = np.argsort(window, kind="stable")
    window, page, count = window[order], page[order], count[order]
    if not len(window):
        return window, page, count
    first = np.flatnonzero(np.concatenate(([True], window[1:] != window[:-1])))
    low, high = np.minimum.reduceat(page, first), np.maximum.reduceat(page, first)
    return window[first], np.where(low == high, low, page.dtype.type(0)), np.add.reduceat(count, first)


def _page_key(blocks: str) -> int:
    """32 bits of what a page says, never 0."""
    return int.from_bytes(hashlib.blake2b(blocks.encode("utf-8", "surrogatepass"), digest_size=4).digest(), "little") | 1


def _outside_windows(blocks: list[str], min_run: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The windows outside the articles of pages: (window, page key, pages with it)."""
    times: dict[str, int] = {}
    for b in blocks:
        times[b] = times.get(b, 0) + 1
    found = [np.unique(K.ngram_hashes(_Page(b).outside(), min_run)) for b in times]
    key = [_page_key(b) for b in times]
    sizes = [len(w) for w in found]
    return _by_window(np.concatenate([*found, np.zeros(0, np.uint64)]), np.repeat(np.array(key, dtype=np.uint32), sizes), np.repeat(np.array(list(times.values()), dtype=np.int64), sizes))


def _packed_windows(batch: pa.RecordBatch, min_run: int) -> list[tuple]:
    """(host, bucket, arrays, n_pages, windows, pages, counts) outside the articles of the
    pages of hosts with several arrays."""
    by: dict[tuple, list[str]] = {}
    for host, arrays, n_pages, html in zip(*(batch.column(c).to_pylist() for c in ("host", "arrays", "n_pages", "html")), strict=True):
        if arrays > 1:
            by.setdefault((host, arrays, n_pages), []).append("\n".join(z + t for z, t in read_blocks(html)))
    rows = []
    for (host, arrays, n_pages), blocks in by.items():
        window, page, count = _outside_windows(blocks, min_run)
        for bucket, part in _buckets(window, arrays):
            rows.append((host, bucket, arrays, n_pages, window[part].tobytes(), page[part].tobytes(), count[part].astype(np.int32).tobytes()))
    return rows


def _buckets(values: np.ndarray, arrays: int) -> list[tuple[int, np.ndarray]]:
    """Places of hashes by bucket; more buckets for hosts of more arrays."""
    bucket = K.mix64(values.astype(np.uint64)) % np.uint64(arrays // 8 + 1)
    order = np.argsort(bucket, kind="stable")
    return [(int(bucket[part[0]]), part) for part in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1) if len(part)]


def _template_windows(frame: pd.DataFrame, template_share: float) -> pd.DataFrame:
    """The windows of the host's template in a bucket."""
    rows = [tuple(np.frombuffer(r[c], dtype=d) for c, d in (("windows", np.uint64), ("pages", np.uint32), ("counts", np.int32))) for _, r in frame.iterrows()]
    window, page, count = _by_window(*(np.concatenate(x) for x in zip(*rows, strict=True)))
    window = window[(page == 0) & (count >= max(2, template_share * int(frame.n_pages.iloc[0])))]
    some = [window.tobytes()] if len(window) else []
    return pd.DataFrame({"host": pd.Series([frame.host.iloc[0]] * len(some), dtype=object), "arrays": np.full(len(some), frame.arrays.iloc[0], dtype=np.int32), "windows": pd.Series(some, dtype=object)})


def _packed(host: str, rows: list[tuple], names: dict) -> pd.DataFrame:
    """Rows of numbers and bytes of a host as a frame."""
    return pd.DataFrame({"host": pd.Series([host] * len(rows), dtype=object)} | {n: pd.Series([r[i] for r in rows], dtype=t) for i, (n, t) in enumerate(names.items())})


def _unpacked(frame: pd.DataFrame) -> list[str]:
    """The distinct pages of an array."""
    return [zlib.decompress(b).decode() for b in dict.fromkeys(frame.blocks)]


def _streams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of the words of pages, one page after the other, and the words of each."""
    flat = [" ".join([line[1:] for line in b.split("\n")]) if b else "" for b in texts]
    return K.text_words(" ".join(t for t in flat if t)), np.array([t.count(" ") + 1 if t else 0 for t in flat], dtype=np.int64)


def _starts(sizes: np.ndarray, min_run: int) -> np.ndarray:
    """Where windows begin that end in their page."""
    return np.flatnonzero(np.repeat(np.cumsum(sizes), sizes) - np.arange(sizes.sum()) >= min_run)


def _among(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are in a sorted array."""
    return known[np.minimum(np.searchsorted(known, values), len(known) - 1)] == values if len(known) else np.zeros(len(values), dtype=bool)


def _seeds(words: np.ndarray, min_run: int) -> np.ndarray:
    """For each window 32 bits of the least hash of its grams, which are up to three words shorter."""
    n = len(words) - min_run + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    grams = K.ngram_hashes(words, max(1, min_run - 3))
    out = grams[:n]
    for i in range(1, min(3, min_run - 1) + 1):
        out = np.minimum(out, grams[i : i + n])
    return (K.mix64(out) >> np.uint64(32)).astype(np.uint32)


def _steps(values: np.ndarray) -> bytes:
    """Sorted numbers by their differences, of which the high bytes are mostly zero."""
    return zlib.compress(np.diff(values, prepend=np.uint32(0)).view(np.uint8).reshape(-1, 4).T.tobytes(), 1)


def _from_steps(packed: bytes) -> np.ndarray:
    steps = np.frombuffer(zlib.decompress(packed), dtype=np.uint8).reshape(4, -1).T
    return np.cumsum(np.ascontiguousarray(steps).view(np.uint32).ravel(), dtype=np.uint32)


def _array_seeds(frame: pd.DataFrame, min_run: int) -> pd.DataFrame:
    """(host, bucket, array, seeds) of one of several arrays of a host; buckets are ranges."""
    rows, arrays = [], int(frame.arrays.iloc[0])
    if arrays > 1:
        words, sizes = _streams(_unpacked(frame))
        seeds = np.unique(_seeds(words, min_run)[_starts(sizes, min_run)])
        parts = arrays // 8 + 1
        bounds = np.searchsorted(seeds, (np.arange(1, parts, dtype=np.uint64) << np.uint64(32)) // np.uint64(parts))
        rows = [(i, int(frame["array"].iloc[0]), _steps(part)) for i, part in enumerate(np.split(seeds, bounds)) if len(part)]
    return _packed(frame.host.iloc[0], rows, {"bucket": np.int32, "array": np.int32, "seeds": object})


def _common_seeds(frame: pd.DataFrame) -> pd.DataFrame:
    """For each array its seeds that another array has too."""
    seeds = [_from_steps(x) for x in frame.seeds]
    every = np.sort(np.concatenate(seeds))
    common = np.unique(every[1:][every[1:] == every[:-1]])
    mine = [(int(a), x[_among(x, common)]) for a, x in zip(frame["array"], seeds, strict=True)]
    return _packed(frame.host.iloc[0], [(a, _steps(x)) for a, x in mine if len(x)], {"array": np.int32, "seeds": object})


def _joined(packed, kind) -> np.ndarray:
    return np.concatenate([*(np.frombuffer(x, dtype=kind) for x in packed), np.zeros(0, kind)])


def _array_windows(frame: pd.DataFrame, common: pd.DataFrame, min_run: int) -> pd.DataFrame:
    """(host, bucket, array, windows, pages) of the windows with such seeds."""
    rows = []
    if len(frame) and len(common):
        texts = _unpacked(frame)
        words, sizes = _streams(texts)
        at = _starts(sizes, min_run)
        at = at[_among(_seeds(words, min_run)[at], np.sort(np.concatenate([_from_steps(x) for x in common.seeds])))]
        key = np.array([_page_key(b) for b in texts], dtype=np.uint32)
        window, page, _ = _by_window(K.ngram_hashes(words, min_run)[at], np.repeat(key, sizes)[at], np.ones(len(at), dtype=np.int64))
        rows = [(bucket, int(frame["array"].iloc[0]), window[part].tobytes(), page[part].tobytes()) for bucket, part in _buckets(window, int(frame.arrays.iloc[0]))] if len(at) else []
    return _packed(frame.host.iloc[0] if rows else "", rows, {"bucket": np.int32, "array": np.int32, "windows": object, "pages": object})


def _shared_windows(frame: pd.DataFrame) -> pd.DataFrame:
    """For each array its windows that stand on distinct pages of the host."""
    windows, pages = ([np.frombuffer(x, dtype=d) for x in frame[c]] for c, d in (("windows", np.uint64), ("pages", np.uint32)))
    window, page, _ = _by_window(np.concatenate(windows), np.concatenate(pages), np.ones(sum(map(len, windows)), dtype=np.int64))
    rows = [(int(a), w[_among(w, window[page == 0])].tobytes()) for a, w in zip(frame["array"], windows, strict=True)]
    return _packed(frame.host.iloc[0], [r for r in rows if r[1]], {"array": np.int32, "windows": object})


def _extract_group(frame: pd.DataFrame, shared: pd.DataFrame, min_run: int, copy_share: float, template_share: float, cut_marked: bool) -> pd.DataFrame:
    if not len(frame):
        return pd.DataFrame({"page_id": [], "url": pd.Series([], dtype=object), "text": pd.Series([], dtype=object), "n_chars": [], "repeated_share": []})
    once: dict[bytes, int] = {}
    which = [once.setdefault(b, len(once)) for b in frame.blocks]
    texts = _unpacked(frame)
    words, sizes = _streams(texts)
    pages = [_Page(b, w) for b, w in zip(texts, np.split(words, np.cumsum(sizes)[:-1]), strict=True)]
    cover = np.concatenate(repeated_positions([p.words for p in pages], min_run))
    elsewhere = np.sort(_joined(shared.windows[~shared.template.astype(bool)], np.uint64))
    if len(elsewhere):
        at = _starts(sizes, min_run)
        at = at[_among(K.ngram_hashes(words, min_run)[at], elsewhere)]
        for i in range(min_run):
            cover[at + i] = True
    covered = np.split(cover, np.cumsum(sizes)[:-1])
    template = np.unique(_joined(shared.windows[shared.template.astype(bool)], np.uint64))
    if cut_marked and int(frame.arrays.iloc[0]) == 1:
        window, page, count = _outside_windows([texts[w] for w in which], min_run)
        template = window[(page == 0) & (count >= max(2, template_share * len(frame)))]  # sorted, as windows are
    got = [p.main_text(c, template, copy_share, min_run, cut_marked) for p, c in zip(pages, covered, strict=True)]
    got = [got[w] for w in which]
    return pd.DataFrame({"page_id": frame.page_id.array, "url": frame.url.astype(object).array, "text": [t for t, _ in got], "n_chars": [len(t) for t, _ in got], "repeated_share": [s for _, s in got]})


def extract(
    pages: DataFrame,
    id_col: str = "page_id",
    url_col: str = "url",
    html_col: str = "html",
    min_run: int = MIN_RUN,
    pages_per_array: int = PAGES_PER_ARRAY,
    copy_share: float = COPY_SHARE,
    template_share: float = TEMPLATE_SHARE,
    cut_marked: bool = False,
) -> DataFrame:
    """(page_id, url, text, n_chars, repeated_share), one row for each page."""
    host = F.coalesce(F.lower(F.regexp_extract(F.col(url_col), r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]+)", 1)), F.lit(""))
    rows = small_batches(pages).select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).alias("html"), host.alias("host"))
    heavy = rows.groupBy("host").count().filter(F.col("count") > pages_per_array).select("host", F.ceil(F.col("count") / pages_per_array).cast("int").alias("arrays"), F.col("count").alias("n_pages"))
    hosts = heavy.limit(_HEAVY_LIMIT + 1).count()
    if hosts <= _HEAVY_LIMIT:
        heavy = F.broadcast(heavy)  # a checked number of short rows; beyond it a plain join
    rows = rows.join(heavy, "host", "left").withColumn("arrays", F.coalesce("arrays", F.lit(1))).withColumn("array", F.pmod(F.xxhash64("page_id", "url"), F.col("arrays")).cast("int"))

    def outside(batches):
        kinds = (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
        for batch in batches:
            found = _packed_windows(batch, min_run)
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in found], k) for i, k in enumerate(kinds)], ["host", "bucket", "arrays", "n_pages", "windows", "pages", "counts"])

    def parse(batches):
        names = ["page_id", "url", "host", "arrays", "array"]
        for batch in batches:
            lines = [zlib.compress("\n".join(z + t for z, t in read_blocks(html.as_py())).encode(), 6) for html in batch.column("html")]
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in names] + [pa.array(lines, pa.binary())], [*names, "blocks"])

    # Read and dealt to the arrays once: the three steps below take the same exchange.
    parsed = rows.select("page_id", "url", "host", "arrays", "array", "html").mapInArrow(parse, "page_id long, url string, host string, arrays int, array int, blocks binary").groupBy("host", "array")
    shared = pages.sparkSession.createDataFrame([], "host string, array int, template boolean, windows binary")
    if hosts:
        seeds = parsed.applyInPandas(lambda frame: _array_seeds(frame, min_run), "host string, bucket int, array int, seeds binary")
        common = seeds.groupBy("host", "bucket").applyInPandas(_common_seeds, "host string, array int, seeds binary")
        windows = parsed.cogroup(common.groupBy("host", "array")).applyInPandas(lambda frame, more: _array_windows(frame, more, min_run), "host string, bucket int, array int, windows binary, pages binary")
        shared = windows.groupBy("host", "bucket").applyInPandas(_shared_windows, "host string, array int, windows binary").select("host", "array", F.lit(False).alias("template"), "windows")
    if hosts and cut_marked:
        windows = rows.filter("arrays > 1").select("host", "arrays", "n_pages", "html").mapInArrow(outside, "host string, bucket int, arrays int, n_pages long, windows binary, pages binary, counts binary")
        # The template of a host is bounded by 1 / template_share times the words of a page.
        template = windows.groupBy("host", "bucket").applyInPandas(lambda frame: _template_windows(frame, template_share), "host string, arrays int, windows binary")
        template = materialize(template, "windows").groupBy("host", "arrays").agg(F.collect_list("windows").alias("all"))
        template = template.select("host", F.explode(F.expr("sequence(0, arrays - 1)")).alias("array"), F.lit(True).alias("template"), F.expr("aggregate(all, cast('' as binary), (x, y) -> concat(x, y))").alias("windows"))
        shared = shared.unionByName(template)
    return parsed.cogroup(shared.groupBy("host", "array")).applyInPandas(
        lambda frame, more: _extract_group(frame, more, min_run, copy_share, template_share, cut_marked), "page_id long, url string, text string, n_chars long, repeated_share double"
    )
