"""Main text of web pages by differencing each page with its nearest neighbours on the same host.

A page becomes a sequence of text lines, one per block element.  Pages of a host are put in order of URL, and each is
aligned by a longest common subsequence of lines with the nearest different ones, up to ``beside`` on each side.
Lines in common are the site's, not the page's, and are deleted:

* a line outside the main element goes if any neighbour has it;
* a line inside an article or main element goes if at least three neighbours, and all that have a say, have it, since
  articles also quote lines of each other.  Neighbours with half of this page's main text are copies and have no say;
* a line in an element whose class names may or may not mean layout (``search``, ``sidebar``) goes, outside the main
  element, if a neighbour has a line at the same place, as the wording of such boxes differs from page to page.

Differencing cannot find layout whose wording and place are the page's own (a menu of its topics, an advert), so
elements and class names that stand for menus, headers, footers, notices, adverts, forms and comments go without a
neighbour's say.  Names never count on ``html`` and ``body``, nor on a main element with half of the page's text and
on what lies around it.  ``extract(..., names=False)`` leaves everything to differencing.

Plan: borders of slices come from the order of URLs alone: every ``slice_pages``-th page, or a ten-thousandth of
all where there are more, so there are at most ten thousand, which are broadcast.  One pass parses pages; lines travel
compressed, once, to their slice, keys alone also to the neighbouring slice from ``halo`` pages around a border.  Each
slice is a task of equal size, whatever hosts and paths there are, and holds a few pages at a time.

Defined results: null or empty html gives the empty text; a page without a different neighbour loses layout only;
null urls form a host; a neighbour with exactly the same lines is a copy and the next one counts; an unclosed element
ends with the element around it, an unclosed script or comment with the page; a tag that never ends goes up to the
next tag or line; beyond sixteen tags with unbalanced quotes, quotes are not minded.  Repeated rows get equal texts.
"""

from __future__ import annotations

import html
import re
from bisect import bisect_left, bisect_right
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertexlog.llm.common import ordinal

_TAG = re.compile(r"<(/?)([a-z][^\s/>]*)", re.I)
_REST = re.compile(r"(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+>")
_UNFINISHED = re.compile(r"[^<\n]*")
_NAMES = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|/|$)|display\s*:\s*none|aria-hidden\s*=\s*[\"']?true", re.I)
_PARTS = re.compile(r"[^a-z0-9]+")

#: Element names and name parts by what they hold; fixed values.
RAW = frozenset("script style noscript template svg iframe textarea select".split())
RAW_TO_THE_END = frozenset("script style noscript iframe textarea".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section summary table tbody tfoot thead title tr ul".split()
)
LAYOUT = frozenset("aside button dialog footer form head menu nav title".split())
MAIN = frozenset("article main".split())
LAYOUT_NAMES = frozenset(
    "ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments complementary consent contentinfo cookie"
    " cookies dialog disclaimer footer gdpr login masthead menu modal nav navbar navigation newsletter notice notices pager pagination popup"
    " promo promoted promotion related sponsor sponsored subscribe subscription toolbar widget".split()
)
DOUBTFUL_NAMES = frozenset("search share sharing sidebar social".split())
MAIN_NAMES = frozenset("article main".split())
_ENDS_P = BLOCK - {"button", "caption", "option"}

TEXT, LAYOUT_LINE, OWN, DOUBT = 0, 1, 2, 3  # kept unless shared, always deleted, kept unless most share it, deleted if its place is shared


def pieces(page: str) -> Iterator[tuple[str | None, str, bool]]:
    """(None, text, False) and (element name, attributes, whether it closes) in page order, in linear time."""
    at, n, last, quotes = 0, len(page), page.rfind(">"), 16
    unclosed: set[str] = set()
    while at < n:
        lt = page.find("<", at)
        if lt != at:
            yield None, page[at:lt] if lt >= 0 else page[at:], False
        if lt < 0:
            return
        tag = _TAG.match(page, lt)
        if tag is None:
            if page.startswith("<!--", lt):
                end = page.find("-->", lt + 4)
                at = n if end < 0 else end + 3
            elif page[lt + 1 : lt + 2] in ("!", "?", "/"):
                at = page.find(">", lt) + 1 if lt < last else _UNFINISHED.match(page, lt + 1).end()
            else:
                yield None, "<", False
                at = lt + 1
            continue
        if tag.end() > last:
            at = _UNFINISHED.match(page, tag.end()).end()
            continue
        whole = _REST.match(page, tag.end()) if quotes else None
        quotes -= bool(quotes and whole is None)
        at = whole.end() if whole else page.find(">", tag.end()) + 1
        name, attributes = tag.group(2).lower(), page[tag.end() : at - 1]
        if name not in RAW or tag.group(1):
            yield name, attributes, bool(tag.group(1))
            continue
        if name == "svg" and attributes.endswith("/"):
            continue
        close = None if name in unclosed else re.compile(f"</{name}", re.I).search(page, at)
        if close:
            end = page.find(">", close.end())
            at = n if end < 0 else end + 1
            yield None, " ", False
        else:
            unclosed.add(name)
            if name in RAW_TO_THE_END:
                return


class _Page:
    """Elements as they open and close, and the lines of text in them."""

    def __init__(self) -> None:
        self.parent, self.names, self.by_tag, self.by_name, self.main, self.doubt, self.place = [-1], [""], [False], [False], [False], [False], [0]
        self.stack, self.where, self.lines, self.words = [0], {}, [], []

    def open(self, name: str, attributes: str) -> None:
        up = self.stack[-1]
        by_tag, by_name, main, doubt = name in LAYOUT, False, name in MAIN, False
        if "=" in attributes and name not in ("html", "body"):
            for key, a, b, c in _NAMES.findall(attributes):
                parts = {p for p in _PARTS.split((a or b or c).lower()) if p}
                if not parts.isdisjoint(LAYOUT_NAMES) or key.lower() == "role" and not parts.isdisjoint(DOUBTFUL_NAMES):
                    by_name = True
                elif not parts.isdisjoint(DOUBTFUL_NAMES):
                    doubt = True
                elif key.lower() == "role" and not parts.isdisjoint(MAIN_NAMES):
                    main = True
        if attributes and _HIDDEN.search(attributes):
            by_tag = True
        for column, value in ((self.parent, up), (self.names, name), (self.by_tag, by_tag), (self.by_name, by_name), (self.main, main), (self.doubt, doubt)):
            column.append(value)
        self.place.append(xxhash.xxh64_intdigest(name, self.place[up]))
        self.where.setdefault(name, []).append(len(self.stack))
        self.stack.append(len(self.parent) - 1)

    def close(self, name: str, walls: tuple[str, ...] = ()) -> None:
        """Close the innermost element of a name, unless a wall stands before it."""
        open_at = self.where.get(name)
        if open_at and all(not self.where.get(w) or self.where[w][-1] < open_at[-1] for w in walls):
            for element in reversed(self.stack[open_at[-1] :]):
                self.where[self.names[element]].pop()
                self.stack.pop()

    def flush(self) -> None:
        if self.words:
            text = " ".join(html.unescape("".join(self.words)).split())
            self.words.clear()
            if text:
                self.lines.append((self.stack[-1], text))

    def judged(self, names: bool) -> list[tuple[int, int, str]]:
        """(kind, place, text) of every line."""
        n = len(self.parent)
        chars = [0] * n
        for element, text in self.lines:
            chars[element] += len(text)
        for e in range(n - 1, 0, -1):
            chars[self.parent[e]] += chars[e]
        certain = [False] * n  # main elements with half of the page's text, and what lies around them
        for e in range(n):
            if self.main[e] and 2 * chars[e] >= chars[0]:
                while e >= 0 and not certain[e]:
                    certain[e], e = True, self.parent[e]
        layout, main, doubt = [False] * n, [False] * n, [False] * n
        for e in range(1, n):
            up = self.parent[e]
            header = self.names[e] == "header" and not main[up]
            layout[e] = layout[up] or self.by_tag[e] or header or self.by_name[e] and not certain[e]
            main[e], doubt[e] = main[up] or self.main[e], doubt[up] or self.doubt[e] and not certain[e]
        out = []
        for e, text in self.lines:
            kind = (LAYOUT_LINE if layout[e] else (TEXT if doubt[e] else OWN) if main[e] else DOUBT if doubt[e] else TEXT) if names else TEXT
            out.append((kind, self.place[e], text))
        return out


def lines_of(text: str | None, names: bool = True) -> list[tuple[int, int, str]]:
    """(kind, place, text) of every block of text, in page order."""
    page = _Page()
    for name, body, closing in pieces(text or ""):
        if name is None:
            page.words.append(body)
            continue
        if name in BLOCK:
            page.flush()
        elif name in ("br", "td", "th"):
            page.words.append(" ")
        if closing:
            page.close(name)
            continue
        if name in VOID:
            continue
        if name in _ENDS_P:
            page.close("p", ("button", "td", "th", "table"))
        if name == "li":
            page.close("li", ("ul", "ol", "menu"))
        elif name in ("dd", "dt"):
            page.close("dd", ("dl",))
            page.close("dt", ("dl",))
        if not body.endswith("/") or name in BLOCK:
            page.open(name, body)
    page.flush()
    return page.judged(names)


def common(a: list[int], b: list[int]) -> list[bool]:
    """For each of a, whether it is part of a longest common subsequence with b."""
    out, low = [False] * len(a), 0
    while low < min(len(a), len(b)) and a[low] == b[low]:
        out[low] = True
        low += 1
    high_a, high_b = len(a), len(b)
    while high_a > low and high_b > low and a[high_a - 1] == b[high_b - 1]:
        high_a, high_b = high_a - 1, high_b - 1
        out[high_a] = True
    times = Counter(b[low:high_b])
    if sum(times[x] for x in a[low:high_a]) > 40 * (high_a + high_b - 2 * low):
        _halves(a, low, high_a, b, low, high_b, out)
        return out
    where: dict[int, list[int]] = {}
    for j in range(high_b - 1, low - 1, -1):
        where.setdefault(b[j], []).append(j)
    ends: list[int] = []
    chains: list[tuple[int, object]] = []
    for i in range(low, high_a):
        for j in where.get(a[i], ()):
            k = bisect_left(ends, j)
            node = (i, chains[k - 1] if k else None)
            if k == len(ends):
                ends.append(j)
                chains.append(node)
            else:
                ends[k], chains[k] = j, node
    node = chains[-1] if chains else None
    while node:
        out[node[0]] = True
        node = node[1]
    return out


def _lengths(a: list[int], b: list[int]) -> np.ndarray:
    """Length of the longest common subsequence of a with every beginning of b, 64 columns of the table at a time."""
    masks: dict[int, int] = {}
    for j, y in enumerate(b):
        masks[y] = masks.get(y, 0) | 1 << j
    full = (1 << len(b)) - 1
    row = full
    for x in a:
        hit = row & masks.get(x, 0)
        row = ((row + hit) | (row - hit)) & full
    bits = np.unpackbits(np.frombuffer((full ^ row).to_bytes(len(b) // 8 + 1, "little"), np.uint8), bitorder="little")[: len(b)]
    return np.concatenate([[0], np.cumsum(bits, dtype=np.int64)])


def _halves(a: list[int], a0: int, a1: int, b: list[int], b0: int, b1: int, out: list[bool]) -> None:
    """The same by halving a: for lines repeated so often that listing all equal pairs would take too long."""
    if a0 == a1 or b0 == b1:
        return
    if a1 - a0 == 1:
        out[a0] = a[a0] in b[b0:b1]
        return
    mid = (a0 + a1) // 2
    ahead, back = _lengths(a[a0:mid], b[b0:b1]), _lengths(a[mid:a1][::-1], b[b0:b1][::-1])
    cut = b0 + int(np.argmax(ahead + back[::-1]))
    _halves(a, a0, mid, b, b0, cut, out)
    _halves(a, mid, a1, b, cut, b1, out)


def keys_of(lines: list[tuple[int, int, str]]) -> list[int]:
    """What lines are aligned by: their text, or their place where class names leave open what they are."""
    return [place | 1 if kind == DOUBT else xxhash.xxh64_intdigest(text) & ~1 for kind, place, text in lines]


def page_text(lines: list[tuple[int, str]], marks: list[list[bool]]) -> str:
    """Text left of a page; ``lines`` are (kind, text), ``marks`` say for each neighbour which lines it has too."""
    size = [len(text) if kind == OWN else 0 for kind, text in lines]
    apart = [m for m in marks if 2 * sum(n for n, x in zip(size, m, strict=True) if x) < sum(size)]
    kept = []
    for i, (kind, text) in enumerate(lines):
        if kind == OWN:
            votes = sum(m[i] for m in apart)
            gone = votes >= 3 and votes == len(apart)
        else:
            gone = kind == LAYOUT_LINE or any(m[i] for m in marks)
        if not gone:
            kept.append(text)
    return "\n\n".join(kept)


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, "^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    """Path and query of a URL."""
    return F.coalesce(F.regexp_extract(url, "^(?:[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*)?([^#]*)", 1), F.lit(""))


def _borders(pages: DataFrame, id_col: str, step: int, halo: int, n: int) -> list[tuple[tuple, tuple, tuple]]:
    """(first page, first page of the halo before, last page of the halo behind) of each slice but the first."""
    if n <= step:
        return []
    placed = ordinal(pages.select("__host", "__path", F.col(id_col).alias("__id")), "__host", "__path", "__id")
    at = F.pmod(F.col("ord"), F.lit(step))
    found = {r["ord"]: _key(r["__host"], r["__path"], r["__id"]) for r in placed.where(at.isin(0, step - halo, halo - 1)).select("__host", "__path", "__id", "ord").collect()}
    last = max(found.values())
    return [(found[i], found[i - halo], found.get(i + halo - 1, last)) for i in range(step, n, step)]


def _key(host: str, path: str, page: object) -> tuple:
    return host, path, (0,) if page is None else (1, page)


def extract(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", slice_pages: int = 256, beside: int = 2, halo: int = 8, names: bool = True) -> DataFrame:
    """(id, url, text, n_chars) for every page."""
    kinds = [T.StructField("__slice", T.IntegerType()), T.StructField("__host", T.StringType()), T.StructField("__path", T.StringType()), T.StructField("__keys", T.BinaryType()), T.StructField("__body", T.BinaryType())]
    parsed = T.StructType([pages.schema[id_col], pages.schema[url_col], *kinds])
    result = T.StructType([pages.schema[id_col], pages.schema[url_col], T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])
    rows = pages.select(id_col, url_col, host_of(F.col(url_col)).alias("__host"), path_of(F.col(url_col)).alias("__path"), html_col)
    n = pages.count()
    borders = _borders(rows, id_col, max(slice_pages, 2 * halo, -(-n // 10_000)), halo, n)
    shared = pages.sparkSession.sparkContext.broadcast(borders)

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3)
        borders = shared.value
        firsts, before, behind = ([b[k] for b in borders] for k in range(3))
        for batch in batches:
            at, slices, keys, bodies = [], [], [], []
            for i, (page, host, path, value) in enumerate(zip(*(batch.column(k).to_pylist() for k in (0, 2, 3, 4)), strict=True)):
                lines = lines_of(value, names)
                own = np.array(keys_of(lines), np.uint64).tobytes()
                here = bisect_right(firsts, key := _key(host, path, page))
                at.append(i)
                slices.append(here)
                keys.append(own)
                bodies.append(pack.compress("\n".join(f"{kind}{text if kind != LAYOUT_LINE else ''}" for kind, _, text in lines).encode("utf-8", "surrogatepass")))
                beyond = [k + 1 for k in range(here, bisect_right(before, key))] + [k for k in range(bisect_left(behind, key), here)]
                for k in beyond:
                    at.append(i)
                    slices.append(k)
                    keys.append(own)
                    bodies.append(None)
            taken = [batch.column(k).take(pa.array(at, pa.int64())) for k in (0, 1, 2, 3)]
            yield pa.RecordBatch.from_arrays([*taken[:2], pa.array(slices, pa.int32()), *taken[2:], pa.array(keys, pa.binary()), pa.array(bodies, pa.binary())], names=parsed.names)

    def differ(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack, types = zstandard.ZstdDecompressor(), None
        groups: list[tuple[str, bytes, list[tuple]]] = []  # neighbouring rows of a host with the same lines
        done: list[tuple] = []
        first = 0  # the first group that waits for its neighbours

        def solve(i: int) -> None:
            host, own, rows = groups[i]
            if all(r[6] is None for r in rows):
                return
            keys = lambda x: np.frombuffer(x, np.uint64).tolist()
            around = [g for side in (groups[:i][::-1], groups[i + 1 :]) for g in [g[1] for g in side if g[0] == host and g[1] != own][:beside]]
            mine = keys(own)
            marks = [common(mine, keys(g)) for g in around]
            for r in rows:
                if r[6] is not None:
                    body = unpack.decompress(r[6]).decode("utf-8", "surrogatepass")
                    text = page_text([(int(x[0]), x[1:]) for x in body.split("\n")] if body else [], marks)
                    done.append((r[0], r[1], text, len(text)))

        def made() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*done, strict=True), types, strict=True)], names=result.names)
            done.clear()
            return batch

        for batch in batches:
            types = types or [batch.schema.field(0).type, batch.schema.field(1).type, pa.string(), pa.int64()]
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if groups and groups[-1][0] == row[3] and groups[-1][1] == row[5]:
                    groups[-1][2].append(row)
                    continue
                groups.append((row[3], row[5], [row]))
                while first < len(groups) - beside - 2:
                    solve(first)
                    first += 1
                if first > 4 * beside + 4:
                    del groups[: first - beside - 2]
                    first = beside + 2
                if len(done) >= 500:
                    yield made()
        while first < len(groups):
            solve(first)
            first += 1
        if done:
            yield made()

    dealt = rows.mapInArrow(parse, parsed).repartitionById(len(borders) + 1, F.col("__slice")).sortWithinPartitions("__host", "__path", id_col)
    return dealt.mapInArrow(differ, result)
