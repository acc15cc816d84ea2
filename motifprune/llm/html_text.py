"""Main text of web pages by nearest-URL page differencing.

A page is cut into blocks of text, each with the part of the page it stands in. Within a host, pages are
ordered by URL path; each is aligned with its neighbours on either side by a longest common subsequence
of block hashes, and blocks shared with a neighbour are deleted as the site's own, in every page alike. All
blocks of all pages are aligned. The markup assists: what it names as menu, header, footer, side bar, notice,
advert, form or reader comment goes even if no neighbour shares it, and so do blocks outside of an article or main
part where a page names one; paragraphs, headings and items of such a part stay, as articles share passages, and its
other blocks are deleted like any; scripts and styles are no blocks. Two pages that share most of the blocks
which the markup leaves, or most blocks of their article or main parts, are copies, not a template, and delete
nothing from each other.

Only block hashes are sorted, by range over (host, path), so a host with a third of all pages is split; the pages at
the edges of neighbouring ranges are paired through a table of two rows a range. A second reading of the pages
takes the deletions by a key of the page's id, URL and content.

Defined results: null html is empty and gives an empty text; a page without neighbour keeps all blocks not
excluded by the markup, within its article or main part if it has one; unclosed and stray tags are borne; pages of
any length are aligned whole; repeated rows are one page when aligned and get the same text; ties in the order are
settled by page_id and content; columns beside page_id, url and html are not read; an empty table yields no rows.
"""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifprune.llm import common

# Element names and words of class, id and role that mark what is not main text.
DROPPED = frozenset("nav footer aside form script style noscript template iframe svg button select menu dialog head title object canvas audio video".split())
RAW = frozenset("script style noscript template iframe svg title textarea".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
MAIN = frozenset("article main".split())
MARKED = frozenset(
    "ad ads adbox adslot advert adverts advertisement advertising banner cookie cookies consent notice notices sidebar comment comments replies reply disqus menu nav navbar navigation "
    "breadcrumb breadcrumbs share sharing social related promo promotion sponsor sponsored newsletter subscribe subscription popup modal overlay footer header masthead widget contentinfo complementary search alert dialog".split()
)
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd blockquote pre figcaption td th".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|</?([A-Za-z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)>", re.S)
_MARK = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_SPACE = re.compile(r"\s+")
_URL = re.compile(r"^(?:[a-z][a-z0-9+.-]*:)?//([^/?#]*)([^?#]*)", re.I)


def _excluded(attributes: str) -> bool:
    for m in _MARK.finditer(attributes):
        if MARKED & set(re.split(r"[\s_-]+", (m[1] or m[2] or m[3] or "").lower())):
            return True
    return False


def blocks(page: str) -> tuple[list[tuple[str, bool, bool, bool]], bool]:
    """[(text, inside an article or main part, excluded by the markup, prose of such a part)]; whether there is such a part."""
    out: list[tuple[str, bool, bool, bool]] = []
    parts: list[str] = []
    dropped: list[str] = []
    stack: list[tuple[str, bool, bool]] = []  # name, excluded, main
    has_main = False

    def flush() -> None:
        inside = bool(stack) and stack[-1][2]
        prose = inside and next((name for name, _, _ in reversed(stack) if name not in INLINE), "") in PROSE
        for held, excluded in ((parts, False), (dropped, True)):
            if held:
                text = _SPACE.sub(" ", html_lib.unescape("".join(held))).strip()
                if text:
                    out.append((text, inside, excluded, prose))
                held.clear()

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        end = m.start() if m else n
        if end > at:
            (dropped if stack and stack[-1][1] else parts).append(page[at:end])
        if not m:
            break
        at = m.end()
        name = (m[1] or "").lower()
        if not name:
            continue
        if page[m.start() + 1] == "/":
            if name not in INLINE:
                flush()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    del stack[k:]
                    break
                if name in INLINE and stack[k][0] not in INLINE:
                    break
            continue
        if name not in INLINE:
            flush()
            while stack and stack[-1][0] in INLINE and not stack[-1][1]:
                stack.pop()
        elif name == "br":
            (dropped if stack and stack[-1][1] else parts).append(" ")
        if name in VOID or m[2].endswith("/") and name not in MAIN:
            continue
        if name in RAW:
            close = re.compile(rf"</{name}\b[^>]*>", re.I).search(page, at)
            at = close.end() if close else n
            continue
        if name in MAIN and stack and any(x[1] for x in stack):
            stack.clear()  # an excluded part that was never closed
        if name in CLOSES_P:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == "p":
                    del stack[k:]
                    break
                if stack[k][0] not in INLINE:
                    break
        if name == "li" and stack and stack[-1][0] == "li":
            stack.pop()
        above = stack[-1] if stack else ("", False, False)
        inside = above[2] or name in MAIN
        drop = above[1] or name in DROPPED or name == "header" and not above[2] or name not in MAIN | {"html", "body"} and _excluded(m[2])
        has_main |= name in MAIN and not drop
        stack.append((name, drop, inside))
    flush()
    return out, has_main


ALIGNED_BITS = 1 << 30  # of rows held at once


def common_subsequence(a: list[int], b: list[int]) -> list[int]:
    """Positions in a of a longest common subsequence of a and b, by bit-parallel rows.

    Equal ends are cut off first and only lines of both sides are aligned; where the rows would take more than
    ALIGNED_BITS, b is parted at the place that half of a aligns with best, so that memory stays bounded.
    """
    head = 0
    while head < min(len(a), len(b)) and a[head] == b[head]:
        head += 1
    tail = 0
    while tail < min(len(a), len(b)) - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    both = set(a[head : len(a) - tail]) & set(b[head : len(b) - tail])
    x = [k for k in range(head, len(a) - tail) if a[k] in both]
    found: list[int] = []
    waiting = [(x, [v for v in b[head : len(b) - tail] if v in both])]
    while waiting:
        x, y = waiting.pop()
        if len(x) < 2 or len(x) * len(y) <= ALIGNED_BITS:
            found += _aligned(a, x, y)
            continue
        half = len(x) // 2
        before = _lengths([a[k] for k in x[:half]], y)
        after = _lengths([a[k] for k in reversed(x[half:])], y[::-1])[::-1]
        cut = int((before + after).argmax())
        waiting += [(x[:half], y[:cut]), (x[half:], y[cut:])]
    return [*range(head), *sorted(found), *range(len(a) - tail, len(a))]


def _rows(values: list[int], y: list[int]) -> Iterator[int]:
    """After each value, the bits of y's places where the common length does not grow."""
    where: dict[int, int] = {}
    for k, v in enumerate(y):
        where[v] = where.get(v, 0) | 1 << k
    full = row = (1 << len(y)) - 1
    for v in values:
        u = row & where.get(v, 0)
        row = ((row + u) | (row - u)) & full
        yield row


def _lengths(values: list[int], y: list[int]) -> np.ndarray:
    """Length of a longest common subsequence of values with each beginning of y."""
    row = (1 << len(y)) - 1
    for row in _rows(values, y):  # the last one counts
        pass
    bits = np.unpackbits(np.frombuffer(row.to_bytes(len(y) // 8 + 1, "little"), dtype=np.uint8), bitorder="little")[: len(y)]
    return np.concatenate([[0], np.cumsum(1 - bits.astype(np.int64))])


def _aligned(a: list[int], x: list[int], y: list[int]) -> list[int]:
    """Which places x of a align with y."""
    rows = list(_rows([a[k] for k in x], y))
    j, got = len(y) - 1, []
    for i in range(len(x) - 1, -1, -1):
        before = rows[i - 1] if i else (1 << len(y)) - 1
        while j >= 0 and rows[i] >> j & 1:  # walk back to where the length grows
            j -= 1
        if j < 0:
            break
        if before >> j & 1:  # it is this row that adds one
            got.append(x[i])
            j -= 1
    return got


INSIDE, EXCLUDED, KEPT, TAGS = 1, 2, 4, 3  # the last bits of a line's hash


def _copies(shared: int, own: int, other: int) -> bool:
    return own > 0 and other > 0 and shared * 5 >= 4 * max(own, other)


def shared_lines(own: list[int], other: list[int]) -> set[int]:
    """Positions of own lines that the other page shares, unless the two pages are copies."""
    if not own or not other:
        return set()
    got = common_subsequence([x >> TAGS for x in own], [x >> TAGS for x in other])
    left = lambda lines: sum(not x & EXCLUDED for x in lines)
    main = lambda lines: sum(x & (INSIDE | EXCLUDED) == INSIDE for x in lines)
    both = [own[k] for k in got]
    if any(_copies(count(both), count(own), count(other)) for count in (left, main)):
        return set()
    return {k for k in got if not own[k] & KEPT}


def _line(text: str, inside: bool, excluded: bool, prose: bool) -> int:
    """A hash of a block; its last bits tell the part of the page."""
    return (xxhash.xxh3_64_intdigest(text) >> TAGS + 1 << TAGS) | INSIDE * inside | EXCLUDED * excluded | KEPT * (prose and not excluded)


_LINED = "key long, page_id long, host string, path string, lines array<long>"
_PAIRED = "key long, page_id long, lines array<long>, host string, part int, place string, gone array<int>"


def _lined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Lines of each page and its place in the order of its host."""
    for batch in batches:
        rows = []
        for key, page_id, url, page in zip(*(c.to_pylist() for c in batch.columns)):
            m = _URL.match(url or "")
            host, path = (m[1].lower(), m[2]) if m else ("", url or "")
            rows.append((key, page_id, host, re.sub(r"\.html?$", "", path.rstrip("/")), [_line(*f) for f in blocks(page)[0]]))
        yield _batch(rows, _LINED, (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.int64())))


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The blocks that may stand in each page's text; others are empty, so that places stay."""
    for batch in batches:
        rows = []
        for key, page_id, url, page in zip(*(c.to_pylist() for c in batch.columns)):
            found, has_main = blocks(page)
            rows.append((key, page_id, url, ["" if excluded or has_main and not inside else t for t, inside, excluded, _ in found]))
        yield _batch(rows, "key long, page_id long, url string, texts array<string>", (pa.int64(), pa.int64(), pa.string(), pa.list_(pa.string())))


def _batch(rows: list[tuple], schema: str, kinds: tuple) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [[]] * len(kinds), kinds)], [f.split(" ")[0] for f in schema.split(", ")])


def _paired(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of one sorted range that lose lines, with these; the first and last row are told by `place` and keep their lines."""

    def out(rows):
        rows = [(key, page_id, lines if place else [], host, part, place, sorted(gone)) for key, page_id, lines, host, part, place, gone in rows if place or gone]
        return _batch(rows, _PAIRED, (pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.string(), pa.int32(), pa.string(), pa.list_(pa.int32())))

    last = None
    for batch in batches:
        done = []
        for r in zip(*(c.to_pylist() for c in batch.columns)):
            row = [*r, "first" if last is None else "", set()]
            if last is not None:
                if last[:2] == row[:2]:
                    continue  # a repeated row
                if last[3] == row[3]:
                    last[6] |= shared_lines(last[2], row[2])
                    row[6] |= shared_lines(row[2], last[2])
                done.append(last)
            last = row
        yield out(done)
    if last is not None:
        last[5] += "last"
        yield out([last])


def _edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        more = [sorted(shared_lines(own or [], other or [])) for own, other in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
        yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(more, pa.list_(pa.int32()))], ["key", "page_id", "gone"])


def deleted_lines(pages: DataFrame) -> DataFrame:
    """(key, page_id, gone): the places of the lines that pages (key, page_id, url, html) share with a neighbour."""
    lined = common.written(pages.mapInArrow(_lined, _LINED).where("size(lines) > 0"), "lines")
    order = ["host", "path", "page_id", "key"]
    ranged = lined.repartitionByRange(*order).sortWithinPartitions(*order)
    paired = common.written(ranged.select("key", "page_id", "lines", "host", F.spark_partition_id().alias("part")).mapInArrow(_paired, _PAIRED), "paired")
    # Two rows a range: the last page of one is the neighbour of the first page of the next range that has pages.
    ends = paired.where("place <> ''").select("key", "page_id", "part", "place", "host", "lines")
    firsts = ends.where("place LIKE 'first%'")
    follow = firsts.select("part", F.lead("part").over(Window.orderBy("part")).alias("next_part"))
    heads = firsts.select(F.col("part").alias("next_part"), F.col("host").alias("next_host"), F.col("lines").alias("next_lines"), F.col("key").alias("next_key"), F.col("page_id").alias("next_id"))
    met = ends.where("place LIKE '%last'").join(follow, "part").join(heads, "next_part").where(F.col("host") == F.col("next_host"))
    both = met.select("key", "page_id", "lines", F.col("next_lines").alias("other")).union(met.select("next_key", "next_id", "next_lines", "lines"))
    more = both.mapInArrow(_edges, "key long, page_id long, gone array<int>")
    return paired.select("key", "page_id", "gone").union(more).where("size(gone) > 0").groupBy("key", "page_id").agg(F.flatten(F.collect_list("gone")).alias("gone"))


def main_texts(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of every row."""
    src = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html"), F.lit("")).alias("html"))
    src = src.select(F.xxhash64("page_id", "url", "html").alias("key"), "page_id", "url", "html")
    gone = deleted_lines(src).select(F.col("key").alias("gone_key"), F.col("page_id").alias("gone_id"), "gone")
    found = src.mapInArrow(_texts, "key long, page_id long, url string, texts array<string>")
    cut = found.join(gone, (F.col("key") == F.col("gone_key")) & F.col("page_id").eqNullSafe(F.col("gone_id")), "left")
    text = F.concat_ws("\n\n", F.filter("texts", lambda t, k: (t != "") & ~F.coalesce(F.array_contains("gone", k), F.lit(False))))
    return cut.select("page_id", "url", text.alias("text"), F.length(text).cast("long").alias("n_chars"))


def op6_url_differencing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_texts(common.read_table(spark, sf_dir, "pages"))
