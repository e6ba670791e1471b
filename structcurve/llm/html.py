"""Main text of web pages by differencing each page with the pages nearest to it in URL order."""

from __future__ import annotations

import html as entities
import re
from bisect import bisect_left, bisect_right
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, text_of

SCHEMA = "page_id bigint, url string, text string, n_chars bigint, n_shared int"

#: Elements whose text is never shown as text, page furniture, blocks, and words in class, id or role that mark furniture.
HIDDEN = frozenset("script style noscript template head title svg math iframe object canvas audio video select textarea".split())
FURNITURE = frozenset("nav header footer aside form menu dialog button".split())
BLOCKS = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
#: Whole class names, ids and roles of furniture, and what such names are made of.
NAMED = frozenset("ad ads advert adverts advertisement advertising banner cookie cookies consent gdpr notice popup modal sidebar menu navbar nav navigation breadcrumb breadcrumbs footer header comment comments respond related share sharing social promo sponsor sponsored newsletter subscribe signup login search widget pagination pager contentinfo complementary".split())
JOINED = re.compile(r"(?:ads?|advert\w*|sponsor\w*)[-_](?:slot|unit|box|banner|block|container|wrapper|\d+)|comments?[-_](?:list|area|section|form|thread|body|box|wrapper|\d+)|(?:site|page|main|top|left|right|cookie|mobile|primary|secondary)[-_](?:header|footer|nav|navigation|menu|sidebar|banner|notice|consent)|related[-_](?:posts?|articles?|links|stories)|(?:share|social)[-_](?:buttons?|links|bar)", re.I)
MARKED = re.compile(r"(?:^|[\s_-])(?:" + "|".join(sorted(NAMED)) + r")(?:$|[\s_-])", re.I)

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_ATTRIBUTE = re.compile(r"(?:^|\s)(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
#: Raw text: nothing but the end tag ends these.
_RAW_END = {k: re.compile(rf"</{k}\s*(?=[>/\s])[^>]*>", re.I) for k in ("script", "style", "title", "textarea", "noscript", "iframe")}

ARTICLE, OPEN, BOILERPLATE, LOOSE = 2, 1, 0, 3
#: A neighbour that shares this much of a page's open text is a copy and says nothing about furniture.
COPY = 0.9


def page_lines(page: str) -> list[tuple[int, str]]:
    """The page's text blocks in order, each with its place: article, furniture, or open (neither).

    Furniture is what a tag or a whole class name, id or role says it is.  A block whose class only holds such a
    word ("related-work", "notice-period"), and an article's own header, is open, so differencing decides it, also
    inside an article; outside of one, on a page that has one, it is furniture.
    """
    lines: list[tuple[int, str]] = []
    parts: list[str] = []
    skip: list[str] = []  # open elements of furniture, outermost first
    loose: list[str] = []  # open elements that may be furniture, likewise
    article = 0
    hidden_until = ""
    depth = 0

    def close_block() -> None:
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                place = BOILERPLATE if skip else (OPEN if article else LOOSE) if loose else ARTICLE if article else OPEN
                lines.append((place, text))
            parts.clear()

    at, end = 0, len(page)
    while at < end:
        tag = _TAG.search(page, at)
        if not tag:
            if not hidden_until:
                parts.append(page[at:])
            break
        if tag.start() > at and not hidden_until:
            parts.append(page[at : tag.start()])
        at = tag.end()
        name = (tag[2] or "").lower()
        if not name:
            continue
        closing = bool(tag[1])
        if hidden_until:
            if name == hidden_until:
                depth += -1 if closing else 1
                if depth == 0:
                    hidden_until = ""
            continue
        if name == "br":
            parts.append(" ")
            continue
        if name in _RAW_END and not closing:
            found = _RAW_END[name].search(page, at)
            if found:
                at = found.end()
            elif name in ("script", "style"):
                at = end
            parts.append(" " if name not in ("script", "style") else "")
            continue
        if name in HIDDEN:
            if not closing and name not in ("title", "head"):
                hidden_until, depth = name, 1
            elif name == "head" and not closing:
                skip.append("head")
            elif name == "head" and "head" in skip:
                close_block()
                skip.remove("head")
            continue
        if name in BLOCKS or name in FURNITURE:
            close_block()
        if closing:
            if name in skip:
                del skip[len(skip) - 1 - skip[::-1].index(name) :]
            elif name in loose:
                del loose[len(loose) - 1 - loose[::-1].index(name) :]
            elif name in ("article", "main") and article:
                article -= 1
                skip.clear()
                loose.clear()
            continue
        if name in ("article", "main") and not (skip and _is_named(tag[3])):
            if not article:
                skip.clear()  # furniture that was never closed ends here
                loose.clear()
            elif skip:
                skip.append(name)  # an article inside comments and the like
                continue
            article += 1
        elif name == "body":
            skip.clear()
            loose.clear()
        elif skip:
            if name in skip and name not in VOID:
                skip.append(name)
        elif name in FURNITURE and not (name == "header" and article) or (name in BLOCKS or name == "span") and _is_named(tag[3]):
            if name == "span":
                close_block()
            if name not in VOID:
                skip.append(name)
        elif name in loose or name == "header" or name in BLOCKS and MARKED.search(_marks(tag[3])):
            if name not in VOID:
                loose.append(name)
    close_block()
    outside = BOILERPLATE if any(place == ARTICLE for place, _ in lines) else OPEN
    return [(outside if place == LOOSE else place, text) for place, text in lines]


def _marks(attributes: str) -> str:
    return " ".join(a or b or c for a, b, c in _ATTRIBUTE.findall(attributes)) if attributes and "=" in attributes else ""


def _is_named(attributes: str) -> bool:
    return any(m.lower() in NAMED or JOINED.fullmatch(m) for m in _marks(attributes).split())


def shared_lines(a: list[str], b: list[str]) -> set[int]:
    """Places in ``a`` of a longest common subsequence with ``b``.

    Equal ends belong to one and are cut off.  What is left goes by longest rising runs of matches, which follows
    the number of equal pairs; where lines repeat so much that these are many, by rows of bits.
    """
    head, tail = 0, 0
    while head < min(len(a), len(b)) and a[head] == b[head]:
        head += 1
    while tail < min(len(a), len(b)) - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    ends = set(range(head)) | set(range(len(a) - tail, len(a)))
    a, b = a[head : len(a) - tail], b[head : len(b) - tail]
    in_a = Counter(a)
    pairs = sum(n * in_a[line] for line, n in Counter(b).items())
    inner = _by_runs(a, b) if pairs <= 8 * (len(a) + len(b)) else _by_bits(a, b)
    return ends | {i + head for i in inner}


def _bit_rows(a: list[str], b: list[str]) -> Iterator[int]:
    """For each beginning of ``a`` the bits that are 0 where the common subsequence with ``b`` grows by one line."""
    full = (1 << len(b)) - 1
    marks: dict[str, bytearray] = {}
    for j, line in enumerate(b):
        marks.setdefault(line, bytearray(len(b) // 8 + 1))[j >> 3] |= 1 << (j & 7)
    masks = {line: int.from_bytes(m, "little") for line, m in marks.items() if line in set(a)} if len(marks) < 64 else None
    row = full
    for line in a:
        m = masks.get(line, 0) if masks is not None else int.from_bytes(marks[line], "little") if line in marks else 0
        both = row & m
        row = ((row + both) | (row - both)) & full
        yield row


def _by_bits(a: list[str], b: list[str], most: int = 1 << 28) -> set[int]:
    """A longest common subsequence by rows of bits; halves ``a`` while all rows would be above ``most`` bits."""
    if not a or not b:
        return set()
    if len(a) > 1 and len(a) * len(b) > most:
        half, m = len(a) // 2, len(b)

        def grown(part: list[str], other: list[str]) -> np.ndarray:
            *_, row = _bit_rows(part, other)
            bits = np.unpackbits(np.frombuffer(row.to_bytes(m // 8 + 1, "little"), np.uint8), bitorder="little")[:m]
            return np.concatenate([[0], np.cumsum(1 - bits.astype(np.int64))])

        cut = int(np.argmax(grown(a[:half], b) + grown(a[half:][::-1], b[::-1])[::-1]))
        return _by_bits(a[:half], b[:cut], most) | {half + i for i in _by_bits(a[half:], b[cut:], most)}
    rows = list(_bit_rows(a, b))
    out, i, j = set(), len(a), len(b)
    while i and j:
        if rows[i - 1] >> (j - 1) & 1:
            j -= 1
            continue
        i -= 1
        if not (i and not rows[i - 1] >> (j - 1) & 1):
            j -= 1
            out.add(i)
    return out


def _by_runs(a: list[str], b: list[str]) -> set[int]:
    where: dict[str, list[int]] = {}
    for j, line in enumerate(b):
        where.setdefault(line, []).append(j)
    ends: list[int] = []  # for each length, the smallest place in b that ends such a run
    at_end: list[tuple] = []
    for i, line in enumerate(a):
        for j in reversed(where.get(line, ())):
            k = bisect_left(ends, j)
            link = (i, at_end[k - 1] if k else None)
            if k == len(ends):
                ends.append(j)
                at_end.append(link)
            elif j < ends[k]:
                ends[k], at_end[k] = j, link
    out, link = set(), at_end[-1] if at_end else None
    while link:
        out.add(link[0])
        link = link[1]
    return out


def main_text(lines: list[tuple[int, str]], neighbours: list[list[tuple[int, str]]]) -> tuple[str, int]:
    """The page's main text and how many of its lines outside the article are shared with a neighbour.

    Furniture is deleted; open lines are deleted if a neighbour shares them; lines of the article stay.  A
    neighbour that shares nearly all of the open text is a copy of the page, and deletes nothing.
    """
    outside = [i for i, (place, _) in enumerate(lines) if place != ARTICLE]
    own = [lines[i][1] for i in outside]
    free = sum(len(t) for place, t in lines if place == OPEN)
    shared: set[int] = set()
    n_shared: set[int] = set()
    for other in neighbours:
        found = {outside[i] for i in shared_lines(own, [t for place, t in other if place != ARTICLE])}
        n_shared |= found
        if sum(len(lines[i][1]) for i in found if lines[i][0] == OPEN) < COPY * free:
            shared |= found
    return "\n".join(t for i, (place, t) in enumerate(lines) if place == ARTICLE or place == OPEN and i not in shared), len(n_shared)


def host_and_path(url: str) -> tuple[str, str]:
    rest = re.sub(r"^[a-zA-Z][a-zA-Z0-9+.-]*:", "", url or "")
    rest = rest[2:] if rest.startswith("//") else rest
    host, _, path = rest.partition("/")
    return host.lower(), re.split(r"[?#]", "/" + path, maxsplit=1)[0]


def _key(host: str, path: str, page_id: int | None, tie: int) -> tuple:
    """A page's place in URL order, as Spark sorts it (null ids first)."""
    return host, path, page_id is not None, page_id or 0, tie


def url_ranges(keys: DataFrame, chunk: int, tasks: int) -> tuple[list[tuple], list[tuple]]:
    """The first and the last key of each run of about ``chunk`` pages in URL order; equal keys share a run."""

    def borders(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, n = None, 0
        for batch in batches:
            out = []  # (row, is it the first of its range)
            for row in zip(*(batch.column(i).to_pylist() for i in range(4))):
                if last is None or n >= chunk and row != last:
                    out += [(last, False)] * (last is not None) + [(row, True)]
                    n = 0
                last, n = row, n + 1
            yield _borders(out)
        if last is not None:
            yield _borders([(last, False)])

    dealt = keys.repartitionByRange(tasks, *keys.columns).sortWithinPartitions(*keys.columns)
    found = arrow_map(dealt, borders, "host string, path string, page_id bigint, tie bigint, first boolean").collect()
    return tuple(sorted(_key(*r[:4]) for r in found if r.first is first) for first in (True, False))


def _borders(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.string(), pa.string(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([*(pa.array([r[i] for r, _ in rows], k) for i, k in enumerate(kinds)), pa.array([f for _, f in rows], pa.bool_())], ["host", "path", "page_id", "tie", "first"])


def extract_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least_chunk: int = 200) -> DataFrame:
    """One row per page: ``page_id, url, text, n_chars`` and ``n_shared``, the lines shared with neighbours.

    Pages of a host are ordered by URL path; each is differenced with the one before and after it.
    What is furniture is told by :func:`page_lines`; open lines that the page shares with a neighbour are deleted, unless
    the neighbour is a copy of the page; nothing else is dropped, so an article keeps its headline and its
    sections whatever their classes are called.
    The order is cut into ranges of about C pages, where C is ``least_chunk`` or a 200,000th of all pages
    if that is more: a first pass sorts the pages' keys alone and notes the first and last key of each range, and these
    (at most about 200,000 ranges and one for each task) are broadcast.  A range's border pages travel to the range
    beside it too, so every page meets its true neighbours whatever the size of its host or of the table, and no
    task gets a whole hot host.  Null html gives an empty text, a null url counts as an empty host; ids
    may be null or repeat (ties in the order go by id, then by a hash of the html; rows equal in all of these stay in one range);
    empty tables give empty tables; other columns are ignored.  Each page's lines travel once, a border page's
    up to three times, and stream through the task.
    """
    rows = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).cast("string").alias("url"), text_of(html_col).alias("html"), F.xxhash64(text_of(html_col)).alias("tie"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            where = [host_and_path(url) for url in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([w[0] for w in where], pa.string()), pa.array([w[1] for w in where], pa.string()), batch.column(0), batch.column(2)], ["host", "path", "page_id", "tie"])

    keys = arrow_map(rows.select("page_id", "url", "tie"), place, "host string, path string, page_id bigint, tie bigint")
    tasks = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = url_ranges(keys, max(least_chunk, pages.count() // 200_000), tasks)
    tasks = max(tasks, min(20_000, len(found[0]) // 8))  # a task's share does not grow with the table
    ranges = pages.sparkSession.sparkContext.broadcast(found)

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        firsts, lasts = ranges.value
        kinds = (pa.int64(), pa.string(), pa.int32(), pa.bool_(), pa.string(), pa.string(), pa.int64(), pa.list_(pa.string()), pa.list_(pa.int8()))
        for batch in batches:
            out = []
            for page_id, url, page, tie in zip(*(batch.column(i).to_pylist() for i in range(4))):
                host, path = host_and_path(url)
                key = _key(host, path, page_id, tie)
                k = max(0, bisect_right(firsts, key) - 1)
                found = page_lines(page)
                row = (host, path, tie, [t for _, t in found], [p for p, _ in found])
                out.append((page_id, url, k, False, *row))
                if k and key == firsts[k] and lasts[k - 1][0] == host:
                    out.append((page_id, url, k - 1, True, *row))
                if k + 1 < len(firsts) and key == lasts[k] and firsts[k + 1][0] == host:
                    out.append((page_id, url, k + 1, True, *row))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], ["page_id", "url", "chunk", "border", "host", "path", "tie", "lines", "places"])

    def difference(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before: tuple | None = None  # (row, its left neighbour's lines)

        def finish(row: tuple, left: list | None, right: list | None) -> list[tuple]:
            if row[4]:
                return []  # a page of the range beside this one
            text, n = main_text(row[3], [x for x in (left, right) if x is not None])
            return [(row[0], row[1], text, len(text), n)]

        for batch in batches:
            out = []
            for page_id, url, chunk, border, host, lines, places in zip(*(batch.column(i).to_pylist() for i in (0, 1, 2, 3, 4, 7, 8))):
                row = (page_id, url, (chunk, host), list(zip(places, lines)), border)
                left = None
                if before:
                    same = before[0][2] == row[2]
                    out += finish(before[0], before[1], row[3] if same else None)
                    left = before[0][3] if same else None
                before = (row, left)
            yield _texts(out)
        if before:
            yield _texts(finish(before[0], before[1], None))

    parsed = arrow_map(rows, parse, "page_id bigint, url string, chunk int, border boolean, host string, path string, tie bigint, lines array<string>, places array<tinyint>")
    dealt = parsed.repartition(tasks, "chunk").sortWithinPartitions("chunk", "host", "path", "page_id", "tie")
    return arrow_map(dealt, difference, SCHEMA)


def _texts(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int32())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["page_id", "url", "text", "n_chars", "n_shared"])
