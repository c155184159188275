"""HTML extraction with nearest-URL page differencing.

Each page becomes text lines (blocks) with what the markup says of them: inside the article (or main)
element, inside an element that is never article text (navigation, header, footer, sidebar, advert,
notice, form, comments), or neither. Pages are sorted by host and URL path; each is compared with the SPAN
pages before and behind it on its host, its lines aligned with theirs by longest common subsequence.

What is deleted: lines that the markup sets apart; where a page marks an article, whatever lies outside it;
elsewhere, lines that the nearest of these pages has too. A page that has nearly all the text of another
is a copy and tells nothing of templates, so the next nearest is taken. Lines inside an article element are
kept even where neighbours have them: articles under several URLs, and passages that many articles
share, would otherwise vanish.

Pages are dealt out by ranges of the order, found on a bounded sample; pages at an edge also go to the
next range, so each page meets its true neighbours whatever the number of ranges or partitions."""

from __future__ import annotations

import html as html_lib
import math
import re
from bisect import bisect_left, bisect_right
from collections import deque
from collections.abc import Iterator
from itertools import zip_longest

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import count_partitions, ship_package, unique_ids
from .substring_dedup import with_doc_ids

# Element names and attribute words of HTML pages.
RAW = ("script", "style", "textarea", "title", "noscript", "iframe", "xmp")
UNSEEN = {"script", "style", "title", "noscript", "iframe", "xmp", "template", "svg", "math", "object", "embed", "canvas", "audio", "video", "head", "select", "datalist", "button", "textarea", "dialog", "menu", "map", "applet"}
OUTSIDE = {"nav", "footer", "aside", "form", "header"}
BLOCKS = {
    "address", "article", "aside", "blockquote", "body", "caption", "center", "dd", "details", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6",
    "head", "header", "hgroup", "hr", "html", "legend", "li", "main", "nav", "ol", "option", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "title", "tr", "ul",
}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
OUTSIDE_WORDS = re.compile(
    r"(?:^|[\s_-])(?:ad|ads|adv|advert\w*|adsense|banner\w*|breadcrumbs?|byline-share|comments?|comment-?list|consent|cookies?|copyright|disclaimer|disqus|dropdown|flyout|foot|footer|gdpr|header|login|masthead"
    r"|menu\w*|modal|nav|navbar|navigation|newsletter|notice\w*|notification|overlay|paywall|popup|promo\w*|recommend\w*|related|replies|reply|respond|rss|search\w*|share\w*|sharing|sidebar\w*|signup|site-?nav|skip"
    r"|social\w*|sponsor\w*|subscribe\w*|tagcloud|tags|toolbar|topbar|widget\w*)(?:$|[\s_-])"
)
ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
# End of fixed values.

TAG = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$)", re.S)
ATTRIBUTE = re.compile(r"([^\s/>][^\s/>=]*)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?")
CLOSERS = {"p": {"p"}, "li": {"li"}, "dd": {"dd", "dt"}, "dt": {"dd", "dt"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
WHITE = re.compile(r"\s+")
INSIDE, NEITHER, NEVER = 2, 1, 0

#: Pages before and behind a page that it may be compared with.
SPAN = 2
#: Share of a page's free characters on common lines from which the other page counts as a copy.
COPY_SHARE = 0.9
#: Pages a range should hold; ranges at most; sampled pages per range by which they are cut.
RANGE_PAGES, MOST_RANGES, SAMPLED = 256, 1 << 16, 8
#: Shuffle partitions at most.
MOST_TASKS = 1 << 15


def _set_apart(name: str, attributes: str, in_article: bool) -> bool:
    """Whether the element holds text that is never main text."""
    if name in UNSEEN or name in OUTSIDE and not (name == "header" and in_article):
        return True
    if not attributes or name in ("html", "body", "article", "main"):
        if name != "article" or not attributes:
            return False
    for key, value in ATTRIBUTE.findall(attributes):
        key, value = key.lower(), value.strip("\"'").lower()
        if key in ("class", "id") and OUTSIDE_WORDS.search(value) or key == "role" and value in ROLES:
            return True
        if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
            return True
    return False


def page_lines(page: str | None) -> list[tuple[str, int]]:
    """(text, INSIDE an article / NEITHER / NEVER main text) of every block, in page order."""
    out: list[tuple[str, int]] = []
    buffer: list[str] = []
    stack: list[tuple[str, bool, bool]] = []  # name, set apart, article
    page = page or ""
    place, end = 0, len(page)

    def state() -> int:
        apart = inside = False
        if stack:
            _, apart, inside = stack[-1]
        return NEVER if apart else INSIDE if inside else NEITHER

    def close() -> None:
        if buffer:
            text = WHITE.sub(" ", html_lib.unescape("".join(buffer))).strip()
            buffer.clear()
            if text:
                out.append((text, state()))

    while place < end:
        m = TAG.search(page, place)
        if m is None:
            buffer.append(page[place:])
            break
        if m.start() > place:
            buffer.append(page[place : m.start()])
        place = m.end()
        if not m.group(2):
            continue
        name, closing = m.group(2).lower(), bool(m.group(1))
        if name in VOID:
            if name == "br":
                buffer.append(" ")
            elif name == "hr":
                close()
            continue
        if name in BLOCKS or name in UNSEEN:
            close()
        if closing:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    # an inline element's end parts no text, unless what follows is of another kind
                    if stack[-1][1:] != (stack[k - 1][1:] if k else (False, False)):
                        close()
                    del stack[k:]
                    break
            continue
        for k in range(len(stack) - 1, -1, -1):
            if stack[k][0] in CLOSERS.get(name, ()):
                close()
                del stack[k:]
                break
            if stack[k][0] in BLOCKS and stack[k][0] not in ("p",):
                break
        _, apart, inside = stack[-1] if stack else ("", False, False)
        new_apart = _set_apart(name, m.group(3), inside)
        if new_apart and name not in BLOCKS:
            close()
        if not m.group(3).rstrip().endswith("/") or name in BLOCKS:
            stack.append((name, apart or new_apart, inside or name in ("article", "main")))
        if name in RAW:
            tail = re.compile(rf"</{name}\b", re.I).search(page, place)
            place = tail.start() if tail else end
    close()
    return out


def shared_lines(one: list[str], two: list[str]) -> set[int]:
    """Numbers of the lines of `one` on a longest common subsequence with `two`.

    Row by row over `one`, the subsequence lengths of all prefixes of `two` are one integer of a bit for each
    line, so lines that come back any number of times cost no more than others. Every so many rows are
    kept; the rows between are made again on the way back."""
    both = set(one) & set(two)
    rows = [i for i, x in enumerate(one) if x in both]
    columns = [x for x in two if x in both]
    # a common head belongs to some longest one
    head = next((k for k, (i, x) in enumerate(zip(rows, columns, strict=False)) if one[i] != x), min(len(rows), len(columns)))
    out = set(rows[:head])
    rows, columns = rows[head:], columns[head:]
    if not rows or not columns:
        return out
    places: dict[str, int] = {}
    for j, x in enumerate(columns):
        places[x] = places.get(x, 0) | 1 << j
    full = (1 << len(columns)) - 1

    def step(v: int, i: int) -> int:
        # a 0 in bit j: the line j makes the subsequence one longer
        u = v & places.get(one[rows[i]], 0)
        return ((v + u) | (v - u)) & full

    every = math.isqrt(len(rows)) + 1
    marks, v = [], full
    for i in range(len(rows)):
        if i % every == 0:
            marks.append(v)
        v = step(v, i)
    j, start, made = len(columns), len(rows), []
    for i in range(len(rows) - 1, -1, -1):
        if i < start:
            start = i - i % every
            made = [marks[start // every]]
            for r in range(start, i + 1):
                made.append(step(made[-1], r))
        after = made[i - start + 1]
        # lines of `two` that don't lengthen the subsequence of this row aren't on it
        while j and after >> (j - 1) & 1 and one[rows[i]] != columns[j - 1]:
            j -= 1
        if not j:
            break
        if one[rows[i]] == columns[j - 1]:
            out.add(rows[i])
            j -= 1
    return out


def template_lines(lines: list[str], kinds: list[int], around: list[list[str]]) -> set[int]:
    """Free lines that the nearest page which is no copy has too. around: lines of neighbouring pages, nearest
    first."""
    size = sum(len(x) for x, k in zip(lines, kinds, strict=True) if k == NEITHER)
    for other in around:
        common = {i for i in shared_lines(lines, other) if kinds[i] == NEITHER}
        if sum(len(lines[i]) for i in common) < COPY_SHARE * size:
            return common
    return set()


def main_text(lines: list[str], kinds: list[int], around: list[list[str]]) -> str:
    """Article lines where the page marks an article, else the lines that aren't set apart, less template lines."""
    if INSIDE in kinds:
        return "\n".join(x for x, k in zip(lines, kinds, strict=True) if k == INSIDE)
    gone = template_lines(lines, kinds, around)
    return "\n".join(x for i, (x, k) in enumerate(zip(lines, kinds, strict=True)) if k == NEITHER and i not in gone)


def line_kernel(shared):
    """Pages as lines, each with its range; pages at an edge also once for every range next to it (`own` false)."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts, edges = shared.value
        for batch in batches:
            for a in range(0, batch.num_rows, 64):
                part = batch.slice(a, 64)
                found = [page_lines(x) for x in part.column(4).to_pylist()]
                place = list(zip(part.column(1).to_pylist(), part.column(2).to_pylist(), part.column(0).to_pylist(), strict=True))
                take, cell, own = [], [], []
                for i, key in enumerate(place):
                    mine = bisect_right(cuts, key)
                    for c in (mine, *edges.get(key[2], ())):
                        take.append(i)
                        cell.append(c)
                        own.append(c == mine)
                columns = [part.column(k).take(pa.array(take)) for k in range(4)]
                lines = pa.array([[t for t, _ in found[i]] for i in take], pa.list_(pa.string()))
                kinds = pa.array([[k for _, k in found[i]] for i in take], pa.list_(pa.int8()))
                yield pa.RecordBatch.from_arrays([pa.array(cell, pa.int64()), pa.array(own), *columns, lines, kinds], ["cell", "own", "_uid", "host", "path", "url", "lines", "kinds"])

    return kernel


def common_prefix(a: str, b: str) -> int:
    n = 0
    for x, y in zip_longest(a, b):
        if x != y:
            break
        n += 1
    return n


def difference_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Ranges arrive whole and in order of host and path. Each page is compared with the SPAN pages before and
    behind it that are of its range and host, those of the longer common path first (the earlier if
    equal). Holds 2 * SPAN + 1 pages."""
    held: deque = deque()
    middle = 0  # the place in `held` of the next page to be answered

    def answer(k: int):
        page = held[k]
        near = [x for x in list(held)[max(0, k - SPAN) : k][::-1] + list(held)[k + 1 : k + 1 + SPAN] if x[0] == page[0] and x[3] == page[3]]
        near.sort(key=lambda x: -common_prefix(x[4], page[4]))
        return page[2], page[5], main_text(page[6], page[7], [x[6] for x in near])

    def rows(found) -> pa.RecordBatch:
        uid, url, text = zip(*found, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(uid, pa.int64()), pa.array(url, pa.string()), pa.array(text, pa.string())], ["_uid", "url", "text"])

    for batch in batches:
        done: list = []
        for a in range(0, batch.num_rows, 64):
            for row in zip(*(batch.column(k).slice(a, 64).to_pylist() for k in range(8)), strict=True):
                held.append(row)
                if len(held) - middle > SPAN:
                    if held[middle][1]:
                        done.append(answer(middle))
                    if middle == SPAN:
                        held.popleft()
                    else:
                        middle += 1
        if done:
            yield rows(done)
    done = [answer(k) for k in range(middle, len(held)) if held[k][1]]
    if done:
        yield rows(done)


def range_kernel(shared):
    """(_uid, host, path) -> the page's range."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = zip(*(batch.column(k).to_pylist() for k in (1, 2, 0)), strict=True)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(3)), pa.array([bisect_right(shared.value, key) for key in keys], pa.int64())], ["_uid", "host", "path", "cell"])

    return kernel


def page_ranges(places: DataFrame) -> tuple[list[tuple], dict[int, list[int]]]:
    """(cuts, edges) of pages (_uid, host, path): keys (host, path, _uid) that part the ranges, and for pages near an
    edge the other ranges they belong to as well. Both are bounded by MOST_RANGES."""
    spark = places.sparkSession
    total = places.count()
    count = min(MOST_RANGES, math.ceil(total / RANGE_PAGES))
    if count <= 1:
        return [], {}
    sample = places.where(F.pmod(F.xxhash64(F.lit(1), "_uid"), F.lit(1 << 40)) < int((1 << 40) * min(1.0, SAMPLED * count / total))).collect()
    keys = sorted((r["host"], r["path"], r["_uid"]) for r in sample)
    cuts = sorted({keys[len(keys) * i // count] for i in range(1, count)}) if keys else []
    ranged = places.mapInArrow(range_kernel(spark.sparkContext.broadcast(cuts)), "_uid long, host string, path string, cell long")
    order = ("host", "path", "_uid")
    first = F.row_number().over(Window.partitionBy("cell").orderBy(*order))
    last = F.row_number().over(Window.partitionBy("cell").orderBy(*[F.desc(c) for c in order]))
    ends = [ranged.withColumn("nth", n).where(F.col("nth") <= SPAN).select("cell", *order) for n in (first, last)]
    heads, tails = ([(r["cell"], r["host"], r["path"], r["_uid"]) for r in e.orderBy("cell", *order).collect()] for e in ends)
    edges: dict[int, list[int]] = {}
    tail_cells, head_cells = [x[0] for x in tails], [x[0] for x in heads]
    for c in range(len(cuts) + 1):
        # the SPAN pages before the range and behind it; ranges of fewer pages are reached over
        before, behind = bisect_left(tail_cells, c), bisect_right(head_cells, c)
        for x in tails[max(0, before - SPAN) : before] + heads[behind : behind + SPAN]:
            edges.setdefault(x[3], []).append(c)
    return cuts, edges


def extract_text(pages: DataFrame) -> DataFrame:
    """The main text of every page.

    pages: page_id, url, html, any other columns (ignored). Returns page_id, url, text (blocks in page order,
    joined by one newline; white space inside a block is one space; character references decoded; empty
    if there is none), n_chars (code points). One row per row of pages. Null html: empty text. Null
    or odd urls: the page has no host and pairs with others of none. Rows with a null or repeated page_id
    count as pages of their own. Empty table: empty result.

    Pages are dealt out by ranges of (host, path), so that a host of any size is spread over tasks."""
    spark = pages.sparkSession
    ship_package(spark)
    ids = unique_ids(pages.select("page_id", "url", F.col("html").alias("text")), "page_id")
    url = F.coalesce("url", F.lit(""))
    host = F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))
    path = F.regexp_extract(url, r"^(?:[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*)?([^?#]*)", 1)
    ids_ = ids.select("_uid", host.alias("host"), path.alias("path"), "url", "text")
    cuts, edges = page_ranges(ids_.select("_uid", "host", "path"))
    shared = spark.sparkContext.broadcast((cuts, edges))
    lines = ids_.mapInArrow(line_kernel(shared), "cell long, own boolean, _uid long, host string, path string, url string, lines array<string>, kinds array<byte>")
    # ranges are of like size, so each is a task's work by itself, or one of a few where they are many
    ordered = lines.repartition(min(max(len(cuts) + 1, count_partitions(spark)), MOST_TASKS), "cell").sortWithinPartitions("cell", "host", "path", "_uid")
    texts = ordered.mapInArrow(difference_kernel, "_uid long, url string, text string")
    out = texts.select("_uid", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
    return with_doc_ids(out, ids.withColumnRenamed("page_id", "doc_id")).withColumnRenamed("doc_id", "page_id")
