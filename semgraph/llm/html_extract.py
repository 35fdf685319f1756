"""Main text of web pages by nearest-URL page differencing, with the page's own markup as evidence.

Pages are read into text lines (blocks). Each page is paired with the page of its host whose URL path is nearest
in path order (the neighbour that shares the longer start of the path), their lines are aligned by longest common
subsequence, and shared lines outside the article are deleted. Differencing alone does not give right
results where menus differ from page to page or where two pages carry the same article, so markup comes first: lines
inside an article or main element are kept whatever the other page holds, and lines inside menus, headers,
footers, sidebars, notices, adverts, forms and comments go.
"""

from __future__ import annotations

import bisect
import html as entities
import re
from collections import defaultdict
from collections.abc import Iterator
from typing import NamedTuple
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, spread, text_of

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)|<[!?][^>]*(?:>|\Z)", re.S)
_ATTR = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))")
_BARE_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|/|=|$)", re.I)
_NAME_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
#: Elements whose content is no text, elements that end a line, elements without content, chrome by element, role, and class or id.
RAW = frozenset("script style noscript template svg iframe object canvas textarea select math audio video".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CHROME_ELEMENTS = frozenset("nav aside form footer button dialog menu head".split())
CHROME_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())
CHROME_NAMES = frozenset(
    "ad ads advert adverts advertisement advertisements banner banners breadcrumb breadcrumbs comment comments cookie cookies consent disqus footer gdpr login masthead menu menus modal nav navbar navigation newsletter notice notices pager pagination popup promo promos promotion related search share sharing sidebar sidebars signup social sponsor sponsored subscribe toolbar widget widgets".split()
)
ARTICLE = frozenset(("article", "main"))


class Line(NamedTuple):
    text: str
    kept: bool  # inside an article or main element
    chrome: bool  # inside a menu, header, footer, sidebar, notice, advert, form or comments


def _is_chrome(tag: str, attrs: str, in_article: bool) -> bool:
    if tag in CHROME_ELEMENTS or (tag == "header" and not in_article):
        return True
    if not attrs:
        return False
    for m in _ATTR.finditer(attrs):
        name, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if name in ("class", "id") and tag not in ("body", "html", *ARTICLE):
            parts = {p.lower() for p in _NAME_PARTS.findall(value)}
            if parts & CHROME_NAMES or ("header" in parts and not in_article):
                return True
        elif (name == "role" and value.lower() in CHROME_ROLES) or (name == "aria-hidden" and value.lower() == "true"):
            return True
        elif name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            return True
    return _BARE_HIDDEN.search(re.sub(_ATTR, " ", attrs)) is not None


def read_lines(page: str) -> list[Line]:
    """Text lines of a page in order. Broken and cut markup is read as far as it goes."""
    lines: list[Line] = []
    held: list[str] = []
    stack: list[tuple[str, bool, bool]] = []  # (element, in article, in chrome)
    state = (False, False)

    def end_line() -> None:
        if held:
            text = " ".join(entities.unescape("".join(held)).split())
            held.clear()
            if text:
                lines.append(Line(text, *state))

    at, n, lowered = 0, len(page), None
    while at < n:
        m = _TAG.search(page, at)
        if m is None:
            held.append(page[at:])
            break
        if m.start() > at:
            held.append(page[at : m.start()])
        at = m.end()
        if not m[2]:
            continue
        tag, closing = m[2].lower(), bool(m[1])
        if tag in RAW and not closing:
            if not m[3].endswith("/") or tag in ("script", "style", "textarea", "select", "iframe", "noscript", "template"):
                lowered = lowered or page.lower()
                end = lowered.find(f"</{tag}", at)
                at = n if end < 0 else end
            continue
        if tag == "br":
            held.append(" ")
            continue
        if tag in BLOCK:
            end_line()
        if tag in VOID:
            continue
        if closing:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == tag:
                    if tag in BLOCK or i == len(stack) - 1:
                        del stack[i:]
                    else:
                        del stack[i]
                    break
        else:
            if tag in BLOCK and stack:  # a paragraph or list item left open ends here
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] == "p" or (stack[i][0] == tag and tag in ("li", "dd", "dt", "option", "tr", "td", "th")):
                        del stack[i:]
                        break
                    if stack[i][0] in BLOCK:
                        break
            state = (stack[-1][1], stack[-1][2]) if stack else (False, False)
            role_main = tag == "div" and 'role="main"' in m[3]
            article = state[0] or ((tag in ARTICLE or role_main) and not state[1])
            chrome = state[1] or _is_chrome(tag, m[3], article)
            stack.append((tag, article, chrome))
        state = (stack[-1][1], stack[-1][2]) if stack else (False, False)
    end_line()
    return lines


def shared_lines(a: list[int], b: list[int]) -> list[int]:
    """Positions of `a` on a longest common subsequence of a and b (hashes of lines): longest increasing run of matches."""
    places: dict[int, list[int]] = defaultdict(list)
    for j, h in enumerate(b):
        places[h].append(j)
    ends: list[int] = []  # least end in b of a common subsequence of each length
    tails: list[int] = []
    links: list[tuple[int, int]] = []  # (position in a, link before)
    for i, h in enumerate(a):
        for j in reversed(places.get(h, ())):
            k = bisect.bisect_left(ends, j)
            links.append((i, tails[k - 1] if k else -1))
            if k == len(ends):
                ends.append(j)
                tails.append(len(links) - 1)
            else:
                ends[k], tails[k] = j, len(links) - 1
    out, at = [], tails[-1] if tails else -1
    while at >= 0:
        i, at = links[at]
        out.append(i)
    return out[::-1]


def candidate_lines(lines: list[Line]) -> tuple[list[str], list[int]]:
    """(texts, positions) of lines that may be in the result: all inside an article, with position -1 since nothing removes
    them, or, on pages that mark none, all that is not chrome.
    """
    own = [x.text for x in lines if x.kept and not x.chrome]
    if own:
        return own, [-1] * len(own)
    rest = [(x.text, i) for i, x in enumerate(lines) if not x.chrome]
    return [t for t, _ in rest], [i for _, i in rest]


def main_text(texts: list[str], positions: list[int], shared: set[int]) -> str:
    """Candidate lines less the shared ones, joined by blank lines."""
    return "\n\n".join([t for t, i in zip(texts, positions) if i not in shared])


def _place(url: str) -> tuple[str, str]:
    try:
        parts = urlsplit(url)
        return (parts.hostname or "").lower(), parts.path + ("?" + parts.query if parts.query else "")
    except ValueError:
        return "", url


def _hashes(lines: list[Line]) -> list[int]:
    return [xxhash.xxh64_intdigest(x.text) >> 1 for x in lines]


def _common(a: str | None, b: str) -> int:
    if a is None:
        return -1
    n = 0
    for x, y in zip(a, b):
        if x != y:
            break
        n += 1
    return n


def pair_pages(pages: DataFrame) -> DataFrame:
    """(key, shared array<int>) of (key, url, html): for each distinct page the lines it shares with its nearest page.

    Only hashes of lines move. Pages are dealt out by ranges of (host, path, key), so a large host is spread over many
    tasks; numbers along that order join each page with the one before and the one after. No result depends on where
    ranges are cut. A page that shares most of its lines with its neighbour is a copy of it and loses none.
    """

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            places = [_place(u) for u in b.column(1).to_pylist()]
            hashes = [_hashes(read_lines(h)) for h in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([p[0] for p in places]), pa.array([p[1] for p in places]), pa.array(hashes, pa.list_(pa.int64()))], ["key", "host", "path", "lines"])

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pid, at = TaskContext.get().partitionId(), 0
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([pid] * b.num_rows, pa.int32()), pa.array(np.arange(at, at + b.num_rows))], [*b.schema.names, "pid", "at"])
            at += b.num_rows

    spark = pages.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    seen = pages.select("key", "url", "html").mapInArrow(read, "key long, host string, path string, lines array<long>").dropDuplicates(["key"])
    seen = materialize(seen, "page-lines")  # range bounds are sampled: the rows must not change meanwhile
    order = seen.repartitionByRange(parts, "host", "path", "key").sortWithinPartitions("host", "path", "key")
    order = materialize(order.mapInArrow(number, "key long, host string, path string, lines array<long>, pid int, at long"), "page-order")
    sizes = order.groupBy("pid").agg(F.count("*").alias("n"))  # a row for each range
    first = sizes.withColumn("first", F.coalesce(F.sum("n").over(Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    numbered = order.join(F.broadcast(first.select("pid", "first")), "pid").select((F.col("first") + F.col("at")).alias("place"), "key", "host", "path", "lines")
    before = numbered.select((F.col("place") + 1).alias("place"), "host", F.col("path").alias("path_0"), F.col("lines").alias("lines_0"))
    after = numbered.select((F.col("place") - 1).alias("place"), "host", F.col("path").alias("path_1"), F.col("lines").alias("lines_1"))
    beside = numbered.join(before, ["place", "host"], "left").join(after, ["place", "host"], "left")

    def align(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for path, lines, p0, l0, p1, l1 in zip(*(b.column(c).to_pylist() for c in ("path", "lines", "path_0", "lines_0", "path_1", "lines_1"))):
                nearest = l0 if _common(p0, path) >= _common(p1, path) else l1
                found = shared_lines(lines, nearest) if nearest else []
                out.append([] if 5 * len(found) >= 4 * len(lines) else found)
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(out, pa.list_(pa.int32()))], ["key", "shared"])

    return beside.mapInArrow(align, "key long, shared array<int>").filter(F.size("shared") > 0)


def extract_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars): a row for each row of `pages`.

    Null html counts as empty and gives an empty text; null URLs form a host of their own; null ids and repeated rows
    stay. Texts of any length are read whole. An empty table gives an empty result; other columns play no part.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), text_of(html_col).alias("html"))
    keyed = spread(rows).withColumn("key", F.xxhash64("page_id", "url", "html"))
    shared = pair_pages(keyed.select("key", F.coalesce("url", F.lit("")).alias("url"), "html"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [candidate_lines(read_lines(h)) for h in b.column(2).to_pylist()]
            texts, positions = pa.array([f[0] for f in found], pa.list_(pa.string())), pa.array([f[1] for f in found], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), texts, positions, b.column(3)], ["page_id", "url", "texts", "positions", "key"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [main_text(t, p, set(s or ())) for t, p, s in zip(*(b.column(c).to_pylist() for c in ("texts", "positions", "shared")))]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(out, pa.string()), pa.array(list(map(len, out)), pa.int64())], ["page_id", "url", "text", "n_chars"])

    # only lines that may stay move, not the pages
    lines = keyed.select("page_id", "url", "html", "key").mapInArrow(read, "page_id long, url string, texts array<string>, positions array<int>, key long")
    joined = lines.join(shared, "key", "left").select("page_id", "url", "texts", "positions", "shared")
    return joined.mapInArrow(run, "page_id long, url string, text string, n_chars long")
