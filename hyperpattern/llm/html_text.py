"""Main text of web pages, by differencing with the page of the nearest URL and by structure.

A page is read once into blocks of text with their zone: inside an article, in the open, or in a part that is never
main text (navigation, headers, footers, sidebars, forms, adverts, notices, comments, scripts). Every page is paired with
the page of the nearest URL path of its host whose content differs, copies and pages without text being passed over, and the two sequences of
lines are aligned by longest common subsequence. Lines they share are deleted, but for lines inside an article: what a
neighbour repeats there is still the article's. On a page with an article, the article is what remains of the page.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator
from html import unescape
from urllib.parse import urlsplit

import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import small, table, written

#: Fixed lists of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe xmp noembed noframes".split())
NEVER = frozenset("head nav header footer aside form button select dialog menu svg math object canvas audio video".split())
ARTICLE = frozenset("article main".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre section summary table tbody tfoot thead tr ul".split())
HEADING = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Words of class, id and role that name parts which are never main text, and those that name the article.
NEVER_WORDS = frozenset("ad ads adv advert adverts advertisement advertising banner breadcrumb breadcrumbs byline captcha comment comments commentlist consent cookie cookies dialog disclaimer disqus dropdown footer gdpr header login masthead menu modal nav navbar navigation navigator newsletter notice notices notification overlay pager pagination paywall popup promo promotion recommended related search share sharing sidebar signup skip social sponsor sponsored subscribe subscription tags teaser toc toolbar widget complementary contentinfo".split())
ARTICLE_WORDS = frozenset("article articlebody maincontent entry post story".split())
IN_ARTICLE, OPEN, OUT = 0, 1, 2

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</[a-zA-Z][^>]*(?:>|\Z)|<[a-zA-Z](?:[^>\"']|\"[^\"]*\"|'[^']*')*>|<[a-zA-Z][^>]*(?:>|\Z)", re.S)
NAME = re.compile(r"[a-zA-Z][^\s/>]*")
ATTRIBUTE = re.compile(r"(?<![\w-])(class|id|role|hidden|aria-hidden|itemprop)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+)))?", re.I)
WORD = re.compile(r"[a-z]+")


def _kind(name: str, tag: str) -> int | None:
    """IN_ARTICLE or OUT if the element begins such a part."""
    if name in NEVER:
        return OUT
    found = name in ARTICLE
    if len(tag) > len(name) + 2:
        for key, *values in ATTRIBUTE.findall(tag):
            value, key = "".join(values).lower(), key.lower()
            if key == "hidden" or key == "aria-hidden" and value == "true":
                return OUT
            words = set(WORD.findall(value))
            if words & NEVER_WORDS and name not in ("html", "body"):
                return OUT
            found = found or bool(words & ARTICLE_WORDS) and name in ("div", "section", "td") or key == "role" and value == "main"
    return IN_ARTICLE if found else None


def blocks(html: str) -> list[tuple[str, int]]:
    """(text, zone) of all non-empty blocks in page order; white space is one space, references are decoded."""
    out: list[tuple[str, int]] = []
    stack: list[tuple[str, int]] = []  # open elements and the zone around their content
    parts: list[str] = []
    zone, p, seen_article = OPEN, 0, False

    def end_block() -> None:
        if parts:
            if text := " ".join(unescape("".join(parts)).split()):
                out.append((text, zone))
            parts.clear()

    n = len(html)
    while p < n:
        m = TOKEN.search(html, p)
        if m is None:
            parts.append(html[p:])
            break
        if m.start() > p:
            parts.append(html[p : m.start()])
        tag, p = m[0], m.end()
        if tag[1] in "!?":
            if tag.startswith("<![CDATA["):
                parts.append(tag[9:].removesuffix("]]>").replace("&", "&amp;"))
            continue
        closing = tag[1] == "/"
        name = NAME.match(tag, 2 if closing else 1)[0].lower()
        if name in RAW and not closing:
            end = re.compile(rf"</{name}(?=[\s/>])[^>]*>", re.I).search(html, p)
            p = end.end() if end else n
            continue
        if name in BLOCK:
            end_block()
        elif name in ("br", "td", "th"):
            parts.append(" ")
        if closing:
            k = len(stack) - 1
            while k >= 0 and stack[k][0] != name:
                k -= 1
            if k >= 0 and (name in BLOCK or not any(x in BLOCK for x, _ in stack[k + 1 :])):
                if any(z != zone for _, z in stack[k:]):
                    end_block()
                    zone = stack[k][1]
                del stack[k:]
            continue
        if name in VOID or tag.endswith("/>") and name not in BLOCK:
            continue
        if name == "p" or name in BLOCK and stack and stack[-1][0] == "p":
            if stack and stack[-1][0] == "p":
                zone = stack.pop()[1]
        kind = _kind(name, tag)
        if name in HEADING and kind is None and zone == OUT and seen_article and len(stack) > 1 and stack[-1][0] == "header" and stack[-1][1] == IN_ARTICLE:
            kind = IN_ARTICLE  # the heading in an article's own header
        if kind == IN_ARTICLE and zone == OUT:
            if not seen_article and name in ARTICLE:
                end_block()
                stack.clear()  # a part that was never closed
                zone = OPEN
            elif name not in HEADING:
                kind = OUT
        after = zone if kind is None else kind
        if after != zone:
            end_block()
        seen_article |= after == IN_ARTICLE
        stack.append((name, zone))
        zone = after
    end_block()
    return out


def place(url: str | None) -> tuple[str, str]:
    """(host, path) of a URL; what can't be read is a host of its own."""
    try:
        u = urlsplit((url or "").strip())
        return (u.hostname or "").lower(), u.path or "/"
    except ValueError:
        return url or "", "/"


def common_subsequence(a: list[int], b: list[int]) -> list[int]:
    """Places in a of a longest common subsequence: equal ends are matched as they are, between them lines of a are chained through their places in b, shortest tails first."""
    head = 0
    while head < min(len(a), len(b)) and a[head] == b[head]:
        head += 1
    tail = 0
    while tail < min(len(a), len(b)) - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    at: dict[int, list[int]] = {}
    for j in range(len(b) - tail - 1, head - 1, -1):
        at.setdefault(b[j], []).append(j)
    tails: list[int] = []
    ends: list[tuple] = []
    for i in range(head, len(a) - tail):
        for j in at.get(a[i], ()):
            k = bisect_left(tails, j)
            node = (i, ends[k - 1] if k else None)
            if k == len(tails):
                tails.append(j)
                ends.append(node)
            else:
                tails[k], ends[k] = j, node
    chain, node = [], ends[-1] if ends else None
    while node:
        chain.append(node[0])
        node = node[1]
    return [*range(head), *chain[::-1], *range(len(a) - tail, len(a))]


def nearest(path: str, others: list[tuple[str, list[int]]]) -> list[int]:
    """The lines of the page whose path shares the longest beginning; the earlier of equals."""
    def shared(other: str) -> int:
        n = 0
        for x, y in zip(path, other, strict=False):
            if x != y:
                break
            n += 1
        return n

    return max(others, key=lambda o: shared(o[0]))[1] if others else []


def _line_hash(line: str) -> int:
    return xxhash.xxh64_intdigest(line.encode()) - (1 << 63)


def page_lines(pages: DataFrame) -> DataFrame:
    """host, path, content (hash of the lines), url, html_hash, lines (hashes), open (numbers of lines that differencing may delete; none if the page has an article). pages: url, html, html_hash."""
    schema = "host string, path string, content long, url string, html_hash long, lines array<long>, open array<int>"
    names = [x.split(" ")[0] for x in schema.split(", ")]
    kinds = (pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int32()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for url, html, html_hash in zip(*(batch.column(i) for i in range(3)), strict=True):
                found = blocks(html.as_py() or "")
                spare = [] if any(z == IN_ARTICLE for _, z in found) else [i for i, (_, z) in enumerate(found) if z == OPEN]
                lines = [_line_hash(t) for t, _ in found]
                content = xxhash.xxh64_intdigest(repr((lines, spare)).encode()) - (1 << 63)
                out.append((*place(url.as_py()), content, url.as_py(), html_hash.as_py(), lines, spare))
            columns = list(zip(*out, strict=True)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)

    return pages.select("url", "html", "html_hash").mapInArrow(run, schema)


def in_order(frame: DataFrame, order: list[str], name: str) -> DataFrame:
    """frame with its number in the total order: ranges are dealt out and numbered inside, then shifted by the sizes of the ranges before."""
    n = int(frame.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = written(frame.repartitionByRange(n, *order).withColumn("_range", F.spark_partition_id()), "ordered-pages")
    sizes = dealt.groupBy("_range").agg(F.count("*").alias("_n"))
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # one row for each range
    starts = sizes.select("_range", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    own = F.row_number().over(Window.partitionBy("_range").orderBy(*order))
    return dealt.withColumn("_own", own).join(starts, "_range").withColumn(name, F.col("_start") + F.col("_own")).drop("_range", "_own", "_start")


def shared_lines(lines: DataFrame) -> DataFrame:
    """url, html_hash, shared (how many lines a page shares with its nearest page of other content), gone (numbers of those that are deleted). lines: a written table of page_lines, a row for each url and html."""
    kinds = lines.where(F.size("lines") > 0).groupBy("host", "content").agg(F.min("path").alias("path"), F.first("lines").alias("lines"), F.first("open").alias("open"))
    placed = written(in_order(kinds, ["host", "path", "content"], "at"), "placed-pages")
    side = lambda by, tag: placed.select((F.col("at") + by).alias("at"), F.col("host").alias(f"{tag}_host"), F.col("path").alias(f"{tag}_path"), F.col("lines").alias(f"{tag}_lines"))
    beside = placed.join(side(1, "a"), "at", "left").join(side(-1, "b"), "at", "left")
    beside = beside.select("host", "content", "path", "lines", "open", *[F.when(F.col(f"{t}_host") == F.col("host"), F.col(c)).alias(c) for t in "ab" for c in (f"{t}_path", f"{t}_lines")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gone, shared = [], []
            for _, _, path, own, spare, a_path, a, b_path, b in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                other = nearest(path, [(q, x) for q, x in ((a_path, a), (b_path, b)) if q is not None])
                same = common_subsequence(own, other)
                shared.append(len(same))
                gone.append(sorted(set(spare) & set(same)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(shared, pa.int32()), pa.array(gone, pa.list_(pa.int32()))], names=["host", "content", "shared", "gone"])

    found = written(beside.mapInArrow(run, "host string, content long, shared int, gone array<int>").where("shared > 0"), "shared-lines")
    return lines.select("url", "html_hash", "host", "content").join(small(found), ["host", "content"]).select("url", "html_hash", "shared", "gone")


def main_text(html: str, gone: list[int] | None) -> str:
    found = blocks(html)
    inside = [t for t, z in found if z == IN_ARTICLE]
    if inside:
        return "\n\n".join(inside)
    cut = set(gone or ())
    return "\n\n".join(t for i, (t, z) in enumerate(found) if z == OPEN and i not in cut)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars, n_shared, n_deleted for each row of pages (page_id, url, html).

    n_shared: lines that the page shares with its nearest page; n_deleted: those that are deleted from its text. A null or
    empty page has an empty text; equal rows get equal texts, and so do copies under other ids.
    """
    rows = pages.select("page_id", "url", "html", F.xxhash64("html").alias("html_hash"))
    single = rows.groupBy("url", "html_hash").agg(F.count("*").alias("n")).where("n > 1").select("url", "html_hash")
    repeated = written(single, "repeated-pages")
    rare = rows.join(small(repeated), _same_page(rows, repeated), "left_anti")
    one_each = rows.join(small(repeated), _same_page(rows, repeated), "left_semi").groupBy("url", "html_hash").agg(F.first("html").alias("html"))
    lines = written(page_lines(rare.select("url", "html", "html_hash").unionByName(one_each)), "page-lines")
    gone = written(shared_lines(lines), "lines-gone")
    joined = rows.join(small(gone), _same_page(rows, gone), "left").select("page_id", rows["url"], "html", "shared", "gone")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(h.as_py() or "", g.as_py()) for h, g in zip(batch.column(2), batch.column(4), strict=True)]
            chars = pa.array([len(t) for t in texts], pa.int64())
            shared = pc.fill_null(batch.column(3), 0)
            deleted = pc.fill_null(pc.list_value_length(batch.column(4)), 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), chars, shared, deleted], names=["page_id", "url", "text", "n_chars", "n_shared", "n_deleted"])

    return joined.mapInArrow(run, "page_id long, url string, text string, n_chars long, n_shared int, n_deleted int")


def _same_page(a: DataFrame, b: DataFrame) -> Column:
    return a["url"].eqNullSafe(b["url"]) & (a["html_hash"] == b["html_hash"])


def op9_nearest_url_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    return extract(table(spark, sf_dir, "pages"))
