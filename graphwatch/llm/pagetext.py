"""Main text of web pages by nearest-URL page differencing.

Pages are ordered by host and URL path, so that a page's neighbour is the page of its host with the
nearest path before it (after it, for the first page of a host). The visible lines (blocks) of the two
are aligned by a longest common subsequence, and shared lines are the template of the site: they go.
Two things that differencing cannot know come from the markup. Lines inside a page's article (or main)
element are never taken for template, since sites do repeat whole articles and passages; and menus,
headers, footers, sidebars, notices, adverts, forms and reader comments go even where their words
differ from page to page.

Which page is whose neighbour does not depend on how Spark deals the rows. Hosts with many pages are
cut into blocks of consecutive pages, at exact ranks found on URLs alone; the page at a cut is the last
of one block and goes to the next one as well, where it only serves as a neighbour.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from html import unescape

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwatch.functions.ranking import range_rank
from graphwatch.functions.storage import table
from graphwatch.llm.urlfilter import host_of, path_of
from graphwatch.llm.workers import trimmed

#: Pages of a block at least, and blocks that are cut off in all at most (their first URLs are broadcast).
BLOCK_PAGES, MOST_CUTS = 64, 1 << 15

#: Elements by their part in a page.
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split())
UNSEEN = frozenset("script style noscript template head title textarea select option button iframe object embed svg canvas audio video map datalist math".split())
ASIDE = frozenset("nav header footer aside form menu dialog".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes".split())
#: Words in class, id or role that mark what is not main text.
MARKS = frozenset("nav navbar navigation menu breadcrumb breadcrumbs header masthead footer sidebar aside widget cookie cookies consent gdpr notice notification alert banner popup modal overlay ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion share sharing social related recommended newsletter subscribe subscription signup login search pagination pager comment comments commentlist reply replies respond disqus complementary contentinfo skip".split())
MAIN_ROLES = frozenset(["main", "article"])
_TAG = re.compile(r"<!--.*?(?:-->|$)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>", re.S)
_MARK = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_WORDS = re.compile(r"[a-z]+")
#: An end tag that is left out: this start closes those, up to the stop elements.
_CLOSES = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_HELD = frozenset("ul ol dl table tbody thead tfoot body article main section div nav aside header footer form blockquote td".split())


@dataclass(frozen=True)
class Line:
    text: str
    main: bool  # in an article or main element
    aside: bool  # in a part that is not main text


def page_lines(html: str | None) -> list[Line]:
    """The visible lines of a page in order, character references decoded and white space made single."""
    lines: list[Line] = []
    parts: list[str] = []
    stack: list[tuple[str, bool, bool, bool]] = [("", False, False, False)]  # name, main, aside, unseen

    def flush():
        if parts:
            text = " ".join(unescape("".join(parts)).split())
            parts.clear()
            if text:
                _, main, aside, unseen = stack[-1]
                if not unseen:
                    lines.append(Line(text, main, aside))

    at, text = 0, html or ""
    while True:
        found = _TAG.search(text, at)
        if not found:
            parts.append(text[at:])
            break
        if found.start() > at:
            parts.append(text[at : found.start()])
        at = found.end()
        name = (found[2] or "").lower()
        if not name:
            continue
        if found[1]:
            if name in BLOCKS or name in UNSEEN:
                flush()
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i][0] == name:
                        del stack[i:]
                        break
            continue
        seen_as = _words_of(found[3]) if "=" in found[3] else ()
        is_block = name in BLOCKS or name in UNSEEN
        if not is_block and not seen_as:
            continue
        if is_block:
            flush()
        if name in RAW:
            end = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(text, at)
            at = end.end() if end else len(text)
            continue
        if name in VOID:
            continue
        if name in _CLOSES:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] in _CLOSES[name]:
                    del stack[i:]
                    break
                if stack[i][0] in _HELD:
                    break
        if is_block:
            _, main, aside, unseen = stack[-1]
            outer = aside or name in ASIDE and not (main and name == "header") or any(w in MARKS for w in seen_as)
            stack.append((name, main or name in ("article", "main") or any(w in MAIN_ROLES for w in seen_as), outer, unseen or name in UNSEEN))
    flush()
    return lines


def _words_of(attributes: str) -> list[str]:
    return [w for m in _MARK.finditer(attributes) for w in _WORDS.findall((m[1] or m[2] or m[3] or "").lower())]


def common_lines(a: list[str], b: list[str]) -> set[int]:
    """Places in a of a longest common subsequence with b.

    Equal ends are taken off first. Of the rest, row i of the table of lengths is one whole number
    with a bit for each line of b, which is 0 where the length grows, so a row costs a few additions.
    """
    low, top = 0, min(len(a), len(b))
    while low < top and a[low] == b[low]:
        low += 1
    same = 0
    while same < top - low and a[-1 - same] == b[-1 - same]:
        same += 1
    out = set(range(low)) | set(range(len(a) - same, len(a)))
    n, m = len(a) - low - same, len(b) - low - same
    places: dict[str, int] = {}
    for j in range(m):
        places[b[low + j]] = places.get(b[low + j], 0) | 1 << j
    every = (1 << m) - 1
    rows = [every]
    for i in range(n):
        v = rows[-1]
        u = v & places.get(a[low + i], 0)
        rows.append((v + u | v - u) & every)
    i, j = n, m
    while i and j:
        bit = 1 << j - 1
        if rows[i] & bit:
            j -= 1
        elif not rows[i - 1] & bit:
            i -= 1
        else:
            i, j = i - 1, j - 1
            out.add(low + i)
    return out


def main_text(lines: list[Line], neighbour: list[Line] | None) -> str:
    """The lines that are left after differencing: what is no aside, and either in an article or not shared.

    A page that has an article and no neighbour keeps the article alone, as nothing tells the rest from template.
    """
    shared = common_lines([x.text for x in lines], [x.text for x in neighbour]) if neighbour else set()
    article_only = neighbour is None and any(x.main and not x.aside for x in lines)
    return "\n".join(x.text for i, x in enumerate(lines) if not x.aside and (x.main or not article_only and i not in shared))


def _key(path: Column, page: Column, body: Column) -> Column:
    """The place of a page in its host; the hash parts rows that share URL and page_id."""
    return F.struct(path.alias("path"), F.coalesce(page, F.lit(-(1 << 63))).alias("page"), F.xxhash64(body).alias("hash"))


def host_cuts(rows: DataFrame, least: int = BLOCK_PAGES, most: int = MOST_CUTS) -> DataFrame:
    """host, cuts: the keys of every ``step``-th page of each host that has more pages than that, in order. rows: host, key.

    step is ``least`` or so much more that there are at most ``most`` cuts in all.
    """
    per = table(rows.groupBy("host").agg(F.count("*").alias("n")), "page-hosts")
    total = per.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    step = max(least, -(-total // most))
    large = per.filter(F.col("n") > step).select(F.col("host").alias("_h"))  # at most as many as cuts
    light = rows.join(F.broadcast(large), F.col("host") == F.col("_h")).select("host", "key.*")
    ranked = range_rank(light, [F.col(c) for c in ("host", "path", "page", "hash")], "rank", by="host")
    cuts = ranked.filter((F.col("rank") > 0) & (F.col("rank") % step == 0)).select("host", F.struct("path", "page", "hash").alias("key"))
    return cuts.groupBy("host").agg(F.array_sort(F.collect_list("key")).alias("cuts"))


def _cuts_before(cuts: Column, key: Column, most: int = MOST_CUTS) -> Column:
    """How many cuts lie before the key, by halving."""
    steps = F.array(*[F.lit(1 << i) for i in reversed(range(most.bit_length()))])
    at = F.aggregate(steps, F.lit(0), lambda at, s: F.when((at + s <= F.size(cuts)) & (F.get(cuts, at + s - 1) < key), at + s).otherwise(at))
    return F.when(cuts.isNull(), F.lit(0)).otherwise(at)


def extract(pages: DataFrame, html: str = "html", url: str = "url", page_id: str = "page_id", block_pages: int = BLOCK_PAGES) -> DataFrame:
    """page_id, url, text for each row of pages.

    Null or empty html has the empty text. A page is compared with the one before it in the order
    of host, path and page_id, the first of a host with the one after it, a page alone on its host
    with none; a null URL belongs to the empty host. A task keeps the lines of two pages at a time.
    Columns beyond these three are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows():
            for b in batches:
                for host, block, serves, page, link, body in zip(*(b.column(i) for i in range(6)), strict=True):
                    yield (host.as_py(), block.as_py()), serves.as_py(), page.as_py(), link.as_py(), page_lines(body.as_py())

        ids, links, texts, size = [], [], [], 0
        before: tuple | None = None  # block and lines of the last page
        waiting: tuple | None = None  # the first page of a host, until the next one comes

        def done(row, neighbour):
            nonlocal size
            if row[1]:
                return
            text = main_text(row[4], neighbour)
            ids.append(row[2]), links.append(row[3]), texts.append(text)
            size += len(text)

        def batch():
            return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(links, pa.string()), pa.array(texts, pa.string())], ["page_id", "url", "text"])

        for row in rows():
            if waiting is not None:
                done(waiting, row[4] if waiting[0] == row[0] else None)
                waiting = None
            if before is not None and before[0] == row[0]:
                done(row, before[1])
            else:
                waiting = row
            before = (row[0], row[4])
            if size > 8 << 20:
                yield batch()
                ids, links, texts, size = [], [], [], 0
        if waiting is not None:
            done(waiting, None)
        if ids:
            yield batch()

    own = pages.select(host_of(pages[url]).alias("host"), _key(path_of(pages[url]), pages[page_id].cast("long"), pages[html]).alias("key"), pages[page_id].cast("long").alias("page_id"), pages[url].alias("url"), pages[html].alias("html"))
    cuts = table(host_cuts(own.select("host", "key"), block_pages), "page-cuts").withColumnRenamed("host", "_h")
    rows = own.join(F.broadcast(cuts), F.col("host") == F.col("_h"), "left")
    rows = rows.withColumn("block", _cuts_before(F.col("cuts"), F.col("key")))
    # The page at a cut ends its block, and begins the next one as a neighbour.
    at_cut = F.coalesce(F.get("cuts", F.col("block")) == F.col("key"), F.lit(False))
    places = F.when(at_cut, F.array(F.struct(F.col("block"), F.lit(False).alias("serves")), F.struct((F.col("block") + 1).alias("block"), F.lit(True).alias("serves"))))
    rows = rows.withColumn("place", F.explode(F.coalesce(places, F.array(F.struct(F.col("block"), F.lit(False).alias("serves"))))))
    rows = rows.select("host", "place.block", "place.serves", "page_id", "url", "html", "key")
    dealt = rows.repartition("host", "block").sortWithinPartitions("host", "block", "key")
    return dealt.select("host", "block", "serves", "page_id", "url", "html").mapInArrow(trimmed(run), "page_id long, url string, text string")


def op7_query(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return extract(pages).withColumn("n_chars", F.char_length("text").cast("long"))
