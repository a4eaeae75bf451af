"""Main text of web pages by nearest-URL page differencing.

Pages are put in order of host and path; each is compared with the page before and after it within its host. The
text lines (blocks) of the two are aligned by a longest common subsequence, and lines that both share are taken to be
the site's frame and deleted, unless they stand inside the page's own article element. What is left loses the regions that
markup itself names as frame: navigation, headers, footers, sidebars, forms, notices, adverts, comments.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.session import materialise, workers

# Element names of HTML by their role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea iframe svg math object canvas audio video select xmp noembed noframes".split())
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html li main menu nav ol option p pre search section summary table tbody td tfoot th thead title tr ul".split())
FRAME = frozenset("nav header footer aside form head button menu dialog search fieldset".split())
ZONES = frozenset("article main".split())
FRAME_ROLES = frozenset("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar".split())
FRAME_WORDS = frozenset("ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies disclaimer footer gdpr header login masthead menu modal nav navbar navigation newsletter notice notices overlay pagination popup promo promotion related replies share sharing sidebar signup skip social sponsor sponsored subscribe toolbar widget".split())
CLOSES = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:"[^"]*"|'[^']*'|[^>"'])*)(?:>|\Z)""", re.S)
_ATTRIBUTE = re.compile(r"""\b(class|id|role|hidden|aria-hidden)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>"']+))?""", re.I)
_NAME = re.compile(r"[a-z]+")
_SCHEME = r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#]*)"


def _framed(name: str, attributes: str, in_zone: bool) -> bool:
    """Whether an element is frame by its name, role, class or id."""
    if name in FRAME and not (in_zone and name == "header"):
        return True
    for key, value in _ATTRIBUTE.findall(attributes) if attributes else ():
        key, value = key.lower(), value.strip("\"'").lower()
        if key == "hidden" or (key == "aria-hidden" and value == "true"):
            return True
        if key == "role" and value in FRAME_ROLES:
            return True
        if key in ("class", "id") and name not in ("html", "body", *ZONES) and any(w in FRAME_WORDS for w in _NAME.findall(value)):
            return True
    return False


def lines_of(page: str | None) -> list[tuple[str, bool, bool]]:
    """(text, inside the article zone, inside frame) of the non-empty blocks of a page, in order."""
    out: list[tuple[str, bool, bool]] = []
    page = page or ""
    stack: list[tuple[str, bool, bool]] = []
    open_at: dict[str, list[int]] = {}  # places of open elements by name, so that no step searches the stack
    zone = frame = False
    words: list[str] = []

    def flush() -> None:
        text = " ".join(html.unescape("".join(words)).split())
        if text:
            out.append((text, zone, frame))
        words.clear()

    def close(k: int) -> None:
        nonlocal zone, frame
        _, zone, frame = stack[k]
        for x in stack[k:]:
            open_at[x[0]].pop()
        del stack[k:]

    at, raw = 0, ""
    for m in _TOKEN.finditer(page):
        if m.start() < at:
            continue
        if not raw:
            words.append(page[at : m.start()])
        at = m.end()
        name = (m[2] or "").lower()
        if raw:
            if m[1] and name == raw:
                raw = ""
            continue
        if not name:
            continue
        if name in BLOCKS or name in RAW:
            flush()
        if m[1]:
            if open_at.get(name):
                close(open_at[name][-1])
            continue
        if name in RAW:
            if not m[3].rstrip().endswith("/"):
                end = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
                at = end.end() if end else len(page)
            continue
        if name in VOID:
            continue
        while stack and stack[-1][0] in CLOSES.get(name, ()):
            close(len(stack) - 1)
        if name in BLOCKS and name != "p" and open_at.get("p"):
            close(open_at["p"][0])
        open_at.setdefault(name, []).append(len(stack))
        stack.append((name, zone, frame))
        frame = frame or _framed(name, m[3], zone)
        zone = zone or name in ZONES or 'role="main"' in m[3].lower()
    words.append(page[at:])
    flush()
    return out


def line_hash(text: str) -> int:
    return xxhash.xxh3_64_intdigest(text.encode()) - (1 << 63)


def shared_lines(mine: list[int], theirs: list[int]) -> set[int]:
    """Places in ``mine`` of a longest common subsequence with ``theirs`` (Hunt and Szymanski's method)."""
    start = 0
    while start < min(len(mine), len(theirs)) and mine[start] == theirs[start]:
        start += 1
    tail = 0
    while tail < min(len(mine), len(theirs)) - start and mine[-1 - tail] == theirs[-1 - tail]:
        tail += 1
    out = set(range(start)) | set(range(len(mine) - tail, len(mine)))
    places: dict[int, list[int]] = {}
    for j in range(len(theirs) - tail - 1, start - 1, -1):
        places.setdefault(theirs[j], []).append(j)
    ends: list[int] = []
    chains: list[tuple | None] = []
    for i in range(start, len(mine) - tail):
        for j in places.get(mine[i], ()):
            lo, hi = 0, len(ends)
            while lo < hi:
                mid = (lo + hi) // 2
                if ends[mid] < j:
                    lo = mid + 1
                else:
                    hi = mid
            chain = (i, chains[lo - 1] if lo else None)
            if lo == len(ends):
                ends.append(j)
                chains.append(chain)
            else:
                ends[lo], chains[lo] = j, chain
    node = chains[-1] if chains else None
    while node:
        out.add(node[0])
        node = node[1]
    return out


def main_text(page: str | None, neighbours: list[list[int]]) -> tuple[str, int, int]:
    """(text, number of lines deleted by differencing, number deleted as named frame)."""
    lines = lines_of(page)
    zoned = any(z and not f for _, z, f in lines)
    hashes = [line_hash(t) for t, _, _ in lines]
    shared: set[int] = set()
    open_lines = sum(not z and not f for _, z, f in lines)
    for other in neighbours:
        common = {i for i in shared_lines(hashes, other) if not lines[i][1]}
        # a copy of the whole page says nothing about its frame
        if not open_lines or sum(not lines[i][2] for i in common) < open_lines:
            shared |= common
    kept, framed = [], 0
    for i, (text, zone, frame) in enumerate(lines):
        if i in shared:
            continue
        if frame or (zoned and not zone):
            framed += 1
        else:
            kept.append(text)
    return "\n".join(kept), len(shared), framed


def _hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = [[line_hash(t) for t, _, _ in lines_of(x.as_py())] for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.int64()))], ["other", "lines"])


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = [main_text(page.as_py(), others.as_py() or []) for page, others in zip(batch.column(2), batch.column(3), strict=True)]
        columns = [batch.column(0), batch.column(1), pa.array([r[0] for r in rows], pa.string()), pa.array([len(r[0]) for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.int32())]
        yield pa.RecordBatch.from_arrays(columns, ["page_id", "url", "text", "n_chars", "n_shared", "n_framed"])


def _adjacent(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Neighbours within a sorted partition; its first and last row are told once more, for the seams."""
    last = first = None
    for pdf in frames:
        rows = []
        for host, path, page in zip(pdf["host"], pdf["path"], pdf["page_id"], strict=True):
            if last is None:
                first = (host, path, page)
            elif last[0] == host and last[2] != page:
                rows += [(page, last[2], None, None, 0), (last[2], page, None, None, 0)]
            last = (host, path, page)
        if rows:
            yield pd.DataFrame(rows, columns=["page_id", "other", "host", "path", "seam"])
    if first:
        yield pd.DataFrame([(first[2], None, first[0], first[1], 1), (last[2], None, last[0], last[1], 2)], columns=["page_id", "other", "host", "path", "seam"]).astype({"other": "Int64"})


def nearest_pages(pages: DataFrame) -> DataFrame:
    """(page_id, other): for each page the pages next to it in the order of path, then page_id, within its host.

    Only keys are sorted; partitions meet at seams, of which there are two rows each, joined on the driver.
    """
    spark = pages.sparkSession
    url = F.col("url")
    host = F.lower(F.regexp_extract(url, _SCHEME, 1))
    path = F.regexp_replace(F.regexp_replace(url, _SCHEME, ""), r"[?#].*$", "")
    keys = pages.where("page_id is not null").select("page_id", host.alias("host"), path.alias("path")).where("host != ''").dropDuplicates()
    placed = keys.repartitionByRange("host", "path", "page_id").sortWithinPartitions("host", "path", "page_id")
    told = materialise(placed.mapInPandas(_adjacent, "page_id long, other long, host string, path string, seam int"), "adjacent")
    seams = sorted((r.host, r.path, r.page_id, r.seam) for r in told.where("seam > 0").collect())
    joins = []
    for one, two in zip(seams, seams[1:], strict=False):
        if one[3] == 2 and two[3] == 1 and one[0] == two[0] and one[2] != two[2]:
            joins += [(one[2], two[2]), (two[2], one[2])]
    return told.where("seam = 0").select("page_id", "other").union(spark.createDataFrame(joins, "page_id long, other long")).distinct()


def extract_main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row of (page_id, url, html); also how many lines each step deleted.

    Null or empty html gives an empty text. Pages without a host, or without another page on it, and pages with a null
    page_id are not differenced; the rest holds for them. Pages of one host with the same path are next to each other by
    page_id. Rows that repeat a page_id are each extracted, with the neighbours of all of them. Very long pages are taken whole,
    in proportion to their length (and, in alignment, to the pairs of equal lines). Other columns are ignored; an empty table
    gives an empty result.
    """
    workers(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    pairs = nearest_pages(rows)
    hashes = rows.where("page_id is not null").select("page_id", "html").mapInArrow(_hashes, "other long, lines array<long>")
    others = pairs.join(hashes, "other").groupBy("page_id").agg(F.sort_array(F.collect_list("lines")).alias("others"))
    joined = rows.join(others, "page_id", "left").select("page_id", "url", "html", "others")
    return joined.mapInArrow(_extract, "page_id long, url string, text string, n_chars long, n_shared int, n_framed int")
