"""Main text of web pages: nearest-URL page differencing, with markup's vote on what it leaves.

A page is cut into blocks of text, one a line. Pages of a host are put in the order of their paths and each is paired with its
neighbours; the longest common subsequence of the pair's lines outside articles is what the site repeats, and these lines are deleted.
What only one page has is left to markup, which gives each block a role: *kept* inside an article or main element,
*dropped* inside navigation, page headers and footers, sidebars, forms, scripts, notices, adverts and reader comments,
and *open* where it does not say; of the lines that differ, dropped ones go and open ones stay. Lines
inside an article are never deleted, since two pages may carry the same article. ``n_shared`` and ``n_marked`` say how many lines went either way.

The order comes from a range partitioning by (host, path, id), so one large host is spread over many tasks;
pairs across the borders of partitions are made from the border pages alone. Pages are parsed once.

Defined results: a null or empty page has no text; cut-off markup is read as far as it goes; repeated rows are
neighbours of each other and keep their articles; extra columns are not read.
"""

from __future__ import annotations

import html
import re
import zlib
from collections.abc import Iterator
from urllib.parse import urlsplit

import numpy as np
import pandas as pd
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written

_tags = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S).finditer
_names = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I).finditer
# Elements without text of their own, elements of a page's frame, and elements that stay inside a line.
RAW = frozenset(("script", "style", "noscript", "template", "iframe", "svg", "textarea", "title", "object", "canvas", "math"))
FRAME = frozenset(("nav", "header", "footer", "aside", "form", "menu", "dialog", "button", "select", "head"))
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img input ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
NOTICE = re.compile(r"(?:^|[\s_-])(?:ad|ads|advert\w*|sponsor\w*|promo\w*|banner|cookie\w*|consent|notice\w*|alert|popup|modal|sidebar|side|nav\w*|menu\w*|breadcrumb\w*|footer|header|masthead|comment\w*|respond|disqus\w*|share|sharing|social\w*|related|recommend\w*|newsletter|subscribe|signup|widget\w*|pagination|pager|search\w*)(?:$|[\s_-])", re.I)
KEPT, OPEN, DROPPED = 2, 1, 0
CELLS = 20_000_000  # of lines by lines that are compared in one piece


def blocks(page: str | None) -> list[tuple[int, str]]:
    """(role, text) of each block, in page order; blocks without text are left out."""
    page = page or ""
    out: list[tuple[int, str]] = []
    parts: list[str] = []
    opened: list[tuple[str, int]] = []  # elements with a role of their own, and the role outside
    role, at = OPEN, 0

    def close() -> None:
        if parts:
            text = " ".join(html.unescape("".join(parts)).split())
            if text:
                out.append((role, text))
            parts.clear()

    skip_to = 0
    for match in _tags(page):
        if match.start() < skip_to:
            continue
        if match.start() > at:
            parts.append(page[at : match.start()])
        at = match.end()
        name = (match[2] or "").lower()
        if not name:
            continue
        if not match[1] and name in RAW:
            end = re.compile(rf"</{name}\s*>", re.I).search(page, at)
            at = skip_to = end.end() if end else len(page)
            continue
        if name in INLINE:
            if name == "br":
                parts.append(" ")
            continue
        close()
        if match[1]:
            for k in range(len(opened) - 1, -1, -1):
                if opened[k][0] == name:
                    role = opened[k][1]
                    del opened[k:]
                    break
            continue
        if name in VOID or match[3].endswith("/"):
            continue
        marks = " ".join(a or b or c for a, b, c in (m.groups() for m in _names(match[3]))) if match[3] else ""
        new = role
        if name in ("article", "main"):
            if role == OPEN and not NOTICE.search(marks):
                new = KEPT
            elif role == DROPPED and name == "main" or opened and opened[-1][0] in ("nav", "header", "head") and role == DROPPED:
                opened.clear()
                role, new = OPEN, KEPT
            elif NOTICE.search(marks):
                new = DROPPED
        elif name in FRAME and not (name == "header" and role == KEPT):
            new = DROPPED
        elif marks and name not in ("html", "body") and NOTICE.search(marks):
            new = DROPPED
        elif name == "body":
            opened.clear()
            role = new = OPEN
        opened.append((name, role))
        role = new
    if at < len(page):
        rest = page[at:]
        cut = rest.find("<")
        parts.append(rest if cut < 0 or not re.match(r"</?[a-zA-Z]", rest[cut:]) else rest[:cut])
    close()
    return out


def place(url: str | None) -> tuple[str, str]:
    """Host and path of an address."""
    try:
        split = urlsplit(url or "")
        return (split.netloc.rpartition("@")[2].lower(), split.path)
    except ValueError:
        return "", url or ""


def line_hash(text: str) -> int:
    return xxhash.xxh64_intdigest(text) - (1 << 63)


def _rows(a: list[int], b: list[int]) -> Iterator[int]:
    """For each line of b, a number whose bit k is 0 where the common subsequence with a[: k + 1] is longer than with a[:k]."""
    where: dict[int, int] = {}
    for k, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << k
    row = full = (1 << len(a)) - 1
    for y in b:
        u = row & where.get(y, 0)
        row = ((row + u) | (row - u)) & full
        yield row


def _lengths(a: list[int], b: list[int]) -> np.ndarray:
    """Length of the longest common subsequence of b with a[:k], for each k."""
    row = (1 << len(a)) - 1
    for row in _rows(a, b):
        pass
    bits = np.unpackbits(np.frombuffer(row.to_bytes(len(a) // 8 + 1, "little"), np.uint8), bitorder="little")[: len(a)]
    return np.concatenate(([0], np.cumsum(bits == 0)))


def common(a: list[int], b: list[int], most: int = CELLS) -> list[int]:
    """A longest common subsequence of two lists of lines, by bit-parallel rows; lists of more than ``most`` cells are split, so memory stays bounded."""
    n = 0
    while n < min(len(a), len(b)) and a[n] == b[n]:
        n += 1
    if n:
        return a[:n] + common(a[n:], b[n:], most)
    while n < min(len(a), len(b)) and a[-1 - n] == b[-1 - n]:
        n += 1
    if n:
        return common(a[:-n], b[:-n], most) + a[-n:]
    if not a or not b:
        return []
    if len(a) * len(b) > most and len(b) > 1:
        half = len(b) // 2
        at = int((_lengths(a, b[:half]) + _lengths(a[::-1], b[half:][::-1])[::-1]).argmax())
        return common(a[:at], b[:half], most) + common(a[at:], b[half:], most)
    rows = list(_rows(a, b))
    out, i, j = [], len(a) - 1, len(b) - 1
    while i >= 0 and j >= 0:
        if rows[j] >> i & 1:
            i -= 1
        elif j and not rows[j - 1] >> i & 1:
            j -= 1
        else:
            out.append(a[i])
            i, j = i - 1, j - 1
    return out[::-1]


_PARSED = "host string, path string, packed binary, outside array<long>"


def packed(found: list[tuple[int, str]]) -> bytes:
    """Roles of a page's blocks and the texts that may stay, compressed: they are stored and dealt once each."""
    return zlib.compress("\n".join(["".join(str(r) for r, _ in found), *(t for r, t in found if r != DROPPED)]).encode("utf-8", "surrogatepass"))


def left_over(page: bytes, outside, shared) -> tuple[str, int, int]:
    """text, n_shared, n_marked of a packed page; outside: hashes of its lines outside articles, shared: those that a neighbour has too."""
    roles, *texts = zlib.decompress(page).decode("utf-8", "surrogatepass").split("\n")
    lines, given, shared = iter(outside), iter(texts), set(shared)
    kept, n_shared, n_marked = [], 0, 0
    for role in map(int, roles):
        text = next(given) if role != DROPPED else None
        if role != KEPT and next(lines) in shared:
            n_shared += 1
        elif text is None:
            n_marked += 1
        else:
            kept.append(text)
    return "\n".join(kept), n_shared, n_marked


def parsed(pages: DataFrame, page_id: str = "page_id", url: str = "url", page: str = "html") -> DataFrame:
    """page_id, url, text_key, host, path, packed (blocks, dropped ones without their text), outside (hashes of lines outside articles)."""

    @F.pandas_udf(_PARSED)
    def of(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        for urls, htmls in parts:
            rows = []
            for u, h in zip(urls, htmls):
                found = blocks(h)
                rows.append((*place(u), packed(found), [line_hash(t) for r, t in found if r != KEPT]))
            yield pd.DataFrame(rows, columns=["host", "path", "packed", "outside"])

    base = pages.select(pages[page_id].alias("page_id"), pages[url].alias("url"), pages[page].alias("html"))
    return base.select("page_id", "url", F.xxhash64("url", "html").alias("text_key"), of("url", "html").alias("p")).select("page_id", "url", "text_key", "p.*")


def repeated_lines(lines: DataFrame) -> DataFrame:
    """page_id, text_key, shared: hashes of the lines that a page has in common with a neighbour of its host.

    lines: page_id, text_key, host, path, outside.
    """
    fields = "page_id long, text_key long, shared array<long>, part int, edge int, host string, outside array<long>"

    def pair(rows: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part = TaskContext.get().partitionId()
        last = None
        for frame in rows:
            out = []
            for i, k, host, outside in zip(frame["page_id"], frame["text_key"], frame["host"], frame["outside"]):
                outside = list(outside)
                if last is None:
                    out.append((i, k, [], part, 1, host, outside))
                elif last[2] == host:
                    same = common(last[3], outside)
                    if same:
                        out += [(last[0], last[1], same, part, 0, None, None), (i, k, same, part, 0, None, None)]
                last = (i, k, host, outside)
            yield pd.DataFrame(out, columns=["page_id", "text_key", "shared", "part", "edge", "host", "outside"])
        if last is not None:
            yield pd.DataFrame([(last[0], last[1], [], part, 2, last[2], last[3])], columns=["page_id", "text_key", "shared", "part", "edge", "host", "outside"])

    ordered = lines.repartitionByRange("host", "path", "page_id", "text_key").sortWithinPartitions("host", "path", "page_id", "text_key")
    found = ordered.select("page_id", "text_key", "host", "outside").mapInPandas(pair, fields)
    inner = found.where("edge = 0").select("page_id", "text_key", "shared")
    after = Window.orderBy("part", "edge")  # two rows for each partition
    border = found.where("edge > 0").select("*", *[F.lead(c).over(after).alias(f"next_{c}") for c in ("page_id", "text_key", "host", "outside", "part")])
    met = border.where("edge = 2 and host = next_host and part <> next_part")

    @F.pandas_udf("array<long>")
    def both(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([common(list(x), list(y)) for x, y in zip(a, b)])

    met = met.select("page_id", "text_key", "next_page_id", "next_text_key", both("outside", "next_outside").alias("shared"))
    edges = met.select("page_id", "text_key", "shared").unionByName(met.select(F.col("next_page_id").alias("page_id"), F.col("next_text_key").alias("text_key"), "shared"))
    return inner.unionByName(edges).select("page_id", "text_key", F.explode("shared").alias("line")).groupBy("page_id", "text_key").agg(F.collect_set("line").alias("shared"))


def main_text(pages: DataFrame, page_id: str = "page_id", url: str = "url", page: str = "html") -> DataFrame:
    """page_id, url, text, n_chars, n_shared, n_marked of every page; text is empty if there is none."""
    ready = written(parsed(pages, page_id, url, page))
    shared = repeated_lines(ready.select("page_id", "text_key", "host", "path", "outside")).select(F.col("page_id").alias("p"), F.col("text_key").alias("k"), "shared")
    joined = ready.select("page_id", "url", "text_key", "packed", "outside").join(shared, F.col("page_id").eqNullSafe(F.col("p")) & (F.col("text_key") == F.col("k")), "left")

    @F.pandas_udf("text string, n_shared long, n_marked long")
    def told(page: pd.Series, outside: pd.Series, repeats: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([left_over(*x) for x in zip(page, outside, repeats)], columns=["text", "n_shared", "n_marked"])

    out = joined.select("page_id", "url", told("packed", "outside", F.coalesce("shared", F.array().cast("array<long>"))).alias("t")).select("page_id", "url", "t.*")
    return out.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), "n_shared", "n_marked")
