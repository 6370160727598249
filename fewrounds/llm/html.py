"""Main text of web pages by nearest-URL page differencing, with the page's own structure as a hint.

Pages of one host are put in order of their URL path; each is compared with the pages before and after it.  The text
lines of two neighbours are aligned by a longest common subsequence, and the lines they share, menus, notices, adverts
and the like, are deleted.  The structure says which lines this decides about:

* DROPPED, by element or by an unmistakable name (navigation, footers, forms, adverts, comments): goes in any case, and
  so does what follows the heading of a comment section.
* HINTED, by a name that articles use too (notice, related, share and so on): goes outside an article; inside one it
  goes if a neighbour has the line as well.
* ARTICLE, unmarked lines of an article: stay, since two articles may quote the same lines.
* LOOSE, all other lines: go if a neighbour has them.  Where the page has an article, a loose line stays only if
  neighbours were compared, none has it, and it is as long as a paragraph (``PARAGRAPH`` words).

A neighbour that has nearly all of a page's text is a copy and tells nothing about menus, so it isn't compared.

Only hashes and lengths of lines travel for the comparison.  The order is made by range partitioning, so a host of any
size spreads over many tasks; pages at the edges of partitions, two a partition, meet their neighbours in a join.  The
scanner passes over a page once, whatever is left open in it.

Defined results: null or empty html gives the empty text; a page without url has no neighbours; equal rows get equal
results; an empty table gives an empty table; other columns are not looked at.
"""

from __future__ import annotations

import html as entities
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .spool import kept

#: Elements and names of parts that are not main text, and elements that begin a block.
RAW = set("script style noscript template svg iframe object canvas audio video textarea select button math head".split())
OUTSIDE = set("nav footer aside form menu dialog input fieldset".split())
OUTSIDE_ROLES = set("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
OUTSIDE_NAMES = set(
    "nav navbar navigation menu main-menu site-nav sidebar side-bar footer site-footer page-footer masthead site-header page-header ad ads advert adverts advertisement adsense ad-box ad-slot "
    "sponsor sponsored cookie cookies cookie-banner cookie-notice cookie-bar consent gdpr popup modal overlay newsletter subscribe signup login comment comments comment-list comments-area "
    "reader-comments disqus disqus_thread replies respond breadcrumb breadcrumbs pagination pager toolbar skip-link".split()
)
HINT_NAMES = set("banner notice promo promoted share sharing share-bar social social-links related related-posts recommended widget label site-notice".split())
BLOCKS = set("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split())
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
CLOSES_P = BLOCKS - {"body", "html"}
COMMENTS = re.compile(r"(?:\d+ )?(?:reader |user )?(?:comments?|replies|responses|kommentare?|commentaires?|comentarios?)(?: ?\(\d+\)| ?: ?\d+)?|leave a (?:comment|reply)|post a comment", re.I)
PARAGRAPH = 25  # words
COPY = 0.8  # share of a page's loose text that makes a neighbour a copy

_NAME = re.compile(r"[a-zA-Z][^\s/>]*")
_KEY = re.compile(r"[\s/]*([^\s/>=][^\s/>=]*)?(\s*=\s*)?")
_VALUE = re.compile(r"[^\s>]*")
_BODY = re.compile(r"<body\b", re.I)
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_WHITE = re.compile(r"\s+")

DROPPED, LOOSE, ARTICLE, HINTED = 0, 1, 2, 3


class _Scanner:
    """Tags and texts of a page in one pass.  What was looked for once in vain isn't looked for again."""

    def __init__(self, page: str):
        self.page, self.missing = page, set()

    def _find(self, what: str, at: int) -> int:
        if what in self.missing:
            return -1
        k = self.page.find(what, at)
        if k < 0:
            self.missing.add(what)
        return k

    def _close_raw(self, name: str, at: int) -> int:
        """Behind the end of a raw element; one that never ends goes up to the body, or else to the page's end."""
        if name not in self.missing:
            m = re.compile(rf"</{name}\s*>", re.I).search(self.page, at)
            if m:
                return m.end()
            self.missing.add(name)
        if "<body" not in self.missing:
            m = _BODY.search(self.page, at)
            if m:
                return m.start()
            self.missing.add("<body")
        return len(self.page)

    def _attributes(self, at: int) -> tuple[list[tuple[str, str]], int, bool]:
        """Names and values from a place inside a tag, the place behind the tag, and whether it closes itself."""
        page, out, slash = self.page, [], False
        while True:
            m = _KEY.match(page, at)
            at = m.end()
            if at >= len(page):
                return out, len(page), slash
            if m[1] is None and m[2] is None:
                if page[at] == ">":
                    return out, at + 1, page[at - 1] == "/"
                at += 1  # a stray sign
                continue
            name = (m[1] or "").lower()
            if m[2] is None:
                out.append((name, ""))
                continue
            quote = page[at] if at < len(page) else ""
            if quote in ('"', "'") and (end := self._find(quote, at + 1)) >= 0:
                out.append((name, page[at + 1 : end]))
                at = end + 1
            else:
                v = _VALUE.match(page, at)
                out.append((name, v[0].strip("\"'")))
                at = v.end()

    def tokens(self) -> Iterator[tuple]:
        """(text, None, ...) or (None, name, is end, attributes, closes itself)."""
        page, at, done = self.page, 0, 0
        while (k := page.find("<", at)) >= 0:
            mark = page[k + 1 : k + 2]
            end = mark == "/"
            m = _NAME.match(page, k + 2 if end else k + 1) if end or mark.isalpha() else None
            if m is None and mark not in ("!", "?", "/"):
                at = k + 1  # a plain sign
                continue
            if k > done:
                yield page[done:k], None, False, (), False
            if m is None:  # comments and declarations
                stop = "-->" if page.startswith("<!--", k) else "]]>" if page.startswith("<![CDATA[", k) else ">"
                e = self._find(stop, k + 2)
                at = done = len(page) if e < 0 else e + len(stop)
                continue
            name, at = m[0].lower(), m.end()
            if page[at : at + 1] == ">":
                attributes, closed = (), False
                at += 1
            else:
                attributes, at, closed = self._attributes(at)
            if name in RAW and not end:
                if not closed or name not in ("svg", "math"):
                    at = self._close_raw(name, at)
            else:
                yield None, name, end, attributes, closed
            done = at
        if done < len(page):
            yield page[done:], None, False, (), False


def _role(tag: str, attributes: list[tuple[str, str]], now: int) -> int:
    if tag in OUTSIDE or (tag == "header" and now != ARTICLE):
        return DROPPED
    own, is_article = now, tag in ("article", "main")
    for name, value in attributes:
        if name == "hidden" or (name == "aria-hidden" and value.lower() == "true") or (name == "style" and _HIDDEN.search(value)):
            return DROPPED
        if name == "role":
            if value.lower() in OUTSIDE_ROLES:
                return DROPPED
            is_article |= value.lower() in ("main", "article")
        elif name in ("class", "id") and tag not in ("body", "html"):
            names = set(value.lower().split())
            if names & OUTSIDE_NAMES:
                if tag not in ("article", "main") or names & {"comment", "comments", "ad", "ads", "advert", "sponsored"}:
                    return DROPPED
            elif names & HINT_NAMES and tag not in ("article", "main"):
                own = HINTED
        elif name == "itemprop" and value.lower() == "articlebody":
            is_article = True
    return ARTICLE if is_article else own


def blocks(page: str) -> list[tuple[int, str]]:
    """(role, text) of the blocks of a page, in page order.  A hinted block outside any article counts as dropped."""
    out: list[tuple[int, str]] = []
    stack: list[tuple[str, int]] = []
    words: list[str] = []
    opened: Counter[str] = Counter()
    now = LOOSE
    inside = lambda: opened["article"] + opened["main"] > 0

    def leave(k: int) -> None:
        nonlocal now
        now = stack[k][1]
        opened.subtract(t for t, _ in stack[k:])
        del stack[k:]

    def close(tag: str = "") -> None:
        nonlocal now
        if not words:
            return
        text = _WHITE.sub(" ", entities.unescape("".join(words))).strip()
        words.clear()
        if not text:
            return
        if tag in HEADINGS and now != DROPPED and COMMENTS.fullmatch(text):
            now = DROPPED  # until the part that holds the heading ends
            if stack:
                stack[-1] = (stack[-1][0], DROPPED)
            return
        out.append((DROPPED if now == HINTED and not inside() else now, text))

    for text, tag, end, attributes, closed in _Scanner(page).tokens():
        if tag is None:
            words.append(text)
            continue
        if tag == "br":
            words.append(" ")
            continue
        if tag in BLOCKS:
            close(tag if end else "")
        if end:
            if opened[tag] > 0:
                k = next(k for k in range(len(stack) - 1, -1, -1) if stack[k][0] == tag)
                if stack[k][1] != now:
                    close()
                leave(k)
        elif tag not in VOID and not closed:
            if tag in CLOSES_P:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == "p":
                        leave(k)
                        break
                    if stack[k][0] in BLOCKS:
                        break
            role = _role(tag, attributes, now) if now != DROPPED else DROPPED
            if role != now:
                close()
            stack.append((tag, now))
            opened[tag] += 1
            now = role
    close()
    return out


def judged_lines(found: list[tuple[int, str]]) -> list[str]:
    """The lines that differencing looks at: all but the unmarked ones of the article."""
    return [t for role, t in found if role != ARTICLE]


def aligned(a: list[int], b: list[int]) -> set[int]:
    """Places of ``a`` in a longest common subsequence of a and b."""
    where: dict[int, list[int]] = {}
    for j, x in enumerate(b):
        where.setdefault(x, []).append(j)
    tails: list[int] = []
    ends: list[tuple] = []
    for i, x in enumerate(a):
        for j in reversed(where.get(x, ())):
            k = bisect_left(tails, j)
            node = (i, ends[k - 1] if k else None)
            if k == len(tails):
                tails.append(j)
                ends.append(node)
            else:
                tails[k], ends[k] = j, node
    out, node = set(), ends[-1] if ends else None
    while node:
        out.add(node[0])
        node = node[1]
    return out


def main_text(found: list[tuple[int, str]], shared: set[int] | list[int] = (), compared: bool = False) -> str:
    """The kept blocks, two line ends between them.  ``shared``: places among the judged lines that neighbours have;
    ``compared``: whether there was a neighbour to compare with."""
    gone, place, out = set(shared), -1, []
    has_article = any(role == ARTICLE for role, _ in found)
    for role, text in found:
        if role == ARTICLE:
            out.append(text)
            continue
        place += 1
        if role == DROPPED or place in gone:
            continue
        if role == HINTED or not has_article or (compared and len(text.split(" ")) >= PARAGRAPH):
            out.append(text)
    return "\n\n".join(out)


def _line_hash(text: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(text.encode()) - (1 << 63)


def shared_places(lines: list[int], sizes: list[int], other: list[int]) -> set[int] | None:
    """Places of the lines that a neighbour has; None if the neighbour is a copy."""
    places = aligned(lines, other)
    whole = sum(sizes)
    return None if whole and sum(sizes[k] for k in places) > COPY * whole else places


def shared_lines(pages: DataFrame) -> DataFrame:
    """page_id, row_key, shared (places of judged lines that a neighbour by URL has too) and compared (neighbours)."""

    def outline(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lines = [judged_lines(blocks(p)) if p else [] for p in batch.column(4).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array([[_line_hash(t) for t in x] for x in lines], pa.list_(pa.int64())), pa.array([[len(t) for t in x] for x in lines], pa.list_(pa.int32()))], ["host", "path", "page_id", "row_key", "lines", "sizes"])

    bare = F.regexp_replace("url", "^[A-Za-z][A-Za-z0-9+.-]*://", "")
    named = pages.where("url IS NOT NULL").select(F.lower(F.regexp_extract(bare, "^([^/?#]*)", 1)).alias("host"), F.regexp_extract(bare, "^[^/?#]*([^?#]*)", 1).alias("path"), "page_id", F.xxhash64("url", "html").alias("row_key"), "html")
    outlined = kept(named.mapInArrow(outline, "host string, path string, page_id long, row_key long, lines array<long>, sizes array<int>"))
    ordered = outlined.repartitionByRange("host", "path", "page_id", "row_key").sortWithinPartitions("host", "path", "page_id", "row_key")

    def judge(row: tuple, others: list[tuple]) -> tuple[list[int], int]:
        shared: set[int] = set()
        seen = 0
        for other in others:
            if other is not None and other[0] == row[0] and (places := shared_places(row[4], row[5], other[4])) is not None:
                shared |= places
                seen += 1
        return sorted(shared), seen

    # a row of an edge table: part, is_last and the page's outline, for pages whose other neighbour is in another part
    kinds = [("page_id", pa.int64()), ("row_key", pa.int64()), ("shared", pa.list_(pa.int32())), ("compared", pa.int32()), ("part", pa.int32()), ("is_last", pa.bool_()), ("host", pa.string()), ("lines", pa.list_(pa.int64())), ("sizes", pa.list_(pa.int32()))]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        own = TaskContext.get().partitionId()
        before = waiting = None
        rows: list[tuple] = []

        def edge(row: tuple, is_last: bool) -> tuple:
            return row[2], row[3], None, 0, own, is_last, row[0], row[4], row[5]

        def packed() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, (_, t) in enumerate(kinds)], [n for n, _ in kinds])
            rows.clear()
            return out

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if waiting is not None and row[:4] == waiting[:4]:
                    continue  # a repeated row
                if waiting is None:
                    rows.append(edge(row, False))
                else:
                    rows.append((waiting[2], waiting[3], *judge(waiting, [before, row]), None, None, None, None, None))
                    before = waiting
                waiting = row
            if rows:
                yield packed()
        if waiting is not None:
            rows.append((waiting[2], waiting[3], *judge(waiting, [before]), None, None, None, None, None))
            rows.append(edge(waiting, True))
            yield packed()

    inner = kept(ordered.mapInArrow(compare, "page_id long, row_key long, shared array<int>, compared int, part int, is_last boolean, host string, lines array<long>, sizes array<int>"))
    edges = inner.where("part IS NOT NULL")
    parts = sorted(r["part"] for r in edges.where("is_last").select("part").collect())  # one number a partition
    following = pages.sparkSession.createDataFrame(list(zip(parts, parts[1:], strict=False)), "part int, after int")
    low = edges.where("is_last").select("part", *(F.col(c).alias(f"a_{c}") for c in ("page_id", "row_key", "host", "lines", "sizes")))
    high = edges.where("NOT is_last").select(F.col("part").alias("after"), *(F.col(c).alias(f"b_{c}") for c in ("page_id", "row_key", "host", "lines", "sizes")))
    across = low.join(following, "part").join(high, "after").where("a_host = b_host").select(*(c for c in low.columns if c != "part"), *(c for c in high.columns if c != "after"))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                for x, y in ((r[:5], r[5:]), (r[5:], r[:5])):
                    places = shared_places(x[3], x[4], y[3])
                    if places is not None:
                        out.append((x[0], x[1], sorted(places), 1))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, (_, t) in enumerate(kinds[:4])], [n for n, _ in kinds[:4]])

    met = across.mapInArrow(meet, "page_id long, row_key long, shared array<int>, compared int")
    return inner.where("part IS NULL").drop("part", "is_last", "host", "lines", "sizes").unionByName(met)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row."""
    rows = pages.select("page_id", "url", "html", F.when(F.col("url").isNotNull(), F.xxhash64("url", "html")).alias("row_key"))
    found = shared_lines(rows).groupBy(F.col("page_id").alias("_page"), "row_key").agg(F.flatten(F.collect_list("shared")).alias("shared"), F.sum("compared").alias("compared"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(blocks(p), shared or (), bool(seen)) if p else "" for p, shared, seen in zip(*(batch.column(k).to_pylist() for k in (2, 3, 4)), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(1), pa.array(texts, pa.string()), pa.array(np.array([len(t) for t in texts], np.int64))], ["page_id", "url", "text", "n_chars"])

    same = rows["page_id"].eqNullSafe(found["_page"]) & (rows["row_key"] == found["row_key"])
    return rows.join(found, same, "left").select("page_id", "url", "html", "shared", "compared").mapInArrow(run, "page_id long, url string, text string, n_chars long")
