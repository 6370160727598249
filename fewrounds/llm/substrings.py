"""Substring deduplication by windows of growing length.

A word goes if a window of ``length`` words covers it whose word sequence also starts in a document with a smaller id.

Level 1 looks at windows of half the length.  Not all are needed: among the half-length windows inside each full
window the one with the least hash stands for it, so equal full windows always have equal stand-ins.  Stand-ins that
start in two documents survive.  Level 2 extends only the survivors to the full length, where each document learns
which of its windows start in a smaller document.  ``levels`` goes on from there: at each level a window of twice the
length is looked at only if both its halves survived, its number comes from theirs and no text is read again, and it
ends at the level where nothing survives.

Skew: a task first compares its own documents.  A window that several of them share is decided for all but the first
(level 2) or all but the outer two (level 1) on the spot, so the group of one window gets two rows of a task at most,
however often a passage occurs.  Exact copies are found by a digest of the whole text and skip both levels.

Windows are compared by 64 bits on level 1, which only chooses candidates, and by 96 bits on level 2.

Defined results: null texts have no words; a row without id is returned unchanged and neither gives nor takes windows;
rows that share an id are one document for "smaller id" but are cut each by its own text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textnum as tn
from .spool import kept

LENGTH = 13
FLUSH = 1_000_000  # windows that a task compares at once
_TOP = np.iinfo(np.uint64).max


def stand_ins(w: tn.Words, half: int, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Starts of the full windows; the start of each one's stand-in; starts and hashes of all stand-ins."""
    full, _ = _starts(w, length)
    if not len(full):
        return full, full, full, np.zeros(0, np.uint64)
    at, h = tn.windows(w, half)
    by_place = np.full(len(w.doc), _TOP, np.uint64)
    by_place[at] = h
    span = length - half + 1
    best = np.lib.stride_tricks.sliding_window_view(by_place, span)[full].argmin(1) + full
    chosen = np.unique(best)
    return full, best, chosen, by_place[chosen]


def _starts(w: tn.Words, length: int) -> tuple[np.ndarray, None]:
    if len(w.doc) < length:
        return np.zeros(0, np.int64), None
    return np.flatnonzero(w.doc[: len(w.doc) - length + 1] == w.doc[length - 1 :]), None


def _firsts(*keys: np.ndarray) -> np.ndarray:
    """Where a new group begins in sorted keys."""
    new = np.zeros(len(keys[0]), bool)
    if len(new):
        new[0] = True
        for k in keys:
            new[1:] |= k[1:] != k[:-1]
    return new


class _Pool:
    """Windows of a task's documents, sent on as rows (g, c, doc_id, more).

    A row without ``more`` says that window (g, c) starts in doc_id and is undecided.  A row with ``more`` holds the
    hashes of decided windows of doc_id."""

    def __init__(self, keep: int):
        self.keep = keep  # 1: only the smallest document of a window stays undecided; 2: the smallest and the largest
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.size = 0

    def add(self, g: np.ndarray, c: np.ndarray, doc: np.ndarray) -> None:
        self.parts.append((g, c, doc))
        self.size += len(g)

    def flush(self) -> Iterator[pa.RecordBatch]:
        if not self.size:
            return
        g, c, doc = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        self.parts, self.size = [], 0
        order = np.lexsort((doc, c, g))
        g, c, doc = g[order], c[order], doc[order]
        once = _firsts(g, c, doc)
        g, c, doc = g[once], c[once], doc[once]
        head = _firsts(g, c)
        open_ = head.copy()
        if self.keep == 2:
            open_[:-1] |= head[1:]
            open_[-1] = True
        yield self._rows(g[open_], c[open_], doc[open_], None)
        g, doc = g[~open_], doc[~open_]
        if len(g):
            order = np.argsort(doc, kind="stable")
            g, doc = g[order], doc[order]
            heads = np.flatnonzero(_firsts(doc))
            blobs = [g[b:e].tobytes() for b, e in zip(heads.tolist(), [*heads[1:].tolist(), len(g)], strict=True)]
            own = doc[heads]
            yield self._rows(tn.mix(own.view(np.uint64)), np.zeros(len(own), np.int32), own, blobs)

    @staticmethod
    def _rows(g: np.ndarray, c: np.ndarray, doc: np.ndarray, more: list[bytes] | None) -> pa.RecordBatch:
        blobs = pa.nulls(len(g), pa.binary()) if more is None else pa.array(more, pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(g.view(np.int64)), pa.array(c, pa.int32()), pa.array(doc), blobs], ["g", "c", "doc_id", "more"])


_ROWS = "g long, c int, doc_id long, more binary"


def _ids(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    column = part.column(0).cast(pa.int64())
    return column.fill_null(0).to_numpy(zero_copy_only=False), column.is_valid().to_numpy(zero_copy_only=False)


def _hash_set(lists: list | None, blobs: list | None) -> np.ndarray:
    own = np.array(lists or [], np.int64).view(np.uint64)
    return np.unique(np.concatenate([own, *(np.frombuffer(b, np.uint64) for b in blobs or [])]))


def _decided(rows: DataFrame, later_only: bool) -> DataFrame:
    """doc_id, hashes, blobs: what each document has of the windows that start in a smaller document (``later_only``) or
    in any other document, and of those that were decided before.

    The rows of a window come sorted by document and stream past: its first document is all that is held of it, and the
    first row waits until another document is seen."""

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = None  # the window the last batch ended in: g, c, its first document, and whether that row waits
        for batch in batches:
            if not batch.num_rows:
                continue
            g, c, doc = (batch.column(k).to_numpy() for k in range(3))
            head = _firsts(g, c)
            goes_on = first is not None and first[0] == g[0] and first[1] == c[0]
            group = np.cumsum(head) - 1
            least = doc[head]
            if goes_on:
                least[0] = first[2]
            later = doc != least[group]
            more = batch.column(3).is_valid().to_numpy(zero_copy_only=False)
            several = np.zeros(len(least), bool)
            several[group[later]] = True
            waits = goes_on and first[3]
            alive = more | later
            if not later_only:
                alive |= several[group]
                if goes_on and not first[3]:
                    alive[group == 0] = True
                if waits and several[0]:
                    yield pa.RecordBatch.from_arrays([pa.array([first[2]], pa.int64()), pa.array([first[0]], pa.int64()), pa.array([None], pa.binary())], ["doc_id", "g", "more"])
            settled = several[-1] or (len(least) == 1 and goes_on and not first[3])
            first = (g[-1], c[-1], least[-1], not settled)
            keep = pa.array(alive)
            yield pa.RecordBatch.from_arrays([batch.column(2).filter(keep), batch.column(0).filter(keep), batch.column(3).filter(keep)], ["doc_id", "g", "more"])

    seen = rows.repartition("g", "c").sortWithinPartitions("g", "c", "doc_id").mapInArrow(judge, "doc_id long, g long, more binary")
    return seen.groupBy("doc_id").agg(F.collect_list(F.when(F.col("more").isNull(), F.col("g"))).alias("hashes"), F.collect_list("more").alias("blobs"))


def _candidates(texts: DataFrame, half: int, length: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pool = _Pool(2)
        for part, data, offsets in tn.batched(batches, "text"):
            ids, _ = _ids(part)
            w = tn.words_of(data, offsets)
            _, _, at, h = stand_ins(w, half, length)
            pool.add(h, np.zeros(len(h), np.int32), ids[w.doc[at]])
            if pool.size >= FLUSH:
                yield from pool.flush()
        yield from pool.flush()

    return _decided(texts.where("doc_id IS NOT NULL").mapInArrow(run, _ROWS), later_only=False)


def _extended(joined: DataFrame, half: int, length: int) -> DataFrame:
    """Full windows around the survivors (columns hashes and blobs) of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pool = _Pool(1)
        some = (b.filter(pa.array((b.column(2).is_valid()).to_numpy(zero_copy_only=False))) for b in batches)
        for part, data, offsets in tn.batched(some, "text"):
            ids, _ = _ids(part)
            w = tn.words_of(data, offsets, hashes=2)
            full, best, at, h = stand_ins(w, half, length)
            if not len(full):
                continue
            alive = np.zeros(len(w.doc), bool)
            bound = np.searchsorted(w.doc[at], np.arange(len(ids) + 1))
            for d, (hashes, blobs) in enumerate(zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True)):
                b, e = bound[d], bound[d + 1]
                if e > b:
                    known = _hash_set(hashes, blobs)
                    if len(known):
                        near = np.minimum(np.searchsorted(known, h[b:e]), len(known) - 1)
                        alive[at[b:e]] = known[near] == h[b:e]
            take = alive[best]
            _, long_h = tn.windows(w, length)
            _, check = tn.windows(w, length, 1)
            pool.add(long_h[take], (check[take] >> np.uint64(33)).astype(np.int32), ids[w.doc[full[take]]])
            if pool.size >= FLUSH:
                yield from pool.flush()
        yield from pool.flush()

    return _decided(joined.select("doc_id", "text", "hashes", "blobs").mapInArrow(run, _ROWS), later_only=True)


def _copies(texts: DataFrame) -> DataFrame:
    """doc_id and is_copy (true) of documents whose whole text a smaller document has."""
    own = texts.where("doc_id IS NOT NULL AND text IS NOT NULL").select("doc_id", F.xxhash64("text").alias("a"), F.md5("text").alias("b"))
    first = kept(own.groupBy("a", "b").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").drop("last"))
    return own.join(first, ["a", "b"]).where("doc_id > first").select("doc_id").distinct().withColumn("is_copy", F.lit(True))


def _cut(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray, length: int) -> tuple[tn.Words, np.ndarray]:
    """The words of some rows with columns hashes, blobs, is_copy, and which of them go."""
    w = tn.words_of(data, offsets)
    at, h = tn.windows(w, length)
    bound = np.searchsorted(w.doc[at], np.arange(len(w.counts) + 1))
    hit = np.zeros(len(at), bool)
    column = {name: part.column(part.schema.get_field_index(name)).to_pylist() for name in ("hashes", "blobs", "is_copy")}
    for d, (hashes, blobs, copy) in enumerate(zip(column["hashes"], column["blobs"], column["is_copy"], strict=True)):
        b, e = bound[d], bound[d + 1]
        if copy:
            hit[b:e] = True
        elif e > b and (hashes or blobs):
            known = _hash_set(hashes, blobs)
            near = np.minimum(np.searchsorted(known, h[b:e]), len(known) - 1)
            hit[b:e] = known[near] == h[b:e]
    return w, tn.covered(len(w.doc), at[hit], length)


def _flagged(docs: DataFrame, length: int) -> DataFrame:
    """doc_id, text with the hashes of the windows that go."""
    texts = docs.select("doc_id", "text")
    half = max(1, length // 2)
    copies = _copies(texts)
    alive = _candidates(texts, half, length).join(copies, "doc_id", "left_anti")
    joined = texts.join(alive, "doc_id", "left")  # left like the last join, so that both read one exchange of the texts
    gone = _extended(joined, half, length).join(copies, "doc_id", "full_outer")
    return texts.join(gone, "doc_id", "left")


def dedup(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (of the kept words joined by one space) and kept_text for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            w, gone = _cut(part, data, offsets, length)
            texts = kept_texts(w, gone, data)
            removed = np.bincount(w.doc[gone], minlength=len(w.counts))
            shas = [hashlib.sha256(t).hexdigest() for t in texts]
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(w.counts, pa.int64()), pa.array(removed, pa.int64()), pa.array(shas, pa.string()), pa.array([t.decode("utf-8") for t in texts], pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"])

    return _flagged(docs, length).mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string")


def kept_texts(w: tn.Words, gone: np.ndarray, data: np.ndarray) -> list[bytes]:
    """The kept words of each document joined by one space, for all documents of a slice at once."""
    starts, ends, doc = w.starts[~gone], w.ends[~gone], w.doc[~gone]
    size = ends - starts + 1  # with a space behind
    upto = np.concatenate([[0], np.cumsum(size)])
    where = np.repeat(starts - upto[:-1], size) + np.arange(upto[-1])
    out = np.where(np.arange(upto[-1]) == np.repeat(upto[1:] - 1, size), 0x20, data[np.minimum(where, max(len(data) - 1, 0))]).astype(np.uint8).tobytes()
    bound = upto[np.searchsorted(doc, np.arange(len(w.counts) + 1))]
    return [out[b : e - 1] if e > b else b"" for b, e in zip(bound[:-1].tolist(), bound[1:].tolist(), strict=True)]


def _alive(hashes: list | None, blobs: list | None, h: np.ndarray) -> np.ndarray:
    """Which of the hashes are among the survivors of a document."""
    known = _hash_set(hashes, blobs)
    if not len(known) or not len(h):
        return np.zeros(len(h), bool)
    return known[np.minimum(np.searchsorted(known, h), len(known) - 1)] == h


_GRID = "doc_id long, at binary, h binary, check binary"


def _grid(rows: list[tuple]) -> pa.RecordBatch:
    """Places, hashes and second hashes of documents' windows."""
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), *(pa.array([r[k].tobytes() for r in rows], pa.binary()) for k in (1, 2, 3))], ["doc_id", "at", "h", "check"])


def _survivors(grid: DataFrame) -> DataFrame:
    """The windows of a grid that start in more than one document."""

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pool = _Pool(2)
        for batch in batches:
            for doc, h, check in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                h, check = np.frombuffer(h, np.uint64), np.frombuffer(check, np.uint64)
                pool.add(h, (check >> np.uint64(33)).astype(np.int32), np.full(len(h), doc, np.int64))
                if pool.size >= FLUSH:
                    yield from pool.flush()
        yield from pool.flush()

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, at, h, check, hashes, blobs in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                at, h, check = np.frombuffer(at, np.int64), np.frombuffer(h, np.uint64), np.frombuffer(check, np.uint64)
                some = _alive(hashes, blobs, h)
                if some.any():
                    rows.append((doc, at[some], h[some], check[some]))
            yield _grid(rows)

    alive = _decided(grid.mapInArrow(deal, _ROWS), later_only=False)
    return grid.join(alive, "doc_id").mapInArrow(keep, _GRID)


def _doubled(grid: DataFrame, length: int) -> DataFrame:
    """The windows of twice the length both of whose halves are in the grid."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, at, h, check in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                at, h, check = np.frombuffer(at, np.int64), np.frombuffer(h, np.uint64), np.frombuffer(check, np.uint64)
                after = np.searchsorted(at, at + length)
                both = np.flatnonzero(at[np.minimum(after, len(at) - 1)] == at + length)
                if len(both):
                    second = after[both]
                    rows.append((doc, at[both], *(tn.mix(tn.mix(x[both]) + (x[second] ^ np.uint64(length))) for x in (h, check))))
            yield _grid(rows)

    return grid.mapInArrow(run, _GRID)


def levels(docs: DataFrame, first: int = LENGTH) -> DataFrame:
    """length, n_docs, n_windows: by doubled length, how many documents hold windows that also start in another
    document, and at how many places.  Ends where nothing survives.  Rows that share an id are one document."""
    half = max(1, first // 2)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            w = tn.words_of(data, offsets, hashes=2)
            full, best, at, h = stand_ins(w, half, first)
            alive = np.zeros(len(w.doc), bool)
            bound = np.searchsorted(w.doc[at], np.arange(len(w.counts) + 1))
            for d, (hashes, blobs) in enumerate(zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True)):
                alive[at[bound[d] : bound[d + 1]]] = _alive(hashes, blobs, h[bound[d] : bound[d + 1]])
            take = np.flatnonzero(alive[best]) if len(full) else full
            _, long_h = tn.windows(w, first)
            _, check = tn.windows(w, first, 1)
            bound = np.searchsorted(w.doc[full[take]], np.arange(len(w.counts) + 1))
            ids = part.column(0).to_pylist()
            yield _grid([(ids[d], full[own], long_h[own], check[own]) for d in range(len(ids)) if len(own := take[bound[d] : bound[d + 1]])])

    texts = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    grid = kept(_survivors(kept(texts.join(_candidates(texts, half, first), "doc_id").mapInArrow(cut, _GRID))))
    out, length = [], first
    while True:
        row = grid.agg(F.count_distinct("doc_id"), F.coalesce(F.sum(F.length("h") / 8).cast("long"), F.lit(0))).first()
        if not row[0]:
            break
        out.append((length, row[0], row[1]))
        grid, length = kept(_survivors(kept(_doubled(grid, length)))), 2 * length
    return docs.sparkSession.createDataFrame(out, "length int, n_docs long, n_windows long")
