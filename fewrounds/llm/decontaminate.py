"""Benchmark decontamination with a generalised suffix automaton.

The test items' words form one automaton.  The words of each document are streamed through it and the length of the
longest suffix that some item contains is tracked; where it reaches ``window`` words (or a whole shorter item) the
words are hit.  Stretches whose neighbouring words never stand together in any item are passed over without being
streamed, because no match of the wanted length can lie in them.

Items are handled in blocks of at most ``block_bytes`` of text.  One block, the usual case, is broadcast and the
documents are scanned once; further blocks cost a scan each, and their hits are united per document.

Defined results: null texts have no words; items without words, text or id hit nothing; rows are judged alone, so ids
may repeat or be null; an empty table of items leaves all documents clean.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textnum as tn
from .spool import kept

WINDOW = 10
BLOCK_BYTES = 8 << 20


def item_words(text: str | None) -> np.ndarray:
    data, offsets = tn.strings(pa.array([text or ""]))
    return tn.words_of(data, offsets, tn.FOLDED_SEPARATORS, lower=True).hash


@dataclass
class Automaton:
    """Substrings of all items, over word numbers."""

    window: int
    vocabulary: np.ndarray  # sorted word hashes
    pairs: np.ndarray  # sorted numbers of neighbouring words
    shortest: int
    step: list[dict[int, int]]
    link: list[int]
    length: list[int]
    whole: dict[int, list[str]]  # items that hold the window of a state
    short: dict[int, list[tuple[int, str]]]  # shorter items that end in a state

    @classmethod
    def build(cls, items: list[tuple[str, np.ndarray]], window: int) -> Automaton | None:
        items = [(k, h) for k, h in items if len(h)]
        if not items:
            return None
        vocabulary = np.unique(np.concatenate([h for _, h in items]))
        numbered = [(k, np.searchsorted(vocabulary, h)) for k, h in items]
        pairs = np.unique(np.concatenate([a[:-1] * len(vocabulary) + a[1:] for _, a in numbered]))
        step, link, length = [{}], [-1], [0]

        def add(last: int, c: int) -> int:
            if c in step[last]:
                q = step[last][c]
                return q if length[q] == length[last] + 1 else split(last, c, q)
            new = len(step)
            step.append({})
            link.append(0)
            length.append(length[last] + 1)
            p = last
            while p >= 0 and c not in step[p]:
                step[p][c] = new
                p = link[p]
            if p >= 0:
                q = step[p][c]
                link[new] = q if length[q] == length[p] + 1 else split(p, c, q)
            return new

        def split(p: int, c: int, q: int) -> int:
            twin = len(step)
            step.append(dict(step[q]))
            link.append(link[q])
            length.append(length[p] + 1)
            link[q] = twin
            while p >= 0 and step[p].get(c) == q:
                step[p][c] = twin
                p = link[p]
            return twin

        for _, a in numbered:
            at = 0
            for c in a.tolist():
                at = add(at, c)
        made = cls(window, vocabulary, pairs, min(window, min(len(a) for _, a in numbered)), step, link, length, {}, {})
        for k, a in numbered:
            at = 0
            for i, c in enumerate(a.tolist()):
                at = step[at][c]
                if i + 1 >= window:
                    made.whole.setdefault(made.held(at, window), []).append(k)
            if len(a) < window:
                made.short.setdefault(made.held(at, len(a)), []).append((len(a), k))
        return made

    def held(self, state: int, n: int) -> int:
        """The state of the last n words of what a state stands for."""
        while self.length[self.link[state]] >= n:
            state = self.link[state]
        return state

    def stream(self, numbers: list[int], first: int, hits: list[tuple[int, int]], items: set[str]) -> None:
        """Adds the hit ranges (of word places from ``first`` on) and items of a stretch of words."""
        step, link, length, window = self.step, self.link, self.length, self.window
        at = have = 0
        for i, c in enumerate(numbers, first):
            while at and c not in step[at]:
                at = link[at]
                have = length[at]
            if c not in step[at]:
                continue
            at = step[at][c]
            have += 1
            if have >= window:
                hits.append((i - have + 1, i + 1))
                items.update(self.whole.get(self.held(at, window), ()))
            if self.short:
                state, most = at, have
                while state:
                    for n, k in self.short.get(state, ()):
                        if n <= most:
                            hits.append((i - n + 1, i + 1))
                            items.add(k)
                    state = link[state]
                    most = length[state]

    def scan(self, w: tn.Words) -> tuple[np.ndarray, list[set[str]]]:
        """Which words are hit, and the items found, by document."""
        found: list[set[str]] = [set() for _ in w.counts]
        hit = np.zeros(len(w.doc), bool)
        at = np.minimum(np.searchsorted(self.vocabulary, w.hash), len(self.vocabulary) - 1)
        known = self.vocabulary[at] == w.hash
        if self.shortest < 2:
            stretch = known
        else:
            code = at[:-1] * len(self.vocabulary) + at[1:]
            near = np.minimum(np.searchsorted(self.pairs, code), len(self.pairs) - 1)
            stretch = known[:-1] & known[1:] & (self.pairs[near] == code) & (w.doc[:-1] == w.doc[1:]) if len(self.pairs) else np.zeros(max(0, len(at) - 1), bool)
        edge = np.diff(np.concatenate([[0], stretch.astype(np.int8), [0]]))
        for begin, end in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
            end += self.shortest >= 2
            if end - begin < self.shortest:
                continue
            starts = begin + np.flatnonzero(np.diff(w.doc[begin:end], prepend=-1))  # documents may meet when single words count
            for b, e in zip(starts.tolist(), [*starts[1:].tolist(), end], strict=True):
                hits: list[tuple[int, int]] = []
                self.stream(at[b:e].tolist(), b, hits, found[w.doc[b]])
                for x, y in hits:
                    hit[x:y] = True
        return hit, found


def blocks(items: DataFrame, window: int, block_bytes: int = BLOCK_BYTES) -> Iterator[Automaton]:
    """Automata of bounded size that hold all items."""
    rows = items.select(F.col("item_id").cast("string").alias("k"), "text").where("item_id IS NOT NULL AND text IS NOT NULL")
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-size // block_bytes))
    for b in range(n):
        part = rows if n == 1 else rows.where(F.pmod(F.xxhash64("k"), F.lit(n)) == b)
        made = Automaton.build([(r["k"], item_words(r["text"])) for r in part.collect()], window)
        if made is not None:
            yield made


def _blocks_ahead(items: DataFrame, window: int, block_bytes: int) -> tuple[Automaton | None, Iterator[Automaton] | None]:
    """The only automaton (None without items), or all of several."""
    made = blocks(items, window, block_bytes)
    first, second = next(made, None), next(made, None)
    return (first, None) if second is None else (None, chain([first, second], made))


def _by_blocks(spark: SparkSession, automata: Iterator[Automaton], scan) -> DataFrame:
    """The united rows of scan(broadcast automaton) for each automaton.  Each pass is written before the next automaton
    is built, so that executors hold one at a time."""
    parts = None
    for automaton in automata:
        own = spark.sparkContext.broadcast(automaton)
        one = kept(scan(own))
        own.destroy()
        parts = one if parts is None else parts.unionByName(one)
    return parts


def _ranges(hit: np.ndarray) -> list[list[int]]:
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return np.stack([np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)], 1).tolist()


def _result(n_words: int, ranges: list[list[int]], items: set[str]) -> tuple:
    n_hit = sum(e - b for b, e in ranges)
    return n_hit, len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), n_hit > 0


SCHEMA = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, spans array<array<long>>, items array<string>"


def find(docs: DataFrame, items: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per document; spans: ranges of hit words; items: ids of the items found."""
    context = docs.sparkSession.sparkContext
    first, rest = _blocks_ahead(items, window, block_bytes)

    def scanner(own):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            automaton = own.value
            for part, data, offsets in tn.batched(batches, "text"):
                w = tn.words_of(data, offsets, tn.FOLDED_SEPARATORS, lower=True)
                hit, found = automaton.scan(w) if automaton else (np.zeros(len(w.doc), bool), [set()] * len(w.counts))
                ends = np.cumsum(w.counts)
                total = np.zeros(len(hit) + 1, np.int64)
                np.cumsum(hit, out=total[1:])
                some = total[ends] > total[ends - w.counts]
                spans = [_ranges(hit[e - n : e]) if s else [] for e, n, s in zip(ends.tolist(), w.counts.tolist(), some.tolist(), strict=True)]
                made = [_result(n, r, k) for n, r, k in zip(w.counts.tolist(), spans, found, strict=True)]
                columns = [pa.array([m[k] for m in made], kind) for k, kind in enumerate((pa.int64(), pa.int64(), pa.string(), pa.bool_()))]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).cast(pa.int64()), pa.array(w.counts, pa.int64()), *columns, pa.array(spans, pa.list_(pa.list_(pa.int64()))), pa.array([sorted(k) for k in found], pa.list_(pa.string()))],
                    ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "spans", "items"],
                )

        return run

    if rest is None:
        return docs.select("doc_id", "text").mapInArrow(scanner(context.broadcast(first)), SCHEMA)
    # more items than one block holds: unite what the blocks found, row by row
    rows = docs.select("doc_id", "text")
    keyed = rows.withColumn("row_key", F.xxhash64("text"))

    def marker(own):
        run = scanner(own)

        def with_key(batches):
            for batch in batches:
                key, done = batch.column(2), 0
                for out in run(iter([pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["doc_id", "text"])])):
                    yield pa.RecordBatch.from_arrays([*out.columns, key.slice(done, out.num_rows)], [*out.schema.names, "row_key"])
                    done += out.num_rows

        return with_key

    parts = _by_blocks(docs.sparkSession, rest, lambda own: keyed.mapInArrow(marker(own), SCHEMA + ", row_key long"))
    copies = keyed.groupBy("doc_id", "row_key").agg(F.count(F.lit(1)).alias("copies"))
    united = parts.groupBy("doc_id", "row_key", "n_words").agg(F.array_distinct(F.flatten(F.collect_list("spans"))).alias("spans"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"))

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                hit = np.zeros(r["n_words"], bool)
                for b, e in r["spans"]:
                    hit[b:e] = True
                spans = _ranges(hit)
                a = _result(r["n_words"], spans, set(r["items"]))
                out += [dict(zip(("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "spans", "items"), (r["doc_id"], r["n_words"], *a, spans, sorted(r["items"])), strict=True))] * r["copies"]
            yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_()), ("spans", pa.list_(pa.list_(pa.int64()))), ("items", pa.list_(pa.string()))]))

    same = united["doc_id"].eqNullSafe(copies["doc_id"]) & united["row_key"].eqNullSafe(copies["row_key"])
    return united.join(copies, same).select(united["doc_id"], "n_words", "spans", "items", "copies").mapInArrow(finish, SCHEMA)


def _without(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray, w: tn.Words, hit: np.ndarray, max_coverage: float) -> pa.RecordBatch:
    """The rows without their hit words, and without the rows that are hit too much."""
    if not hit.any():
        return part
    n_hit = np.bincount(w.doc[hit], minlength=len(w.counts))
    texts, raw = part.column(part.schema.get_field_index("text")).to_pylist(), data.tobytes()
    ends = np.cumsum(w.counts)
    for d in np.flatnonzero(n_hit).tolist():
        b, e, left, at = int(ends[d] - w.counts[d]), int(ends[d]), [], int(offsets[d])
        for x, y in _ranges(hit[b:e]):
            left.append(raw[at : int(w.starts[b + x])])
            at = int(w.starts[b + y]) if b + y < e else int(w.ends[b + y - 1])
        texts[d] = b"".join([*left, raw[at : int(offsets[d + 1])]]).decode("utf-8")
    columns = dict(zip(part.schema.names, part.columns, strict=True))
    columns["text"] = pa.array(texts, part.schema.field("text").type)
    if "n_chars" in columns:
        n = columns["n_chars"].to_pylist()
        columns["n_chars"] = pa.array([len(texts[d]) if n_hit[d] else n[d] for d in range(len(n))], part.schema.field("n_chars").type)
    return pa.RecordBatch.from_arrays(list(columns.values()), schema=part.schema).filter(pa.array(n_hit <= max_coverage * w.counts))


def remove_spans(docs: DataFrame, items: DataFrame, window: int = WINDOW, max_coverage: float = 0.5, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The documents without their hit spans; one whose hit words exceed ``max_coverage`` of all its words goes as a
    whole.  All columns stay; ``n_chars``, if there, follows the new text of a changed row.

    With several blocks of items the rows are written once and numbered; every block scans the texts as they came, and
    each row is cut and judged once by all its hits, so the answer does not depend on ``block_bytes``.
    """
    first, rest = _blocks_ahead(items, window, block_bytes)
    if first is None and rest is None:
        return docs
    if rest is None:
        own = docs.sparkSession.sparkContext.broadcast(first)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part, data, offsets in tn.batched(batches, "text"):
                w = tn.words_of(data, offsets, tn.FOLDED_SEPARATORS, lower=True)
                yield _without(part, data, offsets, w, own.value.scan(w)[0], max_coverage)

        return docs.mapInArrow(run, docs.schema)

    names = docs.columns
    row, hits = (next(n for n in (base + "_" * k for k in range(len(names) + 1)) if n not in names) for base in ("_row", "_spans"))

    def marker(own):
        def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part, data, offsets in tn.batched(batches, "text"):
                w = tn.words_of(data, offsets, tn.FOLDED_SEPARATORS, lower=True)
                hit, _ = own.value.scan(w)
                some = np.unique(w.doc[hit])
                ends = np.cumsum(w.counts)
                spans = [_ranges(hit[ends[d] - w.counts[d] : ends[d]]) for d in some.tolist()]
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(some, pa.int64())), pa.array(spans, pa.list_(pa.list_(pa.int64())))], [row, hits])

        return mark

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            w = tn.words_of(data, offsets, tn.FOLDED_SEPARATORS, lower=True)
            hit = np.zeros(len(w.doc), bool)
            begins = np.cumsum(w.counts) - w.counts
            for begin, spans in zip(begins.tolist(), part.column(part.schema.get_field_index(hits)).to_pylist(), strict=True):
                for x, y in spans or ():
                    hit[begin + x : begin + y] = True
            yield _without(part.select(names), data, offsets, w, hit, max_coverage)

    rows = kept(docs.withColumn(row, F.monotonically_increasing_id()))
    parts = _by_blocks(docs.sparkSession, rest, lambda own: rows.select(row, "text").mapInArrow(marker(own), f"{row} long, {hits} array<array<long>>"))
    united = parts.groupBy(row).agg(F.flatten(F.collect_list(hits)).alias(hits))
    return rows.join(united, row, "left").select(*names, hits).mapInArrow(finish, docs.schema)
