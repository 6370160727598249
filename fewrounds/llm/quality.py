"""Quality rules by repetition coverage.

Rolling hashes of several n-gram lengths measure how many characters of a text lie inside n-grams and lines that
occur more than once in it.  A text fails the base rules if it has fewer than ``min_words`` words or if more than
``max_repeat`` of its words lie in repeated windows; it fails the coverage rules if, for some n, the characters of
repeated n-grams exceed that n's share of all word characters, or if repeated lines do.

Defined results: null and blank texts have no words and fail the base rules; ids may be null or repeated (each row is
judged alone); an empty table gives an empty table; other columns of the input are ignored by ``measure`` and kept by
``keep_good``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import textnum as tn

#: The largest share, in percent, of word characters inside repeated n-grams, by n (published web-text rules).
NGRAM_LIMITS = {5: 15, 6: 14, 7: 13, 8: 12, 9: 11, 10: 10}

_SYMBOLS = np.zeros(256, np.int64)
_SYMBOLS[list(b"#*$%&|<>")] = 1


@dataclass(frozen=True)
class QualityRules:
    min_words: int = 10
    window: int = 5
    max_repeat: int = 20  # percent of words in repeated windows
    ngram_limits: dict[int, int] = field(default_factory=lambda: dict(NGRAM_LIMITS))
    max_line_chars: int = 30  # percent of word characters in repeated lines


def _per_doc(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Sums of consecutive groups of the given sizes."""
    total = np.zeros(len(values) + 1, np.int64)
    np.cumsum(values, out=total[1:])
    ends = np.cumsum(counts)
    return total[ends] - total[ends - counts]


def _repeated(doc: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Which (document, hash) pairs occur twice or more."""
    with np.errstate(over="ignore"):
        key = tn.mix(h + doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    ordered = np.sort(key)
    twice = ordered[1:][ordered[1:] == ordered[:-1]]
    if not len(twice):
        return np.zeros(len(h), bool)
    at = np.minimum(np.searchsorted(twice, key), len(twice) - 1)
    return twice[at] == key


def _lines(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and document of all lines; a text always has one line at least."""
    breaks = np.flatnonzero(data == 0x0A)
    starts = np.sort(np.concatenate([offsets[:-1], breaks + 1]), kind="stable")
    ends = np.sort(np.concatenate([offsets[1:], breaks]), kind="stable")
    doc = np.repeat(np.arange(len(offsets) - 1), np.bincount(np.searchsorted(offsets, breaks, "right") - 1, minlength=len(offsets) - 1) + 1)
    return starts, ends, doc


def measures(data: np.ndarray, offsets: np.ndarray, rules: QualityRules) -> dict[str, np.ndarray]:
    n = len(offsets) - 1
    w = tn.words_of(data, offsets)
    chars = np.zeros(len(data) + 1, np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=chars[1:])
    word_chars = chars[w.ends] - chars[w.starts]
    out = {"n_words": w.counts.astype(np.int64), "word_chars": _per_doc(word_chars, w.counts)}
    symbols = np.zeros(len(data) + 1, np.int64)
    np.cumsum(_SYMBOLS[data], out=symbols[1:])
    out["n_symbols"] = symbols[offsets[1:]] - symbols[offsets[:-1]]

    starts, ends, doc = _lines(data, offsets)
    first, last = np.searchsorted(w.starts, starts), np.searchsorted(w.starts, ends)
    full = last > first
    starts, ends, doc, first, last = starts[full], ends[full], doc[full], first[full], last[full]
    h = tn.range_hashes(data, starts, ends, tn.byte_values(2))
    order = np.lexsort((h, doc))  # stable: an earlier line comes first
    again = np.zeros(len(h), bool)
    again[order[1:]] = (h[order[1:]] == h[order[:-1]]) & (doc[order[1:]] == doc[order[:-1]])
    out["n_dup_lines"] = np.bincount(doc[again], minlength=n).astype(np.int64)
    upto = np.zeros(len(word_chars) + 1, np.int64)
    np.cumsum(word_chars, out=upto[1:])
    dup_line_chars = np.bincount(doc[again], weights=(upto[last] - upto[first])[again], minlength=n).astype(np.int64)

    at, h = tn.windows(w, rules.window)
    hit = _repeated(w.doc[at], h)
    out["n_repeat_words"] = _per_doc(tn.covered(len(w.doc), at[hit], rules.window), w.counts)
    words, repeat = out["n_words"], out["n_repeat_words"]
    failed = (words < rules.min_words) | (100 * repeat > rules.max_repeat * words)
    good = ~failed & (100 * dup_line_chars <= rules.max_line_chars * out["word_chars"])
    out["dup_line_chars"] = dup_line_chars
    for k, limit in sorted(rules.ngram_limits.items()):
        long_at, long_h = tn.windows(w, k)
        if k > rules.window:  # a longer n-gram repeats only where its first window does
            maybe = np.isin(long_at, at[hit], assume_unique=True)
            long_at, long_h = long_at[maybe], long_h[maybe]
        inside = tn.covered(len(w.doc), long_at[_repeated(w.doc[long_at], long_h)], k)
        share = _per_doc(word_chars * inside, w.counts)
        out[f"dup_chars_{k}"] = share
        good &= 100 * share <= limit * out["word_chars"]
    out["base_failed"], out["kept"] = failed, good
    return out


def measure(docs: DataFrame, rules: QualityRules | None = None) -> DataFrame:
    """One row per document: doc_id, the measures, base_failed and kept."""
    rules = rules or QualityRules()
    lengths = sorted(rules.ngram_limits)
    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, dup_line_chars long" + "".join(f", dup_chars_{k} long" for k in lengths)
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            m = measures(data, offsets, rules)
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), *(pa.array(m[x]) for x in names[1:])], names)

    return docs.select("doc_id", "text").mapInArrow(run, schema)


def keep_good(docs: DataFrame, rules: QualityRules | None = None) -> DataFrame:
    """The rows whose text passes all rules, with all columns."""
    rules = rules or QualityRules()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in tn.batched(batches, "text"):
            yield part.filter(pa.array(measures(data, offsets, rules)["kept"]))

    return docs.mapInArrow(run, docs.schema)
