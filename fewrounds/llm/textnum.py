"""Vectorised text kernel: words, hashes and windows of whole Arrow string columns.

Every function works on the raw UTF-8 bytes of many documents at once, so no Python loop runs per word or
per document.  Null strings count as empty.  Long texts are hashed in pieces that are cut between words, so
scratch memory stays at some tens of megabytes whatever the length of one document.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

_libc = ctypes.CDLL(None)
U64 = np.uint64
PIECE = 1 << 20  # bytes hashed at a time

_WHITE = np.zeros(256, bool)
_WHITE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: Bytes that end a word of the plain kind: space and 0x09 to 0x0D.
WHITE_SEPARATORS = _WHITE
#: Bytes that end a word of the folded kind: ASCII other than letters and digits.
FOLDED_SEPARATORS = np.array([b < 0x80 and not chr(b).isalnum() for b in range(256)])


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (public-domain splitmix64 constants)."""
    x = np.asarray(x, U64).copy()
    with np.errstate(over="ignore"):
        x += U64(0x9E3779B97F4A7C15)
        x ^= x >> U64(30)
        x *= U64(0xBF58476D1CE4E5B9)
        x ^= x >> U64(27)
        x *= U64(0x94D049BB133111EB)
        x ^= x >> U64(31)
    return x


def byte_values(seed: int, lower: bool = False) -> np.ndarray:
    """A random odd value for each byte; with ``lower``, capitals A to Z take their small letter's value."""
    v = mix(np.arange(256, dtype=U64) + U64(seed * 1000 + 1)) | U64(1)
    if lower:
        v[65:91] = v[97:123]
    return v


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}
_BASES = (0x2545F4914F6CDD1D, 0x9FB21C651E98DF25)


def _tables(n: int, which: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64."""
    have = _powers.get(which)
    if have is None or len(have[0]) < n:
        base = _BASES[which]
        inverse = pow(base, -1, 1 << 64)
        size = max(n, PIECE + (1 << 16))
        out = []
        for b in (base, inverse):
            t = np.full(size, b, U64)
            t[0] = 1
            with np.errstate(over="ignore"):
                np.multiply.accumulate(t, out=t)
            out.append(t)
        have = (out[0], out[1])
        if n <= PIECE + (1 << 16):
            _powers[which] = have
    return have


def strings(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets (one more than rows) of a string column."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_null(column.type):
        column = column.cast(pa.string())
    if column.null_count:
        column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, offsets, data = column.buffers()
    if offsets is None or not len(column):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, at - at[0]


def slices(offsets: np.ndarray, limit: int = PIECE, rows: int = 50_000) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes; a longer text is a range of its own."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1
        j = min(max(j, i + 1), n, i + rows)
        yield i, j
        i = j


def give_back() -> None:
    """Returns freed memory to the system: a worker process serves many tasks, and what it keeps adds up."""
    pa.default_memory_pool().release_unused()
    if (trim := getattr(_libc, "malloc_trim", None)) is not None:
        trim(0)


def batched(batches: Iterator[pa.RecordBatch], column: str, limit: int = PIECE) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices of the batches with the bytes and offsets of one string column."""
    for batch in batches:
        data, offsets = strings(batch.column(batch.schema.get_field_index(column)))
        for i, j in slices(offsets, limit):
            yield batch.slice(i, j - i), data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        del batch, data, offsets
        give_back()


@dataclass
class Words:
    """Words of several documents in order: byte ranges, document index, hashes."""

    starts: np.ndarray
    ends: np.ndarray
    doc: np.ndarray
    counts: np.ndarray
    hashes: list[np.ndarray]

    @property
    def hash(self) -> np.ndarray:
        return self.hashes[0]


def spans(data: np.ndarray, offsets: np.ndarray, separators: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte starts and ends of the words; no word crosses a document's end."""
    inside = ~separators[data]
    if not len(inside):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    cut = offsets[(offsets > 0) & (offsets < len(inside))]
    before = np.empty_like(inside)
    before[0], before[1:] = False, inside[:-1]
    before[cut] = False
    after = np.empty_like(inside)
    after[-1], after[:-1] = False, inside[1:]
    after[cut - 1] = False
    return np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1


def range_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, values: np.ndarray, which: int = 0) -> np.ndarray:
    """A 64-bit hash of each byte range; ranges are in order and don't overlap."""
    out = np.empty(len(starts), U64)
    i = 0
    while i < len(starts):
        low = starts[i]
        j = int(np.searchsorted(ends, low + PIECE, "right"))
        j = max(j, i + 1)
        high = ends[j - 1]
        power, inverse = _tables(int(high - low) + 1, which)
        with np.errstate(over="ignore"):
            total = np.zeros(int(high - low) + 1, U64)
            np.cumsum(values[data[low:high]] * power[: high - low], out=total[1:])
            out[i:j] = (total[ends[i:j] - low] - total[starts[i:j] - low]) * inverse[starts[i:j] - low]
        i = j
    return mix(out + (ends - starts).astype(U64))


def words_of(data: np.ndarray, offsets: np.ndarray, separators: np.ndarray = WHITE_SEPARATORS, lower: bool = False, hashes: int = 1) -> Words:
    starts, ends = spans(data, offsets, separators)
    doc = np.searchsorted(offsets, starts, "right") - 1
    made = [range_hashes(data, starts, ends, byte_values(k, lower), k) for k in range(hashes)]
    return Words(starts, ends, doc, np.bincount(doc, minlength=len(offsets) - 1), made)


_STEPS = mix(np.arange(1, 4097, dtype=U64)) | U64(1)


def joined(parts: list[np.ndarray], salt: int = 0) -> np.ndarray:
    """One hash from several equally long arrays of hashes, in their order."""
    with np.errstate(over="ignore"):
        total = np.full(len(parts[0]), salt, U64)
        for k, p in enumerate(parts):
            total += p * _STEPS[k]
    return mix(total)


def grown(h: np.ndarray, have: int, want: int) -> np.ndarray:
    """Hashes of windows of ``want`` words from those of ``have`` words (have <= want <= 2 * have): a window of the
    longer length is given by the two shorter ones at its start and at its end."""
    n = max(0, len(h) - (want - have))
    return joined([h[:n], h[want - have : want - have + n]], want)


def windows(w: Words, length: int, which: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Start indices and hashes of the windows of ``length`` words that lie within one document, by doubling."""
    h, have = w.hashes[which], 1
    while have < length:
        want = min(2 * have, length)
        h, have = grown(h, have, want), want
    if len(w.doc) < length:
        return np.zeros(0, np.int64), np.zeros(0, U64)
    whole = np.flatnonzero(w.doc[: len(w.doc) - length + 1] == w.doc[length - 1 :])
    return whole, h[whole]


def covered(n: int, starts: np.ndarray, length: int | np.ndarray) -> np.ndarray:
    """Which of n places lie in a range that begins at ``starts`` and has ``length`` places."""
    change = np.zeros(n + 1, np.int64)
    np.add.at(change, starts, 1)
    np.add.at(change, starts + length, -1)
    return np.cumsum(change[:-1]) > 0
