"""Token counts by overlap resynchronisation.

A text longer than ``chunk`` characters is encoded in overlapping chunks with offsets.  Two neighbouring chunks are
spliced at a pre-token boundary that both found inside their overlap, away from the left chunk's end.  Such a boundary
is proven stable: the splitting pattern looks at no text before the place where it stands, and what ends more than
``MARGIN`` characters before a chunk's end cannot have been changed by the cut.  Where no common boundary exists the
overlap is doubled, in the end to the whole rest of the text.

Short texts go through the library in batches.  If the tokenizer file is a byte-level BPE whose ids follow its merges,
texts below U+0500 use a rank-based encoder made from the same file, which gives the same tokens faster; all other
texts, and all other files, use the tokenizers library itself.

Defined results: a null text counts as empty (0 bytes, 0 tokens); null or repeated ids are kept as they are.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import textnum as tn

CHUNK, OVERLAP = 1 << 16, 1 << 10
#: Longer than any special string or contraction whose recognition looks past a boundary.
MARGIN = 64
#: Fixed value: the splitting pattern of the byte-level pre-tokenizer.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class Counter:
    """Counts tokens as the library does for one tokenizer file."""

    def __init__(self, path: str, chunk: int = CHUNK, overlap: int = OVERLAP):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.chunk, self.overlap = chunk, overlap
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        special = [x["content"] for x in spec.get("added_tokens") or []]
        self.margin = max([MARGIN, *(2 * len(x) for x in special)])
        plain = not any(x[k] for x in spec.get("added_tokens") or [] for k in ("single_word", "lstrip", "rstrip", "normalized"))
        before = spec.get("pre_tokenizer") or {}
        #: Chunks may be cut only where splitting looks forward alone.
        self.forward = spec.get("normalizer") is None and before.get("type") == "ByteLevel" and not before.get("add_prefix_space") and before.get("use_regex", True) and plain
        self.special = re.compile("|".join(map(re.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.fast = self._ranked(spec) if self.forward else None

    @staticmethod
    def _ranked(spec: dict):
        """A rank-based encoder if the ids of merged tokens follow the order of the merges."""
        import tiktoken

        model = spec["model"]
        if model.get("type") != "BPE" or any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges", "byte_fallback")):
            return None
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        letter = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
        added = {x["content"] for x in spec.get("added_tokens") or []}
        vocab = {k: v for k, v in model["vocab"].items() if k not in added}
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        ids = [vocab.get(a + b) for a, b in merges]
        if None in ids or any(x >= y for x, y in zip(ids, ids[1:], strict=False)) or len(ids) + 256 != len(vocab) or any(c not in letter for k in vocab for c in k):
            return None
        ranks = {bytes(letter[c] for c in k): v for k, v in vocab.items()}
        if sum(len(k) == 1 for k in ranks) != 256 or max(v for k, v in ranks.items() if len(k) == 1) > min(ids):
            return None
        return tiktoken.Encoding("ranks", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})

    def short(self, text: str) -> int:
        if self.special is None:
            return len(self.fast.encode_ordinary(text))
        at, n = 0, 0
        for m in self.special.finditer(text):
            n += len(self.fast.encode_ordinary(text[at : m.start()])) + 1
            at = m.end()
        return n + len(self.fast.encode_ordinary(text[at:] if at else text))

    def _bounds(self, text: str) -> tuple[dict[int, int], int]:
        """Pre-token starts with the number of tokens before each; tokens in all."""
        e = self.library.encode(text, add_special_tokens=False)
        found, last = {}, None
        for k, ((begin, _), word) in enumerate(zip(e.offsets, e.word_ids, strict=True)):
            if word != last or word is None:
                found.setdefault(begin, k)
                last = word
        return found, len(e.ids)

    def long(self, text: str) -> int:
        """Tokens of a text by chunks that are spliced where both sides agree."""
        if not self.forward or len(text) <= self.chunk:
            return len(self.library.encode(text, add_special_tokens=False).ids)
        total, at = 0, 0
        while True:
            end, overlap = at + self.chunk, self.overlap
            if end >= len(text):
                return total + len(self.library.encode(text[at:], add_special_tokens=False).ids)
            left, _ = self._bounds(text[at:end])
            while True:
                # the right chunk begins ``overlap`` before the left one's end
                begin = max(at + 1, end - overlap)
                right, _ = self._bounds(text[begin : end + self.margin])
                common = [p for p in right if at < begin + p <= end - self.margin and begin + p - at in left]
                if common:
                    p = begin + max(common)
                    total += left[p - at]
                    at = p
                    break
                if begin == at + 1:  # no boundary in the whole chunk: take a longer one
                    end = min(len(text), at + 2 * (end - at))
                    if end == len(text):
                        return total + len(self.library.encode(text[at:], add_special_tokens=False).ids)
                    left, _ = self._bounds(text[at:end])
                overlap *= 2

    def counts(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        out = np.zeros(len(offsets) - 1, np.int64)
        high = np.zeros(len(data) + 1, np.int64)
        np.cumsum(data >= 0xD4, out=high[1:])  # lead bytes from U+0500 on
        rare = high[offsets[1:]] > high[offsets[:-1]]
        size = np.diff(offsets)
        raw, slow = data.tobytes(), []
        for i in np.flatnonzero(size):
            text = raw[offsets[i] : offsets[i + 1]].decode("utf-8")
            if len(text) > self.chunk:
                out[i] = self.long(text)
            elif self.fast is None or rare[i]:
                slow.append((i, text))
            else:
                out[i] = self.short(text)
        if slow:
            for (i, _), e in zip(slow, self.library.encode_batch_fast([t for _, t in slow], add_special_tokens=False), strict=True):
                out[i] = len(e.ids)
        return out


@lru_cache(maxsize=4)
def counter(path: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> Counter:
    return Counter(path, chunk, overlap)


def count_tokens(docs: DataFrame, path: str, limit: int = 512, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row.  ``path``: a tokenizer file present on every executor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(path, chunk, overlap)
        for part, data, offsets in tn.batched(batches, "text"):
            n = c.counts(data, offsets)
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(np.diff(offsets)), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
