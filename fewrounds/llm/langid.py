"""Language identification in two steps: the family by linear machines, then one-versus-one linear SVMs within it.

Features are counts of letter n-grams of one to three bytes, hashed into ``DIMENSIONS`` buckets, square-rooted and
normalised.  Fitting uses at most ``per_language`` labelled rows of each language, those with the smallest hash of
their id; everything else covers whole texts of all rows.

Defined results: a text that is null or has no letter gets ``und`` and score 0; with no labelled row at all every text
gets ``und``.  A language outside the table of families is a family of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textnum as tn

DIMENSIONS = 4096
PER_LANGUAGE = 600
#: Families of language codes.
FAMILIES = {
    "germanic": ["af", "da", "de", "en", "fy", "is", "lb", "nb", "nl", "nn", "no", "sv", "yi"],
    "romance": ["ca", "es", "fr", "gl", "it", "la", "oc", "pt", "ro"],
    "slavic": ["be", "bg", "bs", "cs", "hr", "mk", "pl", "ru", "sk", "sl", "sr", "uk"],
    "uralic": ["et", "fi", "hu"],
    "turkic": ["az", "kk", "tr", "uz"],
    "indo-aryan": ["bn", "gu", "hi", "mr", "ne", "pa", "ur"],
}

_FOLD = np.arange(256, dtype=np.uint64)
for _b in range(128):
    _FOLD[_b] = ord(chr(_b).lower()) if chr(_b).isalpha() else 32
_LETTER = np.array([b < 128 and chr(b).isalpha() for b in range(256)])


def features(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of DIMENSIONS floats per text, of length one (zero for a text without letters or other signs)."""
    n = len(offsets) - 1
    out = np.zeros(n * DIMENSIONS)
    if len(data):
        b = _FOLD[data]
        doc = np.repeat(np.arange(n) * DIMENSIONS, np.diff(offsets))
        code = b.copy()
        place = np.arange(len(b)) - offsets[:-1][doc // DIMENSIONS]
        for k in range(3):
            if k:
                code = code[:-1] * np.uint64(257) + b[k:]
            last = slice(k, None)
            # an n-gram lies within one text and isn't white space alone
            fine = (place[last] >= k) & ((b[last] != 32) if k == 0 else ~((b[last] == 32) & (b[k - 1 : -1] == 32)))
            with np.errstate(over="ignore"):
                bucket = ((code[fine] + np.uint64(k << 40)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(52)).astype(np.int64)
            out += np.bincount(doc[last][fine] + bucket, minlength=n * DIMENSIONS)
    x = np.sqrt(out.reshape(n, DIMENSIONS))
    return (x / np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-9)).astype(np.float32)


def linear_svm(x: np.ndarray, y: np.ndarray, c: float = 30.0, steps: int = 150) -> np.ndarray:
    """Weights and bias (last) of a squared-hinge linear machine, y in -1, 1; classes weigh alike."""
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    weight = np.where(y > 0, 1 / max((y > 0).sum(), 1), 1 / max((y < 0).sum(), 1)) / 2
    w = before = np.zeros(x.shape[1])
    rate = 1 / (1 + 2 * c * float((weight * (x * x).sum(1)).sum()))
    for k in range(steps):
        ahead = w + (k / (k + 3)) * (w - before)
        slack = np.maximum(0, 1 - y * (x @ ahead.astype(np.float32)))
        before, w = w, ahead - rate * (ahead - 2 * c * ((weight * slack * y).astype(np.float32) @ x))
    return w.astype(np.float32)


@dataclass
class Model:
    languages: list[str]
    families: list[list[int]]  # indices of languages
    family_weights: np.ndarray  # one row per family
    pairs: list[tuple[int, int]]  # languages of one family
    pair_weights: np.ndarray

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the language and a score from 0 to 1."""
        n = len(x)
        x = np.hstack([x, np.ones((n, 1), np.float32)])
        margin = x @ self.family_weights.T
        family = margin.argmax(1)
        gap = np.full(n, 4.0)
        if len(self.families) > 1:
            top = np.sort(margin, 1)
            gap = (top[:, -1] - top[:, -2]).astype(float)
        votes = np.zeros((n, len(self.languages)))
        for f, members in enumerate(self.families):
            votes[np.ix_(family == f, members)] += 1e-3
        closest = gap
        if self.pairs:
            signed = x @ self.pair_weights.T
            for k, (a, b) in enumerate(self.pairs):
                mine = votes[:, a] > 0
                votes[mine, a] += (signed[mine, k] > 0) + 1e-6 * np.tanh(signed[mine, k])
                votes[mine, b] += (signed[mine, k] <= 0) - 1e-6 * np.tanh(signed[mine, k])
            best = votes.argmax(1)
            for k, (a, b) in enumerate(self.pairs):
                mine = (best == a) | (best == b)
                closest[mine] = np.minimum(closest[mine], 2 * np.where(best[mine] == a, signed[mine, k], -signed[mine, k]))
        return votes.argmax(1), 1 / (1 + np.exp(-2 * np.clip(closest, -20, 20)))


def fit_model(x: np.ndarray, languages: list[str]) -> Model | None:
    names = sorted(set(languages))
    if not names:
        return None
    index = np.array([names.index(v) for v in languages])
    known = {v: f for f, members in FAMILIES.items() for v in members}
    groups: dict[str, list[int]] = {}
    for k, v in enumerate(names):
        groups.setdefault(known.get(v, f"={v}"), []).append(k)
    families = [groups[g] for g in sorted(groups)]
    if len(families) > 1:
        family_weights = np.stack([linear_svm(x, np.where(np.isin(index, members), 1.0, -1.0)) for members in families])
    else:
        family_weights = np.zeros((1, x.shape[1] + 1), np.float32)
    pairs = [(a, b) for members in families for i, a in enumerate(members) for b in members[i + 1 :]]
    made = []
    for a, b in pairs:
        rows = np.isin(index, (a, b))
        made.append(linear_svm(x[rows], np.where(index[rows] == a, 1.0, -1.0)))
    return Model(names, families, family_weights, pairs, np.stack(made) if made else np.zeros((0, x.shape[1] + 1), np.float32))


def fit(labelled: DataFrame, per_language: int = PER_LANGUAGE) -> Model | None:
    """A model from the rows of (doc_id, text, lang) whose lang is known: at most ``per_language`` of each."""
    rows = labelled.select("doc_id", "text", "lang").where("lang IS NOT NULL AND text IS NOT NULL").withColumn("draw", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)))
    known = rows.groupBy("lang").count().collect()  # a row for each language
    if not known:
        return None
    bound = F.lit(None).cast("double")
    for r in known:  # a few more rows than wanted, then exactly the smallest draws
        bound = F.when(F.col("lang") == r["lang"], float(1 << 40) * min(1.0, 1.3 * per_language / r["count"] + 20 / r["count"])).otherwise(bound)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = tn.strings(batch.column(1))
            for i, j in tn.slices(offsets, rows=256):
                part, x = batch.slice(i, j - i), features(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), part.column(3), pa.array([v.astype(np.float16).tobytes() for v in x], pa.binary())], ["doc_id", "lang", "draw", "x"])

    got = rows.where(F.col("draw") <= bound).mapInArrow(run, "doc_id long, lang string, draw long, x binary").toArrow()
    taken: dict[str, list] = {}
    for lang, draw, doc_id, x in sorted(zip(got["lang"].to_pylist(), got["draw"].to_pylist(), got["doc_id"].to_pylist(), got["x"].to_pylist(), strict=True), key=lambda r: (r[0], r[1], r[2] or 0, r[3])):
        if len(taken.setdefault(lang, [])) < per_language:
            taken[lang].append(x)
    x = np.stack([np.frombuffer(v, np.float16) for vs in taken.values() for v in vs]).astype(np.float32)
    return fit_model(x, [k for k, vs in taken.items() for _ in vs])


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, lang_pred, score for every row."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # a few weights for each language

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for batch in batches:
            data, offsets = tn.strings(batch.column(1))
            for i, j in tn.slices(offsets, rows=256):
                own, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
                letters = np.zeros(len(own) + 1, np.int64)
                np.cumsum(_LETTER[own], out=letters[1:])
                has = letters[at[1:]] > letters[at[:-1]]
                for k in np.flatnonzero(~has & (np.diff(at) > 0)):
                    has[k] = any(c.isalpha() for c in own[at[k] : at[k + 1]].tobytes().decode("utf-8"))
                lang, score = np.array(["und"] * (j - i), object), np.zeros(j - i)
                if m is not None and has.any():
                    best, sure = m.predict(features(own, at)[has])
                    lang[has], score[has] = np.array(m.languages, object)[best], sure
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i).cast(pa.int64()), pa.array(lang, pa.string()), pa.array(score)], ["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")
