"""Odd input for every operator and pipeline stage, draws against exact probabilities, languages against a plain
reimplementation, and recall of near duplicates by similarity."""

import collections
import math
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from fewrounds.llm import decontaminate, html, langid, neardup, pieces, quality, queries, shards, substrings, surrogates, tokencount
from fewrounds.llm.queries import tokenizer

EXTRA = ["node", "bucket", "label", "signature", "row_key", "_row", "_doc", "_text", "_pieces", "_fix", "_spans", "_gone", "hashes", "blobs", "g", "c", "draw", "score", "spans", "lines", "shared", "n", "value", "kinds"]
SENTENCE = "the quick brown fox jumps over the lazy dog while seven wise owls watch from the old oak tree "
TEXTS = [
    (1, SENTENCE * 3), (2, SENTENCE * 3), (2, "another text shares the same number but none of its words with the one before it here"), (None, SENTENCE * 3), (None, None), (3, None), (4, ""), (5, " \n\t"), (6, "漢字かな交じり文 🙂 é\u0301 \u0001 end"),
    (7, "y" * 200_000), (8, ("w1 w2 w3 w4 w5 w6 w7 " * 6000)), (9, SENTENCE * 3), (9, SENTENCE * 3), (10, "mail a.b@c.org or Mrs. Anna Smith now"),
]
OPERATORS = {
    "quality": lambda d: quality.measure(d), "keep_good": lambda d: quality.keep_good(d), "near_classes": lambda d: neardup.near_classes(d), "keep_one": lambda d: neardup.keep_one(d), "substrings": lambda d: substrings.dedup(d),
    "find": lambda d: decontaminate.find(d, _items(d)), "remove_spans": lambda d: decontaminate.remove_spans(d, _items(d)), "encode": lambda d: pieces.encode(d, tokenizer("piece_bpe_32k.model")), "digest": lambda d: pieces.digest(d, tokenizer("piece_bpe_32k.model")),
    "shards": lambda d: shards.sharded(d, target_bytes=1 << 20)[1], "replace": lambda d: surrogates.replace(d, "key"), "counted": lambda d: surrogates.counted(d, "key"), "tokens": lambda d: tokencount.count_tokens(d, tokenizer("byte_bpe_50k.json")),
    "language": lambda d: langid.predict(d, langid.fit(d)),
}
FILTERS = {"keep_good", "keep_one", "remove_spans"}
KEEPS_COLUMNS = FILTERS | {"shards", "replace"}


def _items(d):
    return d.sparkSession.createDataFrame([(1, "seven wise owls watch from the old oak tree the quick"), (2, None), (None, "x y")], "item_id long, text string")


def table(spark, rows):
    kind = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in EXTRA)
    return spark.createDataFrame([(k, t, "en" if k else None, "s", None, *(["kept"] * len(EXTRA))) for k, t in rows], kind)


@pytest.mark.parametrize("name", list(OPERATORS))
def test_operators_take_odd_rows(spark, name):
    docs = table(spark, TEXTS).repartition(3)
    out = OPERATORS[name](docs)
    rows = out.collect()
    if name in KEEPS_COLUMNS:
        assert out.columns == docs.columns and all(r["_fix"] == "kept" and r["node"] == "kept" for r in rows)
    if name not in FILTERS:
        assert collections.Counter(r.doc_id for r in rows) == collections.Counter(k for k, _ in TEXTS)
    empty = OPERATORS[name](docs.where("false"))
    assert empty.columns == out.columns and empty.count() == 0
    again = OPERATORS[name](docs.repartition(1))
    if name != "shards":
        assert sorted(map(str, again.collect())) == sorted(map(str, rows))


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages_take_odd_rows(spark, tmp_path, name):
    stage = dict(corpus_pipeline.STAGES)[name]
    docs = table(spark, TEXTS)
    _items(docs).write.parquet(str(tmp_path / "benchmark.parquet"))
    out = stage(spark, docs, str(tmp_path))
    n = out.count()
    if name in ("personal_data", "sentence_pieces"):
        assert n == len(TEXTS)
    if name != "sentence_pieces":
        assert out.columns == docs.columns
    assert stage(spark, docs.where("false"), str(tmp_path)).count() == 0
    if name == "near_duplicates":  # one of the texts stays, and rows without id
        assert out.where(F.col("text") == SENTENCE * 3).where("doc_id IS NOT NULL").count() == 1


def test_pages_take_odd_rows(spark):
    rows = [(1, "http://a/x", "<p>t</p>", "kept"), (1, "http://a/x", "<p>t</p>", "kept"), (None, "http://a/y", "<p>u</p>", "kept"), (2, None, None, "kept"), (3, "not a url", "", "kept"), (4, "", "<p>v", "kept")]
    out = html.extract(spark.createDataFrame(rows, "page_id long, url string, html string, lines string"))
    assert sorted((r.page_id or 0, r.text, r.n_chars) for r in out.collect()) == [(0, "u", 1), (1, "t", 1), (1, "t", 1), (2, "", 0), (3, "", 0), (4, "v", 1)]


def test_draws_have_the_exact_probabilities(spark):
    """Every segmentation of a word, weighed by the product of its pieces' weights, against the drawn shares."""
    path, keys = tokenizer("piece_bpe_32k.model"), 20_000
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    known = {model.id_to_piece(k): model.get_score(k) for k in range(model.vocab_size()) if not (model.is_control(k) or model.is_unknown(k) or model.is_byte(k))}
    ranked = all(s <= 0 and float(s).is_integer() for s in known.values())
    low = min(-s for s in known.values())
    weight = {p: 1 / (-s - low + 3) if ranked else math.exp(s) for p, s in known.items()}
    word = "\u2581than"
    paths = {}

    def walk(at, done, w):
        if at == len(word):
            paths[tuple(done)] = w
        for e in range(at + 1, len(word) + 1):
            if word[at:e] in weight:
                walk(e, [*done, word[at:e]], w * weight[word[at:e]])

    walk(0, [], 1.0)
    total = sum(paths.values())
    rows = pieces.encode(spark.range(keys).select(F.col("id").alias("doc_id"), F.lit("than").alias("text")), path)
    drawn = collections.Counter(tuple(model.id_to_piece(int(i)) for i in r.pieces) for r in rows.select("pieces").collect())
    assert set(drawn) <= set(paths) and len(paths) > 4
    large = {p: w / total * keys for p, w in paths.items() if w / total * keys >= 5}
    chi = sum((drawn[p] - e) ** 2 / e for p, e in large.items())
    assert chi < len(large) + 4 * math.sqrt(2 * len(large)) + 4


def test_language_query_keeps_its_contract(spark, tmp_path):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    odd = spark.createDataFrame([(900001, None, "en"), (900002, "12 34", "de"), (None, "the of and", None)], "doc_id long, text string, lang string")
    whole = docs.select("doc_id", "text", "lang").unionByName(odd)
    whole.write.parquet(str(tmp_path / "documents.parquet"))
    rows = whole.collect()
    got = queries.op8_language(spark, str(tmp_path)).collect()
    held = lambda k: k is not None and zlib.crc32(str(k).encode()) % 4 == 2
    assert collections.Counter((r.doc_id, r.held_out) for r in got) == collections.Counter((r.doc_id, held(r.doc_id)) for r in rows)
    learned = {r.lang for r in rows if r.lang and r.text and not held(r.doc_id)}
    by_id = collections.defaultdict(list)
    for r in got:
        by_id[r.doc_id].append(r)
        assert 0 <= r.score <= 1 and r.lang_pred in learned | {"und"}
    assert by_id[900001][0].lang_pred == by_id[900002][0].lang_pred == "und"
    # plain: rank profiles of letter trigrams, an independent way to tell the same languages
    profile = collections.defaultdict(collections.Counter)
    grams = lambda t: collections.Counter(t[i : i + 3] for i in range(len(t) - 2))
    for r in rows:
        if r.lang and r.text and not held(r.doc_id):
            profile[r.lang].update(grams(r.text.lower()[:2000]))
    size = {k: sum(c.values()) for k, c in profile.items()}
    same = n = 0
    for r in rows:
        if r.text and held(r.doc_id) and len(r.text) > 200:
            plain = max(profile, key=lambda k: sum(m * math.log((profile[k][g] + 0.1) / size[k]) for g, m in grams(r.text.lower()[:2000]).items()))
            same += plain == by_id[r.doc_id][0].lang_pred
            n += 1
    assert n > 10 and same >= 0.95 * n


def test_recall_by_similarity(spark):
    """Pairs of each similarity from 0.8 on that land in one class, against exact similarities; below 0.8 none does."""
    r = random.Random(11)
    pairs, rows = [], []
    for k in range(260):
        base = [f"{k}_{r.randrange(10 ** 6)}" for _ in range(r.choice((60, 200, 400)))]
        edits = r.randrange(1, max(2, len(base) // 40))
        other = list(base)
        for _ in range(edits):
            other[r.randrange(len(other))] = f"edit{r.randrange(10 ** 9)}"
        rows += [(2 * k, " ".join(base)), (2 * k + 1, " ".join(other))]
        a, b = (collections.Counter(tuple(t[i : i + 5]) for i in range(len(t) - 4)) for t in (base, other))
        pairs.append((2 * k, sum((a & b).values()) / sum((a | b).values())))
    found = {x.doc_id: x.class_id for x in neardup.near_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    bins = collections.defaultdict(list)
    for k, s in pairs:
        if s < 0.8:
            assert found[k] != found[k + 1]
        else:
            bins[int(s * 20)].append(found[k] == found[k + 1])
    assert len(bins) >= 3 and all(np.mean(v) >= 0.9 for v in bins.values()) and np.mean([x for v in bins.values() for x in v]) >= 0.98
