"""Each operator against a brute-force version and on odd input: nulls, empty and long texts, ties, repeated rows."""

import collections
import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import fewrounds.llm.textnum as tn
from fewrounds.llm import decontaminate, html, langid, neardup, pieces, quality, shards, substrings, surrogates, tokencount
from fewrounds.llm.queries import tokenizer

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LONG = "ein sehr langer Satz mit Wörtern " * 3000
PASSAGE = " ".join(f"w{i}" for i in range(60))
ROWS = [
    (1, f"start one {PASSAGE} end one"), (2, f"other two {PASSAGE} end two"), (2, f"other two {PASSAGE} end two"), (3, None), (4, ""), (5, " \n\t "), (6, LONG), (7, LONG), (None, f"no id {PASSAGE}"),
    (8, "short text"), (9, "a b a b a b a b a b a b a b a b"), (10, "漢字 🙂 ▁ é\x00"), (11, "line one two three\nline one two three\nline four"), (12, "x" * 5000),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*r, "en", "s", 1, "kept") for r in ROWS], "doc_id long, text string, lang string, source string, n_chars long, node string")


def words(t):
    return WORD.findall(t or "")


def test_quality(docs):
    got = sorted(((r.doc_id if r.doc_id is not None else -1, r.n_words, r.word_chars, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in quality.measure(docs).collect()))
    want = []
    for k, t in ROWS:
        w = words(t)
        c = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        hit = {i + j for i in range(len(w) - 4) if c[tuple(w[i : i + 5])] > 1 for j in range(5)}
        seen, dup = set(), 0
        for line in (t or "").split("\n"):
            if words(line):
                dup += line in seen
                seen.add(line)
        want.append((-1 if k is None else k, len(w), sum(map(len, w)), dup, len(hit), len(w) < 10 or 100 * len(hit) > 20 * len(w)))
    assert got == sorted(want)
    assert quality.keep_good(docs).columns == docs.columns and quality.measure(docs.where("false")).count() == 0


def test_substrings(docs):
    got = {(r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substrings.dedup(docs).collect()}
    first = {}
    for k, t in ROWS:
        w = words(t)
        for i in range(len(w) - 12):
            g = tuple(w[i : i + 13])
            if k is not None:
                first[g] = min(first.get(g, k), k)
    for k, t in ROWS:
        w = words(t)
        gone = {i + j for i in range(len(w) - 12) if k is not None and first[tuple(w[i : i + 13])] < k for j in range(13)}
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        assert (k, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()) in got
    assert substrings.dedup(docs).count() == len(ROWS)
    assert [r.length for r in substrings.levels(docs).orderBy("length").collect()][:2] == [13, 26]


def test_near_duplicates(spark, docs):
    got = {(r.doc_id, r.class_id) for r in neardup.near_classes(docs).collect()}
    assert {(6, 6), (7, 6), (3, 3), (4, 4), (8, 8), (9, 9)} <= got and neardup.near_classes(docs.where("false")).count() == 0
    r = random.Random(4)
    base = [r.choice("abcdefghij") + str(r.randrange(50)) for _ in range(300)]
    rows = [(k, " ".join(base if k == 0 else [("edit" + str(k)) if i == 40 + k else x for i, x in enumerate(base)])) for k in range(30)] + [(99, " ".join(reversed(base)))]
    got = dict(neardup.near_classes(spark.createDataFrame(rows, "doc_id long, text string"), rounds=1).select("doc_id", "class_id").collect())
    assert got == {**{k: 0 for k in range(30)}, 99: 99}


def test_signatures_are_unbiased():
    r = np.random.default_rng(1)
    el = r.integers(1, 1 << 40, 80).astype(np.uint64)
    a, b = r.integers(1, 12, 80), r.integers(1, 12, 80)
    sig = neardup.signatures(np.repeat([0, 1], 80), np.concatenate([el, el]), np.concatenate([a, b]), 2, 6000)
    assert abs((sig[0] == sig[1]).mean() - np.minimum(a, b).sum() / np.maximum(a, b).sum()) < 0.03


def test_decontaminate(spark, docs):
    items = spark.createDataFrame([(1, " ".join(f"W{i}" for i in range(5, 25))), (2, "Short text"), (3, None), (None, PASSAGE), (4, "")], "item_id long, text string")
    for block in (decontaminate.BLOCK_BYTES, 20):
        got = {r.doc_id: r for r in decontaminate.find(docs, items, block_bytes=block).collect()}
        assert decontaminate.find(docs, items, block_bytes=block).count() == len(ROWS)
        assert got[1].n_hit == 20 and got[1].items == ["1"] and got[8].n_hit == 2 and got[8].items_sha256 == hashlib.sha256(b"2").hexdigest() and not got[3].contaminated and got[3].items_sha256 == hashlib.sha256(b"").hexdigest()
    left = {r.doc_id: r for r in decontaminate.remove_spans(docs, items).collect()}
    assert 8 not in left and " w4 w25 " in left[1].text and left[6].text == LONG
    assert decontaminate.find(docs, items.where("false")).where("contaminated").count() == 0


def test_spans_do_not_depend_on_blocks(spark):
    """Rows hit by items of different blocks are cut and judged by all their hits at once."""
    w = [f"p{i}" for i in range(15)]
    items = spark.createDataFrame([(0, " ".join(w[:10])), (1, " ".join(w[5:])), (9, " ".join(f"q{i}" for i in range(12))), (10, " ".join(f"r{i}" for i in range(12)))], "item_id long, text string")
    fill = " ".join(f"f{i}" for i in range(16))
    rows = [(1, f"{fill} {' '.join(w)} end"), (2, f"{' '.join(f'q{i}' for i in range(12))} {fill} {' '.join(f'r{i}' for i in range(12))}"), (2, fill), (None, f"no id {fill} {' '.join(w)}"), (3, None), (None, None)]
    docs = spark.createDataFrame([(*r, 7, 8, 9) for r in rows], "doc_id long, text string, n_chars long, _row long, _spans long")
    one, many = (sorted(map(str, decontaminate.remove_spans(docs, items, block_bytes=b).collect())) for b in (decontaminate.BLOCK_BYTES, 8))
    assert len(list(decontaminate.blocks(items, 10, 8))) > 2
    assert one == many and len(one) == 5 and not any("p14" in r or "q1" in r for r in one)


def test_pieces(docs):
    path = tokenizer("piece_bpe_32k.model")
    rows = pieces.encode(docs, path)
    assert rows.where("lossless").count() == len(ROWS)
    back = collections.Counter(r.text for r in pieces.decode(rows, path).collect())
    assert back == collections.Counter(t or "" for _, t in ROWS)
    again = {(r.doc_id, tuple(r.pieces)) for r in pieces.encode(docs.repartition(7), path).collect()}
    assert again == {(r.doc_id, tuple(r.pieces)) for r in rows.collect()}


def test_token_counts(docs):
    from tokenizers import Tokenizer

    path = tokenizer("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    for chunk in (1 << 16, 300):
        got = sorted((r.doc_id or -1, r.n_tokens) for r in tokencount.count_tokens(docs, path, chunk=chunk, overlap=16).collect())
        assert got == sorted((k or -1, len(library.encode(t or "", add_special_tokens=False).ids)) for k, t in ROWS)


def test_language(spark):
    r = random.Random(2)
    sample = {"en": "the of and with that thing", "de": "der und nicht über schön", "fr": "le la été être vous", "xx": "kwa zulu moto"}
    rows = [(i, " ".join(r.choice(sample[k].split()) for _ in range(12)), k) for i in range(400) for k in [r.choice(list(sample))]]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(df.where("doc_id % 4 <> 2"))
    test = langid.predict(df.where("doc_id % 4 = 2"), model).join(df, "doc_id")
    assert test.where("lang = lang_pred").count() >= 0.97 * test.count()
    odd = {r.doc_id: r.lang_pred for r in langid.predict(spark.createDataFrame([(1, None), (2, "123 !"), (3, "")], "doc_id long, text string"), model).collect()}
    assert set(odd.values()) == {"und"}
    assert {r.lang_pred for r in langid.predict(df, langid.fit(df.where("false"))).collect()} == {"und"}


def test_surrogates(spark):
    private = ["ann.72@mail3.example.com", "+1 (640) 555-0953", "180.194.127.198", "4111111111111111", "4d8a45c418324758e099eb7cb89bc0f5fa9f619a", "123-45-6789", "Mrs. Anna Smith"]
    rows = [(i, f"see {x} and {x}.") for i, x in enumerate(private)] + [(90, None), (91, "clean 12 text")]
    got = {r.doc_id: r for r in surrogates.counted(spark.createDataFrame(rows, "doc_id long, text string"), "surrogates-1").collect()}
    for i, x in enumerate(private):
        assert x not in got[i].text and got[i].n_entities == 2
        first, second = re.fullmatch(r"see (.*) and (.*)\.", got[i].text).groups()
        assert first == second and len(re.sub(r"\d", "", first)) == len(re.sub(r"\d", "", x))
    assert got[90].text is None and got[91].text == "clean 12 text"
    phones = spark.range(3000).select(F.concat(F.lit("+1 ("), F.lpad((F.col("id") % 1000).cast("string"), 3, "0"), F.lit(") 555-"), F.lpad(F.floor(F.col("id") / 1000).cast("string"), 4, "0")).alias("text"))
    named = phones.select(surrogates.surrogate(F.col("text"), "surrogates-1").alias("s"), "text")
    assert named.select("s").distinct().count() == 3000 and named.where("s = text").count() == 0


def test_html(spark):
    menu = "<div><p>Menu line</p></div>"
    page = lambda own: f"<html><head><title>t</title></head><body><nav>x</nav>{menu}<p>{own}</p><div class='comments'>c</div><script>var a='<p>';</script></body></html>"
    rows = [(1, "http://a.org/x/1", page("First &amp; only")), (2, "http://a.org/x/2", page("Second\n  text")), (3, "http://b.org/", "<article><h1>T</h1><p>Menu line</p></article><p>out</p>"), (4, None, page("alone")), (5, "http://c.org/", None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html.extract(df).collect()}
    assert got == {1: "First & only", 2: "Second text", 3: "T\n\nMenu line", 4: "Menu line\n\nalone", 5: ""}
    assert html.aligned([1, 2, 3, 4], [2, 9, 4]) == {1, 3} and html.extract(df.where("false")).count() == 0


def test_shards(spark, docs, tmp_path):
    store, rows = shards.sharded(docs, arrivals=4, target_bytes=1 << 20, fan_in=3, root=str(tmp_path / "store"))
    assert rows.count() == len(ROWS) and sorted(rows.columns) == sorted(docs.columns)
    version = store.version()
    assert store.append(docs, "arrival-0") == version and len(store.shards()) < 12
    assert rows.exceptAll(docs).count() == 0


def test_kernel_handles_slices_and_nulls():
    data, offsets = tn.strings(pa.array(["a b", None, "", "c"]).slice(1))
    w = tn.words_of(data, offsets)
    assert w.counts.tolist() == [0, 0, 1]
