"""Surrogates against brute force over the given documents, and on hard or odd texts."""

import re
import time

import pytest
from pyspark.sql import functions as F

from fewrounds.llm import surrogates as s


def texts(spark, rows):
    return spark.createDataFrame([(k, t, 7, 8, 9) for k, t in enumerate(rows)], "doc_id long, text string, _row int, _fix int, value int")


def test_every_value_of_the_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    before = [r.text for r in docs.orderBy("doc_id").collect()]
    after = [r.text for r in s.replace(docs, "key").orderBy("doc_id").collect()]
    hits = [r.hits for r in docs.orderBy("doc_id").select(s.found(F.col("text")).alias("hits")).collect()]
    forward, backward = {}, {}
    real = {e.lower() for h in hits for e in h or ()}
    for old, new, own in zip(before, after, hits, strict=True):
        if not own:
            assert old == new
            continue
        pattern = "(.*)".join(re.escape(x) for x in re.split("|".join(map(re.escape, sorted(own, key=len, reverse=True))), old))
        got = re.fullmatch(pattern, new, re.S).groups()
        for e, n in zip(own, got, strict=True):
            e, n = e.lower(), n.lower()
            assert n not in real and (len(n) == len(e) or re.fullmatch(r"[0-9.]+", e))
            assert forward.setdefault(e, n) == n and backward.setdefault(n, e) == e
    assert len(forward) > 50


def test_parts_of_names_keep_their_surrogates(spark):
    rows = ["Mrs. Anna Smith, Mr. Smith; Anna Smith!", "Herr Müller-Lang und Frau LANG", "господин Иванов, госпожа Анна Иванова", "Dr. 王伟 Mr. Σωκράτης Dr. 김민수 Herr אברהם", "Anna said"]
    got = [r.text for r in s.replace(texts(spark, rows), "key").orderBy("doc_id").collect()]
    full, alone, bare = re.fullmatch(r"Mrs\. (\w+ \w+), Mr\. (\w+); (\w+ \w+)!", got[0]).groups()
    assert full == bare and full.split()[1] == alone and full.split()[0][-1] in "aei" and full.split()[0] != "Anna" and alone != "Smith"
    a, b, c = re.fullmatch(r"Herr (\w+)-(\w+) und Frau (\w+)", got[1]).groups()
    assert b.upper() == c and a != "Müller" and re.fullmatch(r"господин [А-Я][а-я]+, госпожа [А-Я][а-я]+[ая] [А-Я][а-я]+[ая]", got[2])
    assert re.fullmatch(r"Dr\. [\u4e00-\u9fff]{2} Mr\. [\u0370-\u03ff]+ Dr\. [\uac00-\ud7a3]{3} Herr [\u05d0-\u05ea]+", got[3]) and "王" not in got[3]
    assert got[4] == rows[4]


def test_formats(spark):
    rows = ["555-123-4567", "(555) 123-4567", "fe80::1", "2001:0db8:85a3:0000:0000:8a2e:0370:7334", "GB82 WEST 1234 5698 7654 32", "DE89370400440532013000", "4111 1111 1111 1111", "王伟@x.com", "at 12:30:45 a::b std::string x@y"]
    got = {r.doc_id: r for r in s.counted(texts(spark, [f"see {r}, end" for r in rows]), "key").collect()}
    assert [got[k].n_entities for k in range(9)] == [1] * 8 + [0] and got[8].text == f"see {rows[8]}, end"
    assert [got[0].n_phone, got[1].n_phone, got[2].n_ipv6, got[3].n_ipv6, got[4].n_iban, got[5].n_iban, got[6].n_card, got[7].n_email] == [1] * 8
    for k in range(8):
        assert rows[k] not in got[k].text
    for k in (4, 5):  # check digits hold
        e = got[k].text[4:-5].replace(" ", "")
        assert int("".join(str(int(c, 36)) for c in e[4:] + e[:4])) % 97 == 1 and e[:2] == rows[k][:2]
    digits = [int(c) for c in got[6].text if c.isdigit()][::-1]
    assert sum(digits[::2]) + sum(sum(divmod(2 * d, 10)) for d in digits[1::2]) == 45 or (sum(digits[::2]) + sum(sum(divmod(2 * d, 10)) for d in digits[1::2])) % 10 == 0


def test_crowded_values_are_settled(spark):
    """Where first attempts clash with real values, later ones settle all, by a map in the plan and by a join alike."""
    letters = "aeiou"
    rows = [f"{a}@x.com and Mr. {b.upper()}{c}" for a in letters for b in "bdfgh" for c in letters]
    docs = texts(spark, rows)
    table = s.repairs(docs, "key")
    assert table.count() > 3
    one = [r.text for r in s.replace(docs, "key").orderBy("doc_id").collect()]
    s.MAX_REPAIRS, most = 1, s.MAX_REPAIRS
    try:
        joined = s.replace(docs, "key")
        assert joined.columns == docs.columns and [r.text for r in joined.orderBy("doc_id").collect()] == one
    finally:
        s.MAX_REPAIRS = most
    mails = {(r.split(" ")[0], n.split(" ")[0]) for r, n in zip(rows, one, strict=True)}
    names = {(r.split(" ")[-1], n.split(" ")[-1]) for r, n in zip(rows, one, strict=True)}
    for pairs in (mails, names):
        old, new = {a for a, _ in pairs}, {b for _, b in pairs}
        assert len(pairs) == len(old) == len(new) and not old & new


def test_long_and_odd_texts(spark):
    assert s.replace(texts(spark, ["x"]).where("false"), "key").count() == 0
    rows = [None, "", "mark \u0001 x.y@z.org", "x" * 1_000_000, "a." * 300_000, "x@" * 200_000, "(" * 300_000, "1" * 400_000, "f" * 400_000, "Mr " + "李" * 50_000]
    began = time.time()
    sizes = [r.n for r in texts(spark, rows).coalesce(1).orderBy("doc_id").select(F.size(s.found(F.col("text"))).alias("n")).collect()]
    assert time.time() - began < 20 and sizes[3:9] == [0] * 6
    got = [r.text for r in s.replace(texts(spark, rows), "key", check=False).orderBy("doc_id").collect()]
    assert got[:2] == [None, ""] and got[2].startswith("mark \u0001 ") and "x.y" not in got[2] and got[3] == rows[3]


def test_key_is_required(spark):
    with pytest.raises(TypeError):
        s.replace(texts(spark, ["x"]))
    one, two = (s.replace(texts(spark, ["a.b@c.org"]), k).first().text for k in ("key", "other"))
    assert one != two
