"""Windows decided in a stream of sorted rows, against plain sets, whatever the batches; and levels against brute force."""

import collections
import random

import pytest

from fewrounds.llm import substrings


@pytest.mark.parametrize("size", [1, 2, 3, 10000])
def test_windows_are_decided_alike_in_any_batches(spark, size):
    r = random.Random(size)
    rows = [(r.randrange(6) - 3, r.randrange(2), r.randrange(5)) for _ in range(60)]
    docs = collections.defaultdict(set)
    for g, c, d in rows:
        docs[g, c].add(d)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
    try:
        df = spark.createDataFrame([(g, c, d, None) for g, c, d in rows] + [(99, 0, 7, b"x"), (99, 0, 7, b"y")], "g long, c int, doc_id long, more binary")
        for later_only in (False, True):
            want = collections.defaultdict(set)
            for (g, _), own in docs.items():
                for d in own:
                    if (d > min(own)) if later_only else len(own) > 1:
                        want[d].add(g)
            got = {x.doc_id: x for x in substrings._decided(df, later_only).collect()}
            assert sorted(map(bytes, got.pop(7).blobs)) == [b"x", b"y"]
            assert {d: set(x.hashes) for d, x in got.items()} == want
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


def test_levels(spark):
    r = random.Random(1)
    long_ = [f"w{r.randrange(30)}" for _ in range(700)]
    texts = [" ".join(long_), "x " + " ".join(long_[100:600]), " ".join(long_[:40]) + " y", None, "", " ".join(f"u{i}" for i in range(50)), " ".join(long_[300:360])]
    got = {x.length: (x.n_docs, x.n_windows) for x in substrings.levels(spark.createDataFrame([*enumerate(texts), (None, texts[0])], "doc_id long, text string")).collect()}
    want, length = {}, 13
    while True:
        held = collections.defaultdict(set)
        split = [(t or "").split() for t in texts]
        for d, w in enumerate(split):
            for i in range(len(w) - length + 1):
                held[tuple(w[i : i + length])].add(d)
        n = [sum(len(held[tuple(w[i : i + length])]) > 1 for i in range(len(w) - length + 1)) for w in split]
        if not any(n):
            break
        want[length] = (sum(x > 0 for x in n), sum(n))
        length *= 2
    assert got == want and max(want) == 416
    assert substrings.levels(spark.createDataFrame([], "doc_id long, text string")).count() == 0
