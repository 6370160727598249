import random

import pytest

pytest.importorskip("fewrounds.llm")

from fewrounds.llm import neardup
from fewrounds.operators.components import UnionFind


def _least(links):
    sets = UnionFind()
    for a, b in links:
        sets.join(a, b)
    return {bytes([x]): bytes([sets.find(x)]) for x in {x for pair in links for x in pair}}


def test_classes_go_on_from_earlier_labels(spark):
    draw = random.Random(3)
    first, second = ([tuple(draw.sample(range(60), 2)) for _ in range(n)] for n in (18, 14))
    frame = lambda links: spark.createDataFrame([(bytes([a]), bytes([b])) for a, b in links], "a binary, b binary")
    labels = neardup.classes(frame(first))
    got = [(bytes(r.node), bytes(r.label)) for r in neardup.classes(frame(second), labels).collect()]
    assert len(got) == len(dict(got)) and dict(got) == _least(first + second)
    inside = [(a, b) for a, b in first if a != b][:3]  # links that join nothing new
    assert {bytes(r.node): bytes(r.label) for r in neardup.classes(frame(inside), labels).collect()} == _least(first)


def test_few_tables_are_written(spark, monkeypatch):
    draw, written, real = random.Random(5), [], neardup.kept
    monkeypatch.setattr(neardup, "kept", lambda df: written.append(1) or real(df))
    rows = []
    for c in range(4):
        text = [f"w{draw.randrange(10**6)}" for _ in range(120)]
        for k in range(8):
            own = list(text)
            for at in draw.sample(range(120), k // 2):
                own[at] = f"x{c}{k}"
            rows.append((len(rows), " ".join(own)))
    found = neardup.near_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id: r.class_id for r in found if r.doc_id % 8 < 4} == {8 * c + k: 8 * c for c in range(4) for k in range(4)}
    assert len(written) <= 42, len(written)  # 40 in three rounds; 47 when joins and counts of a bucket were written one by one
