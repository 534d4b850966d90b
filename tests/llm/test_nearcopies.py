"""Near copies by brute force over all pairs."""

import random

import pytest

import corpus_pipeline as cp
from shardweave.llm import nearcopies

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def similarity(a: str, b: str) -> float:
    x, y = (set(nearcopies.shingles(t.encode()).tolist()) for t in (a, b))
    return len(x & y) / len(x | y) if x | y else 1.0


@pytest.fixture(scope="module")
def texts():
    rnd = random.Random(5)
    word = lambda: "".join(rnd.choices("abcdefghij", k=6))
    out = []
    for _ in range(30):
        own = [word() for _ in range(200)]
        out.append(" ".join(own))
        for changes in (1, 2, 3, 4, 5, 8):
            copy = list(own)
            for at in rnd.sample(range(len(copy)), changes):
                copy[at] = word()
            out.append(" ".join(copy))
    return [*out, "one two", "one  TWO", "one three", "", "  ", None]


def expected(texts) -> list[int]:
    label = list(range(len(texts)))
    for i, a in enumerate(texts):
        for j in range(i):
            if label[i] != label[j] and similarity(a or "", texts[j] or "") >= 0.8:
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if x == old else x for x in label]
    return sorted(set(label))


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "web", len(t or "")) for i, t in enumerate(texts)], SCHEMA)


def test_copies_with_changed_words_leave_the_pipeline(spark, texts):
    got = sorted(r["doc_id"] for r in cp.apart(spark, frame(spark, texts), "").collect())
    assert got == expected(texts)
    assert len(got) < 30 * 4


def test_blocks_in_parts(spark, texts, monkeypatch):
    monkeypatch.setattr(nearcopies.links, "__defaults__", (2,))
    got = sorted(r["doc_id"] for r in nearcopies.keep_one(frame(spark, texts)).select("doc_id").collect())
    assert got == expected(texts)
