"""What the toxicity model gathers."""

from collections import Counter
from itertools import product
from zlib import crc32

import numpy as np
import pytest
from pyspark.sql import functions as F

from shardweave.llm import kneser_ney, registry


def sharing() -> tuple[str, str]:
    """Two words that one of 2 ** 19 slots, by the multiplied checksum, would have to share."""
    known = {}
    # Too short for beginnings, which would speak in their stead.
    for word in map("".join, product("abcdefghijkl", repeat=4)):
        at = (crc32(word.encode()) * 0x9E3779B97F4A7C15 % 2**64) >> 45
        if at in known:
            return known[at], word
        known[at] = word
    raise AssertionError


def scores(spark) -> dict[int, float]:
    common, toxic = sharing()
    texts = [(f"plain talk of day x{i % 12} {common}", 0) for i in range(60)] + [(f"plain talk of day x{i % 12} {toxic}", 1) for i in range(20)] + [(f"{toxic}", None), ("plain", None)]
    docs = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(texts)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, (_, y) in enumerate(texts) if y is not None], "doc_id long, toxic int")
    return {r["id"]: r["score"] for r in kneser_ney.score(docs, labels, F.lit(True)).collect()}


def test_a_commoner_word_takes_nothing_from_a_toxic_one(spark):
    got = scores(spark)
    assert got[80] > 0.9 and got[80] > got[81] + 0.5


def test_shards_change_nothing(spark, monkeypatch):
    whole = scores(spark)
    monkeypatch.setattr(kneser_ney, "PER_SHARD", 4)
    assert scores(spark) == pytest.approx(whole, abs=1e-9)


def trained(spark, monkeypatch, cut=2):
    monkeypatch.setattr(kneser_ney, "CUT", cut)
    rng = np.random.default_rng(8)
    words = [a + b + c for a in ("plain", "talk", "un", "dis") for b in ("able", "ing", "er") for c in ("", "s", "ness")]
    rude = ["grumble", "grumbles", "grumbling", "snort"]
    texts = [(" ".join(rng.choice(words + rude * (3 * y), 40)), y) for y in (0, 0, 0, 1) for _ in range(15)]
    rows = spark.createDataFrame(texts, "text string, label int")
    return texts, kneser_ney.fit(rows)


def code(word: bytes) -> int:
    return int(kneser_ney.tokens(word)[0][0])


def test_every_order_sums_to_one(spark, monkeypatch):
    _, held = trained(spark, monkeypatch)
    model = held.model([])
    words, six, four = (model.table[k][0][:-1].tolist() for k in (kneser_ney.WORD, kneser_ney.SIX, kneser_ney.FOUR))
    # The kept words, the rest of each kept beginning, and the rest of all.
    unused = lambda taken, top, bits: next(top << bits | x for x in range(1 << bits) if (top << bits | x) not in taken)
    events = [*words, *(unused(set(words), b, 16) for b in six), *(unused(set(six), b, 16) << 16 for b in four), unused(set(four), 0, 32) << 32]
    contexts = [0, *model.table[kneser_ney.CONTEXT][0][:-1].tolist(), 12345]
    for v in contexts:
        p = model.probabilities(np.array(events, np.uint64), np.full(len(events), v, np.uint64))
        assert (p > 0).all() and p.sum(axis=1) == pytest.approx([1, 1])
    assert len(contexts) > 3 and 0 < min(model.totals["discount"].values()) and max(model.totals["discount"].values()) < 1


def test_probabilities_equal_plain_counts(spark, monkeypatch):
    texts, held = trained(spark, monkeypatch)
    model = held.model([])
    cut = 2
    count = [Counter(), Counter()]
    for t, y in texts:
        w = t.split()
        count[y].update(set(zip(["", *w], w)))
    types = [Counter(), Counter()]
    for y in (0, 1):
        for _, w in count[y]:
            types[y][w] += 1
    shorter = lambda of, n: [sum((Counter({w[:n]: x}) for w, x in c.items()), Counter()) for c in of]
    orders = [shorter(types, 4), shorter(types, 6), types]
    frees = lambda cs: (n1 := sum(x == 1 for c in cs for x in c.values())) / (n1 + 2 * sum(x == 2 for c in cs for x in c.values())) if any(x == 1 for c in cs for x in c.values()) else 0.5
    seen = {w for c in count for (_, w), x in c.items() if x >= cut}
    kept = {w for c in types for w, x in c.items() if x >= cut} | seen

    def chance(v, w, y):
        p = None
        for cs, name in zip(orders, (w[:4], w[:6], w), strict=True):
            d = frees(cs)
            left = [sum(x - d for x in c.values() if x >= cut) for c in cs]
            down = max(1 - a / sum(c.values()) for a, c in zip(left, cs, strict=True))
            whole = sum(sum(c.values()) for c in cs)
            pooled = cs[0][name] + cs[1][name]
            above = whole if p is None else orders[0][0][w[:4]] + orders[0][1][w[:4]] if cs is orders[1] else orders[1][0][w[:6]] + orders[1][1][w[:6]]
            lower = pooled / (above + 1) * (1 if p is None else p)
            own = cs[y][name] - d if cs[y][name] >= cut else 0
            p = (1 - down) * own / left[y] + down * lower
        d = frees(count)
        rest = [sum(x - d for (a, _), x in c.items() if a == v and x >= cut) for c in count]
        if min(rest) <= 0:
            return p
        down = max(1 - r / sum(x for (a, _), x in c.items() if a == v) for r, c in zip(rest, count, strict=True))
        own = count[y][v, w] - d if count[y][v, w] >= cut else 0
        return (1 - down) * own / rest[y] + down * p

    tried = [(a, b) for a in ["", "grumble", "plainable", "unings"] for b in sorted(kept)]
    before = np.array([crc32(a.encode()) for a, _ in tried], np.uint64)
    got = model.probabilities(np.array([code(b.encode()) for _, b in tried], np.uint64), before)
    for y in (0, 1):
        assert got[y] == pytest.approx([chance(a, b, y) for a, b in tried])


def test_held_out_recall(spark):
    d = "/root/testdata/sf0.1"
    got = registry.QUERIES["op4_kneser_ney"](spark, d).where("held_out").toPandas()
    met = got.merge(spark.read.parquet(f"{d}/labels.parquet").toPandas(), on="doc_id")
    said = met["predicted"] == 1
    assert (met["toxic"][said] == 1).mean() > 0.95 and said[met["toxic"] == 1].mean() > 0.85
