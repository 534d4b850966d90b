"""The ten operators against brute force, round trips, held-out labels and odd inputs."""

import gzip
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F
from pyspark.sql import types as T

from shardweave.llm import balltree, crf, jump, kneser_ney, mixing, pieces, pseudonyms, registry, rules, simhash, warc
from shardweave.staging import stage

SF = "/root/testdata/sf0.01"
DOC = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, " \n\t ", "en", "a", 4), (4, "one two", "en", None, 7), (4, "one two", "en", None, 7), (5, "word " * 30000, "en", "b", 150000), (6, "é🙂 x▁y " * 5, "fr", "b", 0)]
PLAIN = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def odd(spark):
    return stage(spark.createDataFrame(ODD, DOC))


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def test_every_query_has_its_columns(spark):
    assert {int(n[2:].split("_")[0]) for n in registry.QUERIES} == set(range(1, 11))


# --- 1: mixing ---


def test_mixing_meets_targets(spark, docs):
    rows = mixing.mix(docs.select("doc_id", "text", "source")).collect()
    assert len(rows) == docs.count()
    by = {}
    for r in rows:
        by.setdefault(r["source"], []).append(r)
        assert 0 <= r["taken"] <= 3 * r["size"] and (not r["size"] or r["taken"] % r["size"] == 0)
    assert abs(sum(v[0]["target"] for v in by.values()) - sum(r["size"] for r in rows)) < 1
    for v in by.values():
        assert abs(sum(r["taken"] for r in v) - v[0]["target"]) <= max(r["size"] for r in v) / 2 + 1
    again = mixing.mix(docs.select("doc_id", "text", "source").repartition(7)).collect()
    assert sorted((r["doc_id"], r["taken"]) for r in again) == sorted((r["doc_id"], r["taken"]) for r in rows)


def test_budgets_stop_at_their_caps(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 1000), ("c", 1000), (None, 0)], "source string, source_size long")
    got = {r["source"]: r["target"] for r in mixing.budgets(sizes, "source").collect()}
    # Weights 5, 2, 1, 5: a stops at 30, the source of no words at 0, the rest shares 1980 by 2 and 1.
    assert got == pytest.approx({"a": 30, "b": 1320, "c": 660, None: 0})


def test_mixing_odd_rows(spark, odd):
    got = mixing.mix(odd).collect()
    assert len(got) == len(ODD) and [r["size"] for r in got if r["doc_id"] in (1, 2, 3)] == [0, 0, 0]
    assert mixing.mix(odd.where("doc_id < 0")).count() == 0
    clash = mixing.mix(odd.withColumn("size", F.lit("x")).withColumn("target", F.lit("y")))
    assert clash.count() == len(ODD)
    assert mixing.rows_of(mixing.mix(odd)).columns == odd.columns


# --- 2: near-duplicates ---


def slow_print(text):
    w = (text or "").translate({c: c + 32 for c in range(65, 91)})
    w = PLAIN.findall(w)
    parts = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    hashes = [xxhash.xxh64_intdigest(p.encode(), 42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprints(odd, docs):
    for t in [t for _, t, *_ in ODD if not t or len(t) < 1000] + [r["text"] for r in docs.limit(30).collect()]:
        assert simhash.fingerprint((t or "").encode()) == slow_print(t)


def test_links_equal_all_pairs(spark):
    rng = random.Random(5)
    points = {rng.getrandbits(64) for _ in range(800)}
    for p in list(points)[:200]:  # chains and clusters of near ones
        for _ in range(4):
            p ^= 1 << rng.randrange(64)
            points.add(p)
    base = np.array(sorted(points), np.uint64)
    label = np.arange(len(base))
    r, c = np.nonzero(np.bitwise_count(base[:, None] ^ base[None, :]) <= 2)
    simhash.merge(label, r, c)
    assert (base[simhash.link(base, np.ones(len(base), bool))] == base[label]).all()
    df = spark.createDataFrame([(int(x),) for x in base.view(np.int64)], "fp long")
    for per_shard in (64, 10_000):
        found = {r["a"]: r["b"] for r in simhash.components(simhash.links(df, per_shard=per_shard)).collect()}
        sizes = {}
        for x, root in zip(base.view(np.int64).tolist(), base[label].view(np.int64).tolist(), strict=True):
            sizes.setdefault(root, set()).add(found.get(x, x))
        assert all(len(v) == 1 for v in sizes.values()) and len({next(iter(v)) for v in sizes.values()}) == len(sizes)


def test_every_visit_is_made(spark):
    rng = np.random.default_rng(2)
    points = rng.integers(0, 1 << 63, 2000, np.uint64)
    nodes = simhash.plant(points[:500], 16)
    i, shard, home = simhash.route(points, nodes, 2)
    assert sorted(i[home].tolist()) == list(range(2000))
    lives = dict(zip(i[home].tolist(), shard[home].tolist(), strict=True))
    asks = set(zip(i.tolist(), shard.tolist(), strict=True))
    for b in range(64):
        near = points ^ np.uint64(1 << b)
        j, s, h = simhash.route(near[:50], nodes, 2)
        assert all((a, lives[a]) in set(zip(j.tolist(), s.tolist(), strict=True)) for a in range(50))
    assert len(asks) > 2000


def test_classes_odd_rows(spark, odd):
    got = {r["id"]: r for r in simhash.classes(odd).collect()}
    assert got[1]["fp"] == got[2]["fp"] == got[3]["fp"] == 0 and got[3]["component_id"] == 1
    assert simhash.classes(odd).count() == len(ODD) and simhash.classes(odd.where("doc_id < 0")).count() == 0
    assert sorted(r["doc_id"] for r in simhash.keep_one(odd).collect()) == [1, 4, 5, 6]


def test_classes_without_ids_keep_a_row(spark):
    rows = [(None, "alpha beta gamma delta"), (None, "alpha beta gamma delta"), (None, "one two three four five"), (7, "six seven eight nine"), (None, "six seven eight nine"), (7, "six seven eight nine")]
    kept = simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string").withColumn("fp", F.lit("extra"))).collect()
    assert sorted((r["doc_id"] or 0, r["text"]) for r in kept) == [(0, "alpha beta gamma delta"), (0, "one two three four five"), (7, "six seven eight nine")]


# --- 3: top k ---


def test_top_k_equals_all_products(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(700, 8))
    x[100:400] = x[0]  # a hot vector
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(9000, None), (9001, [1.0, None]), (9002, [float("nan")] * 8), (9003, [1e30] * 8), (None, [1.0] * 8), (9004, [1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = balltree.top_k(df, F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect()
    whole = {i: [int(np.floor(c * 256)) if abs(c) < 1e15 else (1 << 63) - 1 for c in v] + [0] * (8 - len(v)) for i, v in rows if i is not None and v and not any(c is None or c != c for c in v)}
    for q in [i for i in whole if i % 50 == 0]:
        score = {i: max(-(1 << 63), min((1 << 63) - 1, sum(a * b for a, b in zip(whole[q], v, strict=True)))) for i, v in whole.items() if i != q}
        want = sorted(score, key=lambda i: (-score[i], i))[:5]
        mine = [r for r in got if r["query_id"] == q]
        assert [r["vec_id"] for r in mine][:1] == want[:1] and [r["rank"] for r in mine] == [1, 2, 3, 4, 5]
        assert [r["vec_id"] for r in mine if r["vec_id"] < 9000] == [i for i in want if i < 9000]
    assert balltree.top_k(df.where("vec_id < 0"), F.lit(True)).count() == 0
    few = balltree.top_k(df.where("vec_id in (50, 51)"), F.col("vec_id") == 50).collect()
    assert [(r["query_id"], r["vec_id"]) for r in few] == [(50, 51)]


# --- 4 and 7: labels ---


def auc(score, y):
    a, b = score[y == 1], score[y == 0]
    return (a[:, None] > b[None, :]).mean() + (a[:, None] == b[None, :]).mean() / 2


@pytest.mark.parametrize(("name", "label", "parts", "part", "least"), [("op4_kneser_ney", "toxic", 3, 1, 0.8), ("op7_crf", "quality", 5, 0, 0.95)])
def test_held_out_labels(spark, name, label, parts, part, least):
    got = registry.QUERIES[name](spark, SF).toPandas()
    assert got["score"].between(0, 1).all() and len(got) == 1000
    assert all(h == (zlib.crc32(str(i).encode()) % parts == part) for i, h in zip(got["doc_id"], got["held_out"], strict=True))
    met = got[got["held_out"]].merge(spark.read.parquet(f"{SF}/labels.parquet").toPandas(), on="doc_id")
    assert auc(met["score"].to_numpy(), met[label].to_numpy()) >= least


@pytest.mark.parametrize("kernel", [kneser_ney, crf])
def test_scores_of_odd_rows(spark, odd, kernel):
    labels = spark.createDataFrame([(4, 1, 1), (5, 0, 0), (6, None, None)], "doc_id long, toxic int, quality int")
    got = kernel.score(odd, labels, F.lit(True)).collect()
    assert len(got) == len(ODD) and all(0 <= r["score"] <= 1 for r in got)
    one = kernel.score(odd, labels.where("doc_id = 4"), F.lit(True)).collect()
    assert {r["score"] for r in one} == {0.5}
    assert kernel.score(odd.where("doc_id < 0"), labels, F.lit(True)).count() == 0


def test_forward_backward_equals_enumeration():
    rng = np.random.default_rng(4)
    emit, move = rng.normal(size=(1, 5, 2)), rng.normal(size=(2, 2))
    weight = {}
    for code in range(32):
        y = [code >> t & 1 for t in range(5)]
        weight[tuple(y)] = np.exp(sum(emit[0, t, y[t]] for t in range(5)) + sum(move[y[t], y[t + 1]] for t in range(4)))
    total = sum(weight.values())
    p, pair = crf.marginals(emit, move, np.ones((1, 5), bool))
    for t in range(5):
        assert p[0, t, 1] == pytest.approx(sum(w for y, w in weight.items() if y[t]) / total)
    assert pair[1, 0] == pytest.approx(sum(w * sum(y[t] == 1 and y[t + 1] == 0 for t in range(4)) for y, w in weight.items()) / total)


# --- 5: archives ---


def test_archives(spark, tmp_path):
    big = "<p>" + "x" * 2000 + "</p>"
    noise = "".join(chr(33 + random.Random(1).randrange(90)) for _ in range(17 << 20))
    rows = [(1, "u1", big), (2, "u2", big), (7, "u7", big), (3, None, None), (4, "u4", "small"), (5, "u\r\n5", "small"), (6, "u6", noise), (7, "u7", big), (None, "n", big), (8, "é", "é" * 600)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    path = str(tmp_path / "w")
    warc.write(df, path)
    got = warc.read(spark, path).collect()
    assert len(got) == len(rows)
    by = {r["page_id"]: r for r in got}
    assert by[1]["record_type"] == by[2]["record_type"] == "revisit" and by[1]["refers_to"] == 7
    assert by[7]["record_type"] == by[4]["record_type"] == by[5]["record_type"] == "response"
    assert bytes(by[6]["payload"]) == noise.encode() and by[1]["payload_bytes"] == len(big) and by[8]["payload_bytes"] == 1200
    assert by[3]["payload_bytes"] == 0 and by[3]["payload_digest"] == hashlib.sha1(b"").hexdigest()
    for f in (tmp_path / "w").glob("part-*"):
        raw = f.read_bytes()
        assert not raw or gzip.decompress(raw).count(b"WARC/1.1\r\n") >= 1
    assert warc.round_trip(df.where("page_id < 0")).count() == 0


def test_broken_archives_are_errors():
    digest = hashlib.sha1(b"abc").hexdigest()
    good = warc.member(warc.record(1, "u", b"abc", digest, None)) + b"\0"
    assert [r["payload"] for r in warc.records(good + good)] == [b"abc", b"abc"]
    bad = warc.member(warc.record(1, "u", b"abd", digest, None)) + b"\0"
    for raw in (good[:-9], bad, warc.member(b"nothing") + b"\0"):
        with pytest.raises((ValueError, zlib.error)):
            list(warc.records(raw))


# --- 6: rules ---


def test_rules_equal_plain_counts(spark, docs, odd):
    for r in rules.judge(docs.limit(60).unionByName(odd)).collect():
        t = r["text"] or ""
        w = PLAIN.findall(t)
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        seen = {}
        for i, g in enumerate(grams):
            seen.setdefault(g, []).append(i)
        covered = {i + o for v in seen.values() if len(v) > 1 for i in v for o in range(5)}
        full = [x for x in t.split("\n") if PLAIN.search(x)]
        assert (r["n_words"], r["word_chars"], r["n_repeat_words"], r["n_dup_lines"]) == (len(w), sum(map(len, w)), len(covered), len(full) - len(set(full)))
        assert r["n_symbols"] == len(re.findall(r"[#*$%&|<>]", t)) and r["base_failed"] == (len(w) < 10 or 100 * len(covered) > 20 * len(w))
        assert not (r["base_failed"] and r["kept"])
    assert rules.judge(odd.withColumn("n_words", F.lit("x")).where("doc_id < 0")).count() == 0


def test_rules_keep_good_and_reject_bad(spark, docs):
    met = rules.judge(docs).join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id")
    good = met.where("quality = 1 and n_words >= 10")
    assert good.where("kept").count() >= 0.97 * good.count() and met.where("quality = 0 and kept").count() <= 0.1 * met.where("quality = 0").count()


# --- 8: pieces ---


@pytest.fixture(scope="module")
def model():
    return pieces.load(registry.MODEL())


def test_lattice_equals_the_library(spark, model, docs):
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    proto.ParseFromString(open(registry.MODEL(), "rb").read())
    proto.trainer_spec.model_type = 1  # the library's own search for the best path over the same pieces
    library = sentencepiece.SentencePieceProcessor(model_proto=proto.SerializeToString())
    words = sorted({w for r in docs.limit(25).collect() for w in re.findall(r"[A-Za-z]+", r["text"])})[:400]
    got = {r["word"]: r["ids"] for r in pieces.lattice(spark.createDataFrame([("▁" + w,) for w in words], "word string"), model).collect()}
    table = {i: s for s, i in model.score.values()}
    cost = lambda ids: sum(table[i] for i in ids)
    for w in words:
        assert cost(got["▁" + w]) == pytest.approx(cost(library.encode(w))) and tuple(got["▁" + w]) == pieces.word_ids("▁" + w, model)


def test_encode_and_decode(spark, model, odd, docs):
    for df in (odd, docs.limit(80)):
        got = stage(pieces.encode(df, model, size=50))
        back = pieces.decode(got, model).join(df.select(F.col("doc_id").alias("id"), F.col("text").alias("was")).distinct(), "id")
        assert got.count() == df.count()
        assert back.where(~F.col("text").eqNullSafe(F.translate("was", "▁", " "))).count() == 0
    assert [r["round_trip"] for r in pieces.encode(odd.where("doc_id in (1, 2)"), model, size=5).orderBy("id").collect()] == [None, True]
    assert pieces.encode(odd.where("doc_id < 0"), model).count() == 0


def test_long_words_encode_alike(spark, model):
    words = ["▁" + "abcde" * 300, "日本ｘ🙂" * 40]
    got = {r["word"]: tuple(r["ids"]) for r in pieces.lattice(spark.createDataFrame([(w,) for w in words], "word string"), model).collect()}
    assert got == {w: pieces.word_ids(w, model) for w in words}


# --- 9: shards ---


def slow_jump(key, n):
    b, j = -1, 0
    while j < n:
        b = j
        key = (key * 2862933555777941757 + 1) % (1 << 64)
        j = int((b + 1) * ((1 << 31) / ((key >> 33) + 1)))
    return b


def test_jump(spark, odd):
    keys = np.array([0, 1, 5, 2**63, 2**64 - 1, *range(1000, 1200)], np.uint64)
    for n in (1, 7, 40):
        assert jump.jump(keys, n).tolist() == [slow_jump(int(k), n) for k in keys]
    rows = jump.assign(spark.range(3000).withColumnRenamed("id", "doc_id"), "doc_id", [], 40).collect()
    by = {}
    for r in rows:
        by.setdefault(r["shard"], []).append(r["slot"])
        assert r["grown_shard"] in (r["shard"], 40)
    assert all(sorted(v) == list(range(len(v))) for v in by.values())
    assert jump.assign(odd.withColumn("slot", F.lit(1)), "doc_id", ["n_chars"], 4).count() == len(ODD)
    assert jump.assign(odd.where("doc_id < 0"), "doc_id", [], 4).count() == 0


# --- 10: pseudonyms ---


def test_pseudonyms_keep_formats_and_links(spark):
    texts = [
        "card 4929348385146306 and 4929-3483-8514-6306.", "not a card 4929348385146307", "+1 (017) 555-7713, 12.34.56.78; 300.1.1.1", "born 1999-02-28, 2/30/1999, 31.12.2001",
        "und.34@mail7.example.com", "DE89 3704 0044 0532 0130 00 and DE88370400440532013000", "078-05-1120 000-12-3456", 'token = "04dbebab91ab85687d33eeaaf9ac699e1188f962"', None, "", "plain",
    ]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string").withColumn("n_private", F.lit("x"))
    got = {r["doc_id"]: r for r in pseudonyms.pseudonymise(df, "k").collect()}
    a, b = re.findall(r"\d[\d-]+\d", got[0]["text"])
    assert a == b.replace("-", "") and a != "4929348385146306" and luhn(a) and got[0]["n_private"] == 2
    assert got[1]["text"] == texts[1] and got[1]["n_private"] == 0
    assert re.fullmatch(r"\+1 \(\d{3}\) \d{3}-\d{4}, (\d+)\.(\d+)\.(\d+)\.(\d+); 300\.1\.1\.1", got[2]["text"]) and "555-7713" not in got[2]["text"]
    assert re.fullmatch(r"born \d{4}-\d\d-\d\d, 2/30/1999, \d\d\.\d\d\.\d{4}", got[3]["text"]) and "1999-02-28" not in got[3]["text"]
    assert re.fullmatch(r"[a-z]{3}\.\d\d@mail7\.example\.com", got[4]["text"]) and got[4]["text"] != texts[4]
    assert got[5]["text"].startswith("DE") and "3704 0044" not in got[5]["text"] and got[5]["text"].endswith("DE88370400440532013000")
    assert got[6]["text"].endswith("000-12-3456") and "078-05-1120" not in got[6]["text"]
    assert re.fullmatch(r'token = "[0-9a-f]{40}"', got[7]["text"]) and got[7]["text"] != texts[7]
    assert (got[8]["text"], got[9]["text"], got[10]["text"]) == (None, "", "plain")


def luhn(digits):
    return sum(int(c) if i % 2 == 0 else (2 * int(c) - 9 if int(c) > 4 else 2 * int(c)) for i, c in enumerate(reversed(digits))) % 10 == 0


def test_the_permutation_is_one_to_one(spark):
    df = spark.range(1000).select(F.format_string("%03d", F.col("id")).alias("v"))
    new = {r[0] for r in df.select(pseudonyms.permute(F.col("v"), "t", "k")).collect()}
    assert len(new) == 1000 and all(len(v) == 3 for v in new)
    other = df.select(pseudonyms.permute(F.col("v"), "t", "other")).limit(50).collect()
    assert [r[0] for r in other] != [r[0] for r in df.select(pseudonyms.permute(F.col("v"), "t", "k")).limit(50).collect()]


def test_pseudonyms_run_no_python(spark, docs):
    plan = pseudonyms.pseudonymise(docs, "k")._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow|Exchange", plan)


def test_types(spark, odd):
    got = registry.QUERIES["op9_jump"](spark, SF).schema
    assert [f.dataType for f in got.fields] == [T.LongType(), T.LongType(), T.LongType(), T.StringType(), T.IntegerType(), T.LongType(), T.IntegerType()]
