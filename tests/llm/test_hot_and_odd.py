"""Hot keys, clashing names, and whole queries by brute force."""

import collections
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from shardweave.llm import balltree, crf, jump, kneser_ney, mixing, pieces, pseudonyms, registry, rules, simhash, warc
from shardweave.staging import stage

SF = "/root/testdata/sf0.001"
NAMES = ("row", "id", "key", "size_", "_epochs", "_last", "_cut", "_key", "_part", "_shard", "_before", "_rank", "_digest", "_w", "_LINES", "_h", "_found", "_new", "fp", "root", "component_id", "goal", "place", "bucket", "entry", "n", "salt", "word", "x", "y")


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def test_extra_columns_are_kept(spark, docs):
    odd = docs.limit(12)
    for name in NAMES:
        odd = odd.withColumn(name, F.lit("kept"))
    got = [mixing.mix(odd), mixing.rows_of(mixing.mix(odd)), simhash.keep_one(odd), rules.judge(odd), jump.assign(odd, "doc_id", ["n_chars"], 4), pseudonyms.pseudonymise(odd, "k")]
    for df in got:
        assert all(r[n] == "kept" for r in df.collect() for n in NAMES)
    labels = spark.createDataFrame([(0, 1, 1), (1, 0, 0)], "doc_id long, toxic int, quality int").withColumn("text", F.lit("t"))
    assert kneser_ney.score(odd, labels, F.lit(True)).count() == crf.score(odd, labels, F.lit(True)).count() == 12
    v = spark.createDataFrame([(1, [1.0], "a"), (2, [2.0], "b")], "vec_id long, embedding array<double>, score string")
    assert balltree.top_k(v, F.lit(True)).count() == 2
    assert warc.round_trip(spark.createDataFrame([(1, "u", "h", "x")], "page_id long, url string, html string, payload_digest string")).count() == 1


# --- 1 ---


@pytest.mark.parametrize("edge", [1, 7, 50_000])
def test_mix_of_a_hot_source(spark, edge):
    """All weights at the floor, one source, many copies of a row: the cut is that of a plain walk in order of the keys."""
    rows = [(i, "1 " * (i % 17 + 1), "hot") for i in range(800)] + [(9000, "7 7 7", "hot")] * 60 + [(5000 + i, "good words here", "b") for i in range(40)]
    df = stage(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    got = mixing.mix(df, edge_rows=edge).collect()
    drawn = mixing.draw(df, "doc_id", "text", "source", None, 42).select("id", "source", "size", "key").collect()
    for name in ("hot", "b"):
        target = next(r["target"] for r in got if r["source"] == name)
        own = sorted((r["key"], r["id"], r["size"]) for r in drawn if r["source"] == name)
        total = sum(x[2] for x in own)
        rest, run, cut = target - target // total * total, 0, None
        for e in own:
            if rest > 0 and run + e[2] / 2 <= rest:
                cut = e
            run += e[2]
        want = collections.Counter((e[1], int(e[2] * (target // total + (cut is not None and e <= cut)))) for e in own)
        assert collections.Counter((str(r["doc_id"]), r["taken"]) for r in got if r["source"] == name) == want
    slim = collections.Counter((r["doc_id"], r["taken"]) for r in mixing.shares(df, edge_rows=edge).collect())
    assert slim == collections.Counter((r["doc_id"], r["taken"]) for r in got)


# --- 2 ---


def test_the_whole_query_equals_all_pairs(spark, docs):
    got = {r["doc_id"]: r for r in registry.QUERIES["op2_simhash"](spark, SF).collect()}
    prints = {r["doc_id"]: simhash.fingerprint((r["text"] or "").encode()) for r in docs.collect()}
    assert {i: int(r["fingerprint"], 16) for i, r in got.items()} == prints
    label = {i: i for i in prints}
    for i in sorted(prints):
        for j in sorted(prints):
            if j < i and label[i] != label[j] and (prints[i] ^ prints[j]).bit_count() <= 2:
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = {k: new if v == old else v for k, v in label.items()}
    assert {i: r["component_id"] for i, r in got.items()} == label


def test_rows_of_one_id_in_several_classes(spark):
    a, b, c = "alpha beta gamma delta", "one two three four five", "six seven eight nine ten"
    rows = [(7, a), (7, b), (3, b), (7, c), (7, c), (9, c)]
    kept = sorted((r["doc_id"], r["text"]) for r in simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert kept == [(3, b), (7, a), (7, c)]


def test_many_shards_need_a_larger_sample(spark):
    rng = np.random.default_rng(1)
    points = rng.integers(0, 1 << 62, 6000, np.uint64)
    vantage, rows = simhash.plant(points, 900)
    assert len(vantage) > 500 and (rows[:, 1:].min() < 0)


# --- 3 ---


def test_fewer_products_than_all(spark):
    rng = np.random.default_rng(4)
    x = np.floor(256 * (rng.normal(size=(40, 16))[rng.integers(0, 40, 20_000)] + rng.normal(size=(20_000, 16)) / 50))
    q = x[:50]
    best = balltree.Best(np.arange(50), np.full(50, balltree.LOW, np.int64), 5)
    done = balltree.search(q, best, x, np.arange(20_000))
    assert done < 0.5 * 50 * 20_000
    full = q @ x.T
    full[np.arange(50), np.arange(50)] = -np.inf
    for i in range(50):
        assert sorted(best.score[best.q == i].tolist()) == sorted(np.sort(full[i])[-5:].astype(int).tolist())


def test_many_blocks_of_queries(spark):
    v = spark.read.parquet(f"{SF}/embeddings.parquet").select("vec_id", "embedding")
    one, many = (sorted(map(tuple, balltree.top_k(v, F.col("vec_id") % 5 == 0, block=b).collect())) for b in (10_000, 7))
    assert one == many and "Union" not in balltree.top_k(v, F.col("vec_id") % 5 == 0, block=7)._jdf.queryExecution().toString()


# --- 5 ---


def test_archives_are_checked():
    import hashlib

    body = b"abc"
    digest = hashlib.sha1(body).hexdigest()
    good = warc.record(1, "u", body, digest, None)
    assert b"WARC-Date: " in good and b"WARC-Profile: " in (again := warc.record(2, "u", body, digest, 1))
    assert warc.record_id(1, digest).encode() in again
    assert [r["record_type"] for r in warc.records(warc.member(good) + b"\0" + warc.member(again) + b"\0")] == ["response", "revisit"]
    for raw in (good.replace(b"X-Payload-Length: 3", b"X-Payload-Length: 99"), good + good, good.replace(b"WARC-Date", b"Other")):
        with pytest.raises(ValueError):
            list(warc.records(warc.member(raw) + b"\0"))


def test_rows_of_one_page_fill_several_archives(spark, tmp_path):
    rows = [(1, "u", "x" * 5000)] * 40 + [(None, "n", "x" * 5000)] * 3 + [(2, "v", "y" * 2000), (None, "m", "z" * 2000)]
    df = stage(spark.createDataFrame(rows, "page_id long, url string, html string"))
    warc.write(df, str(tmp_path / "w"), archive_bytes=20_000)
    got = warc.read(spark, str(tmp_path / "w")).collect()
    assert len(got) == len(rows)
    kinds = collections.Counter((r["page_id"], r["record_type"], r["refers_to"]) for r in got)
    assert kinds == {(1, "response", None): 40, (None, "revisit", 1): 3, (2, "response", None): 1, (None, "response", None): 1}
    sizes = [sum(len(r["payload"]) for r in warc.records(f.read_bytes())) for f in (tmp_path / "w").glob("part-*")]
    assert max(sizes) <= 100_000 and sum(s > 0 for s in sizes) > 3


# --- 6 ---


def test_filters_stay_above_the_projection(docs):
    plan = rules.judge(docs).where("kept")._jdf.queryExecution().optimizedPlan().toString()
    kept = [x for x in plan.split("\n") if x.lstrip("+-: ").startswith("Filter")]
    assert len(kept) == 1 and "n_words" in kept[0] and not any(x in kept[0].lower() for x in ("regexp", "split(", "xxhash64"))


# --- 7 ---


def test_groups_are_bounded():
    lengths = [3] * 1000 + [900_000, 5, 70_000, 70_000]
    groups = crf.grouped(lengths)
    assert sorted(i for g in groups for i in g) == list(range(len(lengths)))
    assert all(len(g) == 1 or (len(g) <= crf.GROUP_CHAINS and len(g) * max(lengths[i] for i in g) <= crf.GROUP_LINES) for g in groups)


def test_the_field_learns_what_neighbours_say():
    rng = np.random.default_rng(6)
    chains, y = [], np.arange(400) % 2
    for label in y:
        own = rng.normal(size=(rng.integers(1, 9), crf.WIDTH)) * 0.1
        own[:, 4] += 1 - label
        chains.append(crf.features(own))
    field = crf.fit(chains, y)
    right = [(field.mean(c, np.ones(len(c))) > 0.5) == bool(label) for c, label in zip(chains, y, strict=True)]
    assert np.mean(right) > 0.97


def test_long_labelled_texts(spark):
    rows = [(i, "\n".join([f"line {i} of good prose that goes on"] * (60_000 if i == 0 else 3)) if i % 2 else "## $$ ## $$\n" * 4) for i in range(8)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(8)], "doc_id long, quality int")
    got = {r["id"]: r["score"] for r in crf.score(spark.createDataFrame(rows, "doc_id long, text string"), labels, F.lit(True)).collect()}
    assert min(got[i] for i in (1, 3, 5, 7)) > max(got[i] for i in (0, 2, 4, 6))


# --- 8 ---


def test_the_dictionary_has_the_most_frequent_words(spark):
    rng = np.random.default_rng(2)
    n = np.concatenate((rng.zipf(1.3, 4000) % 100_000 + 1, np.full(500, 70_001))).astype(int)
    counts = stage(spark.createDataFrame([(f"w{i}", int(x)) for i, x in enumerate(n)], "word string, n long"))
    for size in (1, 100, 499, 500, 700, 3000, 10_000):
        floor = pieces.least_often(counts, size)
        assert (n >= floor).sum() <= size
        # No more than a step of a thousandth of the count is given away.
        assert (n >= max(1, floor - 1 - floor // 512)).sum() > size or floor == 1


# --- 9 ---


def test_slots_of_a_hot_key(spark):
    rows = [(None, i % 50, f"t{i % 7}") for i in range(700)] + [(5, 1, "same")] * 300 + [(i, 0, "x") for i in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, size long, extra string")
    got = jump.assign(df, "doc_id", ["size"], 4, buckets=64).collect()
    by = collections.defaultdict(list)
    for r in got:
        by[r["shard"]].append(r["slot"])
    assert len(got) == len(rows) and all(sorted(v) == list(range(len(v))) for v in by.values())
    assert collections.Counter((r["doc_id"], r["size"], r["extra"]) for r in got) == collections.Counter(rows)
    buckets = {zlib.crc32(f"0|{i}".encode()) % 64 for i in range(50)}
    assert len(buckets) > 20
