"""The pipeline against plain versions of its stages."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as cp
from shardweave.llm import mixing, nearcopies, pseudonyms, rules
from shardweave.staging import stage

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def results(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs]
    for name, step in cp.STAGES:
        out.append(stage(step(spark, out[-1], SF), name))
    return out


def test_shape(results):
    assert 4 <= len(cp.STAGES) <= 5
    assert all(df.columns == cp.COLUMNS for df in results[:-1])
    assert results[-1].columns == ["doc_id", "ids", "n_tokens", "round_trip"]


def one_of_each(texts):
    """The smallest id of each class of texts with similar sets of five-word shingles, by all pairs."""
    sets = {i: set(nearcopies.shingles((t or "").encode()).tolist()) for i, t in texts.items()}
    label = {i: i for i in texts}
    for i in sorted(texts):
        for j in sorted(texts):
            a, b = sets[i], sets[j]
            if j < i and label[i] != label[j] and (len(a & b) >= 0.8 * len(a | b) if a | b else True):
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = {k: new if v == old else v for k, v in label.items()}
    return sorted(set(label.values()))


def test_stages_decide(results):
    ids = [sorted(r["doc_id"] for r in df.select("doc_id").collect()) for df in results]
    kept = sorted(r["doc_id"] for r in rules.judge(results[0]).where("kept").collect())
    assert ids[1] == kept
    assert ids[2] == one_of_each({r["doc_id"]: r["text"] for r in results[1].collect()}) and ids[3] == ids[2]
    times = {r["doc_id"]: r["taken"] // r["size"] for r in mixing.mix(results[3]).collect() if r["size"]}
    assert ids[4] == sorted(i for i, n in times.items() for _ in range(n)) and ids[5] == ids[4]
    assert results[5].where("not round_trip").count() == 0


def test_private_values_are_gone(results):
    text = "\n".join(r["text"] for r in results[3].select("text").collect())
    import re

    for r in results[2].select("text").collect():
        for m in re.findall(pseudonyms.EMAIL.replace(r"\p{L}\p{N}", r"\w"), r["text"]):
            assert m not in text


def test_run_equals_the_stages(spark, results):
    got = cp.run(spark, SF)
    assert sorted((r["doc_id"], r["n_tokens"]) for r in got.collect()) == sorted((r["doc_id"], r["n_tokens"]) for r in results[-1].collect())


def test_empty_table(spark, results):
    df = results[0].where("doc_id < 0")
    for name, step in cp.STAGES:
        df = stage(step(spark, df, SF), name)
    assert df.count() == 0


def test_odd_rows_through_all_stages(spark):
    prose = " ".join(f"the word{i} and this line of it{i}" for i in range(400))
    texts = [None, "", "  ", prose, prose, prose + " and one more", "one two three four five six seven eight nine ten eleven", " ".join(f"the other{i} and its own line{i}" for i in range(20_000))]
    rows = [(i if i != 4 else None, t, "en", None if i % 2 else "web", 0) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, step in cp.STAGES:
        df = stage(step(spark, df, SF), name)
    got = [r.asDict() for r in df.collect()]
    assert {r["doc_id"] for r in got} <= {3, 6, 7} and any(r["doc_id"] == 7 for r in got) and all(r["round_trip"] for r in got)


def test_extra_columns_do_not_clash(spark, results):
    df = results[0].limit(20)
    for name in ("row", "id", "size", "key", "_w", "_found", "_digest", "component_id", "fp", "root"):
        df = df.withColumn(name, F.lit("x"))
    for name, step in cp.STAGES:
        step(spark, df, SF).count()
