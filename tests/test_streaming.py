"""Streams against their batch twins."""

import pytest
from pyspark.sql import functions as F

from shardweave.sources import tables
from shardweave.streaming import segments

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def files(spark, tmp_path_factory):
    """The log in five files, in order of time."""
    path = str(tmp_path_factory.mktemp("log"))
    log = tables.write_log(spark, SF, 100).withColumn("ts", F.col("ts").cast("timestamp"))
    for i in range(5):
        log.where((F.col("event_id") >= i * 200) & (F.col("event_id") < (i + 1) * 200)).coalesce(1).write.mode("append").parquet(path)
    return path, log


def finished(stream, tmp_path, mode="append"):
    name = f"q{abs(hash(str(tmp_path)))}"
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination(120)
    return stream.sparkSession.table(name)


def test_windows_equal_their_twin(spark, files, tmp_path):
    path, log = files
    stream = segments.read(spark, path, log.schema).withWatermark("ts", "2 hours")
    got = finished(segments.by_window(stream), tmp_path, "complete").select("window_start", "n")
    want = segments.by_window(log).select("window_start", "n")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_repeats_go_within_the_watermark(spark, files, tmp_path):
    path, log = files
    stream = segments.read(spark, path, log.schema)
    twice = segments.watermarked(stream.unionByName(stream))
    assert finished(twice, tmp_path).count() == log.count()


def test_segments_seal_at_their_bound(spark, files, tmp_path):
    path, log = files
    got = finished(segments.sealed_by_count(segments.read(spark, path, log.schema), 2, 50), tmp_path)
    by_shard = log.groupBy((F.col("vec_id") % 2).alias("s")).count().collect()
    assert got.count() == sum(r["count"] // 50 for r in by_shard) and {r["n"] for r in got.collect()} == {50}


def test_batches_become_segments(spark, files, tmp_path):
    path, log = files
    v = tables.vectors(spark, SF).where("vec_id < 100")
    segments.write_segments(segments.read(spark, path, log.schema, 2), v, str(tmp_path / "s"), str(tmp_path / "c"), m=4, ef=10).awaitTermination(180)
    changes = spark.read.parquet(str(tmp_path / "s/changes"))
    alive = segments.surviving(changes).where("valid")
    want = segments.latest(log).where("op = 'upsert'")
    assert sorted(r["local_id"] for r in alive.collect()) == sorted(r["vec_id"] for r in want.collect())
    assert spark.read.parquet(str(tmp_path / "s/edges")).count() > 0
