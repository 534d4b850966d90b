"""The write path: a stream of changes to segments, each sealed by a window of time and given a small graph.

Batch twins of the windows (:func:`by_window`, :func:`by_sliding`, :func:`sessions`) run on a stream as well: they are
plain aggregations, and only :func:`watermarked` adds what a stream needs. :func:`write_segments` commits by batch: a
repeated batch overwrites its own segment, so a retry leaves one copy.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

STAMP = "yyyy-MM-dd HH:mm:ss"
LATE = "2 hours"


def read(spark: SparkSession, path: str, schema: T.StructType, files_a_trigger: int = 1) -> DataFrame:
    """A stream of change files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_trigger).parquet(path)


def watermarked(changes: DataFrame, late: str = LATE) -> DataFrame:
    """Changes once each by ``event_id``; those later than the watermark go."""
    return changes.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def by_window(changes: DataFrame, length: str = "1 hour") -> DataFrame:
    n = F.approx_count_distinct("vec_id", 0.01) if changes.isStreaming else F.countDistinct("vec_id")
    got = changes.groupBy(F.window("ts", length)).agg(F.count("*").alias("n"), n.alias("n_vectors"))
    return got.select(F.date_format("window.start", STAMP).alias("window_start"), "n", "n_vectors")


def by_sliding(changes: DataFrame, length: str = "1 hour", step: str = "30 minutes") -> DataFrame:
    got = changes.groupBy(F.window("ts", length, step)).agg(F.count("*").alias("n"))
    return got.select(F.date_format("window.start", STAMP).alias("window_start"), "n")


def sessions(changes: DataFrame, gap: str = "30 minutes") -> DataFrame:
    got = changes.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return got.select("user_id", F.date_format("w.start", STAMP).alias("session_start"), "n")


def latest(changes: DataFrame) -> DataFrame:
    """``(vec_id, op, ts)``: the newest change of every vector."""
    return changes.groupBy("vec_id").agg(F.max_by("op", F.struct("ts", "event_id")).alias("op"), F.max("ts").alias("ts"))


SEALED = "segment string, n long, first_ts timestamp, last_ts timestamp"
STATE = "number long, n long, first_ts timestamp, last_ts timestamp"


def seal(key, batches: Iterator[pd.DataFrame], state, bound: int) -> Iterator[pd.DataFrame]:
    """Count changes of a shard into segments of ``bound``; the state is the open segment, not its vectors."""
    number, n, first, last = state.get if state.exists else (0, 0, None, None)
    out = []
    for batch in batches:
        for ts in batch["ts"].sort_values():
            first = ts if first is None else min(first, ts)
            last = ts if last is None else max(last, ts)
            n += 1
            if n == bound:
                out.append((f"{key[0]}-{number}", n, first, last))
                number, n, first, last = number + 1, 0, None, None
    state.update((number, n, first, last))
    yield pd.DataFrame(out, columns=["segment", "n", "first_ts", "last_ts"])


def sealed_by_count(changes: DataFrame, shards: int, bound: int) -> DataFrame:
    """Segments sealed by their size, per shard of vectors, as a stateful stream."""
    keyed = changes.withColumn("shard", F.pmod("vec_id", F.lit(shards)))
    return keyed.groupBy("shard").applyInPandasWithState(lambda k, b, s: seal(k, b, s, bound), SEALED, STATE, "append", "NoTimeout")


def write_segments(changes: DataFrame, vectors: DataFrame, path: str, checkpoint: str, kind: str = "nsw", **how) -> StreamingQuery:
    """Every batch becomes a segment: the newest change of each vector, and a graph over those that live."""
    from shardweave.plans import builders

    def one(batch: DataFrame, number: int) -> None:
        last = latest(batch)
        last.write.mode("overwrite").parquet(f"{path}/changes/segment={number}")
        live = vectors.join(last.where("op = 'upsert'").select("vec_id"), "vec_id", "left_semi").withColumn("part", F.lit(number))
        builders.build(live, kind, **how).write.mode("overwrite").parquet(f"{path}/edges/segment={number}")

    return changes.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def surviving(changes: DataFrame) -> DataFrame:
    """``(index_id, local_id, valid)`` of all segments' changes: the newest copy of a vector holds unless it is a delete."""
    order = Window.partitionBy("vec_id").orderBy(F.desc("ts"), F.desc("segment"))
    ranked = changes.withColumn("r", F.row_number().over(order))
    return ranked.select(F.col("segment").cast("int").alias("index_id"), F.col("vec_id").alias("local_id"), ((F.col("r") == 1) & (F.col("op") == "upsert")).alias("valid"))
