"""Sharding by jump consistent hashing, with gapless slots inside each shard.

A row's shard follows from its key and the number of shards alone; one more shard takes rows only into itself, about
``1 / (shards + 1)`` of them. The slot is the row's place in its shard. Slots come from counts of small buckets inside the
shards, prefix-summed, plus a rank inside one bucket, so no task ever holds a whole shard.

Defined cases: a null key hashes as zero; equal keys share a shard and their slots follow from the remaining columns;
equal rows take slots that follow on each other; a null text has size 16 and the checksum of the empty string; an empty table
gives an empty result; input columns named like the added ones are replaced, all others are kept; columns of maps are an error.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from shardweave.llm.textcols import boxed
from shardweave.staging import stage

#: Fixed values of the published generator: the multiplier and the 31 bits that it divides by.
MULTIPLIER = np.uint64(2862933555777941757)
SPAN = float(1 << 31)


def jump(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shards of unsigned 64-bit keys. Every key jumps ahead until its next landing is past the last shard."""
    state = keys.astype(np.uint64).copy()
    landed = np.zeros(len(state), np.int64)
    moving = np.arange(len(state))
    ahead = np.zeros(len(state), np.int64)
    while len(moving):
        landed[moving] = ahead[moving]
        state[moving] = state[moving] * MULTIPLIER + np.uint64(1)
        stretch = SPAN / ((state[moving] >> np.uint64(33)).astype(np.float64) + 1.0)
        ahead[moving] = ((landed[moving] + 1) * stretch).astype(np.int64)
        moving = moving[ahead[moving] < shards]
    return landed.astype(np.int32)


def shard_of(key: Column, shards: int) -> Column:
    """The shard of a long key, 0 to ``shards - 1``."""
    if shards < 1:
        raise ValueError(f"shards must be at least 1, not {shards}")

    @F.pandas_udf(T.IntegerType())
    def place(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for keys in batches:
            yield pd.Series(jump(keys.to_numpy(np.int64).view(np.uint64), shards))

    return place(F.coalesce(key.cast("long"), F.lit(0).cast("long")))


def assign(df: DataFrame, key: str, order: list[str], shards: int, buckets: int = 1024) -> DataFrame:
    """``df`` with ``shard``, ``slot`` and ``grown_shard`` (the shard if there were one more).

    ``buckets``: parts of a shard that are ranked apart; raise it with the input so that one part fits a task. A row's
    bucket follows from its key and from ``order``, so the rows of a repeated key spread over the buckets of its shard; rows
    that are equal in all columns are counted before they are ranked, and their slots follow on each other.
    """
    bare = df.drop("shard", "slot", "grown_shard")
    named = [F.col(key), *map(F.col, order)]
    said = F.concat_ws("|", *[F.coalesce(c.cast("string"), F.lit("0")) for c in named])
    rows = bare.select(
        boxed(bare).alias("row"), F.struct(*[c.alias(f"c{i}") for i, c in enumerate(named)]).alias("entry"),
        shard_of(F.col(key), shards).alias("shard"), shard_of(F.col(key), shards + 1).alias("grown_shard"), (F.crc32(said.cast("binary")) % buckets).cast("int").alias("bucket"),
    )
    once = rows.groupBy("shard", "bucket", "entry", "row", "grown_shard").agg(F.count("*").alias("n"))
    placed = stage(once, "jump")
    counts = placed.groupBy("shard", "bucket").agg(F.sum("n").alias("n"))
    ahead = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    # The table of offsets has at most shards * buckets rows, whatever the input.
    offsets = counts.select("shard", "bucket", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("before"))
    inside = Window.partitionBy("shard", "bucket").orderBy("entry", F.xxhash64("row")).rowsBetween(Window.unboundedPreceding, -1)
    first = F.col("before") + F.coalesce(F.sum("n").over(inside), F.lit(0))
    ranked = placed.join(offsets, ["shard", "bucket"]).withColumn("first", first)
    slots = F.sequence(F.col("first"), F.col("first") + F.col("n") - 1)
    return ranked.select("row", "shard", F.explode(slots).alias("slot"), "grown_shard").select("row.*", "shard", F.col("slot").cast("long").alias("slot"), "grown_shard")
