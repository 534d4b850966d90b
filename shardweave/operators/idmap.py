"""Splits of a vector table into indexes, and the map from local to global ids."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def by_modulus(vectors: DataFrame, h: int) -> DataFrame:
    return vectors.withColumn("part", F.pmod(F.col("vec_id"), F.lit(h)).cast("int"))


def by_hash(vectors: DataFrame, h: int, seed: int = 0) -> DataFrame:
    return vectors.withColumn("part", F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(h)).cast("int"))


def by_label(vectors: DataFrame, h: int) -> DataFrame:
    return vectors.withColumn("part", F.pmod(F.col("label"), F.lit(h)).cast("int"))


def skewed(vectors: DataFrame, one_in: int = 8) -> DataFrame:
    """Two parts, the second with one in ``one_in`` vectors."""
    return vectors.withColumn("part", F.when(F.col("vec_id") % one_in > 0, 0).otherwise(1))


def full_and_subset(vectors: DataFrame, one_in: int) -> DataFrame:
    """All vectors as part 0, and one in ``one_in`` of them again as part 1."""
    again = vectors.where(F.col("vec_id") % one_in == 0).withColumn("part", F.lit(1))
    return vectors.withColumn("part", F.lit(0)).unionByName(again)


def build(members: DataFrame, mode: str = "offset", valid: Column | None = None) -> DataFrame:
    """``(index_id, local_id, valid, global_id)`` from ``(index_id, local_id)`` and what the mode needs.

    ``offset``: local id plus the sizes of the indexes before, gaps stay. ``dense``: valid rows renumbered.
    ``newest``: by ``key`` and ``ts``, the newest copy of a key is valid; its key is the global id. ``explicit``: a
    ``global_id`` column is taken as it is.
    """
    ok = F.lit(True) if valid is None else valid
    if mode == "explicit":
        return members.select("index_id", "local_id", ok.alias("valid"), "global_id")
    if mode == "newest":
        latest = Window.partitionBy("key").orderBy(F.desc("ts"), F.desc("index_id"), F.desc("local_id"))
        first = (F.row_number().over(latest) == 1) & ok
        return members.select("index_id", "local_id", first.alias("valid"), F.col("key").alias("global_id"))
    flagged = members.withColumn("valid", ok)
    if mode == "offset":
        sizes = flagged.groupBy("index_id").agg((F.max("local_id") + 1).alias("n"))
        before = Window.orderBy("index_id").rowsBetween(Window.unboundedPreceding, -1)  # one row an index
        offsets = sizes.select("index_id", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
        out = flagged.join(F.broadcast(offsets), "index_id")
        return out.select("index_id", "local_id", "valid", (F.col("local_id") + F.col("offset")).cast("long").alias("global_id"))
    if mode == "dense":
        sizes = flagged.groupBy("index_id").agg(F.sum(F.col("valid").cast("long")).alias("n"))
        before = Window.orderBy("index_id").rowsBetween(Window.unboundedPreceding, -1)
        offsets = sizes.select("index_id", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
        inside = Window.partitionBy("index_id").orderBy("local_id").rowsBetween(Window.unboundedPreceding, 0)
        placed = flagged.join(F.broadcast(offsets), "index_id").withColumn("rank", F.sum(F.col("valid").cast("long")).over(inside) - 1)
        return placed.select("index_id", "local_id", "valid", F.when(F.col("valid"), F.col("rank") + F.col("offset")).cast("long").alias("global_id"))
    raise ValueError(f"mode must be offset, dense, newest or explicit, not {mode!r}")


def apply(edges: DataFrame, mapped: DataFrame, src_index: str = "index_id", dst_index: str = "index_id") -> DataFrame:
    """Edges on local ids renamed to global ones; edges of an invalid end go."""
    good = mapped.where("valid")
    one = good.select(F.col("index_id").alias("_i"), F.col("local_id").alias("_l"), F.col("global_id").alias("_src"))
    two = good.select(F.col("index_id").alias("_j"), F.col("local_id").alias("_m"), F.col("global_id").alias("_dst"))
    out = edges.join(one, (F.col(src_index) == F.col("_i")) & (F.col("src") == F.col("_l")))
    out = out.join(two, (F.col(dst_index) == F.col("_j")) & (F.col("dst") == F.col("_m")))
    return out.withColumns({"src": F.col("_src"), "dst": F.col("_dst")}).drop("_i", "_l", "_src", "_j", "_m", "_dst")
