"""The given tables as vectors, splits and logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(vec_id, x)`` of all embeddings."""
    return table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("x"))


def held_out(vec_id: Column) -> Column:
    return vec_id % 11 == 7


def base_and_queries(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    v = vectors(spark, sf_dir)
    return v.where(~held_out(F.col("vec_id"))), v.where(held_out(F.col("vec_id")))


def checked(df: DataFrame, x: str = "x", metric: str = "l2") -> tuple[DataFrame, DataFrame]:
    """Vectors that can be indexed, and the rest as ``(vec_id, reason)``. The dimension is the most frequent one."""
    facts = df.where(F.col(x).isNotNull()).groupBy(F.size(x).alias("d")).count().orderBy(F.desc("count"), "d").first()
    dim = facts["d"] if facts else 0
    odd = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    zero = F.forall(x, lambda c: c == 0)
    reason = F.when(F.col(x).isNull(), "null").when(F.size(x) != dim, "dimension").when(F.coalesce(odd, F.lit(True)), "not finite")
    if metric == "cosine":
        reason = reason.when(zero, "zero")
    tagged = df.withColumn("reason", reason)
    return tagged.where("reason is null").drop("reason"), tagged.where("reason is not null").select("vec_id", "reason")


def document_vectors(docs: DataFrame, dim: int = 64, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``(vec_id, x)``: signed feature hashing of words, unit length; texts without a word are left out."""
    tokens = docs.select(F.col(id_col).alias("vec_id"), F.explode(F.split(F.lower(text), r"[^\p{L}\p{N}]+")).alias("w")).where("w <> ''")
    h = F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long")
    at = tokens.select("vec_id", (h % dim).cast("int").alias("pos"), F.when(F.floor(h / dim) % 2 == 0, 1.0).otherwise(-1.0).alias("s"))
    sums = at.groupBy("vec_id", "pos").agg(F.sum("s").alias("s"))
    packed = sums.groupBy("vec_id").agg(F.map_from_entries(F.collect_list(F.struct("pos", "s"))).alias("m"), F.sqrt(F.sum(F.col("s") * F.col("s"))).alias("norm"))
    full = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0)) / F.col("norm"))
    return packed.where("norm > 0").select("vec_id", full.cast("array<float>").alias("x"))


def part_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole-numbered columns of ``part``: few dimensions, ties and twins."""
    x = F.array("p_size", F.floor(F.col("p_retailprice") / 100), F.col("p_partkey") % 97, F.length("p_name"))
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("vec_id"), x.cast("array<float>").alias("x"))


def jittered(base: DataFrame, copies: int, step: float = 0.001) -> DataFrame:
    """``copies`` of every vector, each moved by a small amount that follows from its number."""
    many = base.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    moved = F.transform("x", lambda c, i: (c + step * F.col("copy") * ((i % 7) - 3)).cast("float"))
    return many.select((F.col("vec_id") * copies + F.col("copy")).alias("vec_id"), moved.alias("x"))


def blended(base: DataFrame, copies: int, stride: int = 33) -> DataFrame:
    """``base`` and ``copies - 1`` new vectors for each of its own, half way to the vector ``stride`` ids further on (or back).

    A multiple of 11 keeps partners on the same side of :func:`held_out`.
    """
    top = base.agg(F.max("vec_id")).first()[0] or 0
    many = base.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    ahead, back = F.col("vec_id") + stride * F.col("copy"), F.col("vec_id") - stride * F.col("copy")
    many = many.withColumn("other", F.when(ahead <= top, ahead).otherwise(back))
    met = many.join(base.select(F.col("vec_id").alias("other"), F.col("x").alias("y")), "other", "left")
    mean = F.zip_with("x", F.coalesce("y", "x"), lambda a, b: ((a + b) / 2).cast("float"))
    return met.select((F.col("vec_id") * copies + F.col("copy")).alias("vec_id"), mean.alias("x"))


def write_log(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """``(event_id, ts, vec_id, op)``: events as changes of vectors; an error deletes."""
    e = table(spark, sf_dir, "events")
    return e.select("event_id", "ts", (F.col("event_id") % n).alias("vec_id"), F.when(F.col("event_type") == "error", "delete").otherwise("upsert").alias("op"))
