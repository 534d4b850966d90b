"""Lifting graphs to one neighbour graph: own edges, candidates from the other indexes, the best k of both."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardweave.operators import exact, search


def best(edges: DataFrame, k: int, keep: list[str] | None = None) -> DataFrame:
    """The k nearest out-edges of every vertex; of repeated edges one. The rank filter prunes before the shuffle."""
    extra = [F.max(c).alias(c) for c in keep or []]
    once = edges.where("src <> dst").groupBy("src", "dst").agg(F.min("dist").alias("dist"), *extra)
    order = Window.partitionBy("src").orderBy("dist", "dst")
    return once.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).withColumn("rank", F.col("rank").cast("int"))


def pool_size(k: int, h: int, min_degree: int | None = None) -> int:
    """The smallest pool that fills k candidates from h - 1 foreign indexes; with ``min_degree`` the tight form, 1 at least."""
    if h < 2:
        raise ValueError(f"h must be at least 2, not {h}")
    return max(1, math.ceil((k - (min_degree or 0)) / (h - 1)))


def pool_of(pool: int | str, edges: DataFrame, k: int, h: int) -> int:
    """A pool size from ``worst``, ``tight`` (one aggregate over the degrees) or a number."""
    if isinstance(pool, int):
        return pool
    if pool == "worst":
        return pool_size(k, h)
    if pool == "tight":
        least = edges.groupBy("src").count().agg(F.min("count")).first()[0]
        return pool_size(k, h, min(k, least or 0))
    raise ValueError(f"pool must be worst, tight or a number, not {pool!r}")


def own(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst", "dist")


def cross_exact(vectors: DataFrame, pool: int, metric: str = "l2") -> DataFrame:
    """The ``pool`` nearest of every vertex in each foreign part, exactly."""
    found = exact.knn(vectors, vectors, pool, metric, exclude_self=True, scope="other", per_part=True)
    return found.select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist")


def routes(vectors: DataFrame, entries: DataFrame, reach: int | None = None) -> DataFrame:
    """``(target, vec_id, x)``: every vertex once for each foreign index, or for the ``reach`` foreign indexes with the nearest entry.

    ``entries`` has one row an index, so the inequality join has a side of h rows.
    """
    targets = F.broadcast(entries.select(F.col("index_id").alias("target"), F.col("ep_x")))
    met = vectors.join(targets, F.col("part") != F.col("target"))
    if reach is None:
        return met.select("target", "vec_id", "x")
    from shardweave.functions import distance

    near = met.withColumn("d", distance.expr("l2", F.col("x"), F.col("ep_x")))
    order = Window.partitionBy("vec_id").orderBy("d", "target")
    return near.withColumn("r", F.row_number().over(order)).where(F.col("r") <= reach).select("target", "vec_id", "x")


def cross(
    edges: DataFrame, vectors: DataFrame, entries: DataFrame, pool: int, metric: str = "l2", reach: int | None = None, mode: str = "resident", spread: int | None = None, width: int = 1, tri: bool = False, keep: int | None = None
) -> DataFrame:
    """Candidates by beam search in foreign graphs, ``(src, dst, dist, ndc)``; ``ndc`` counts the probe's distances on its first row.

    ``mode``: ``resident`` while an index fits a task (several share its queries), ``frontier`` beyond. ``keep``: so many of a
    pool's best come back, all by default.
    """
    keep = min(keep or pool, pool)
    asked = routes(vectors, entries, reach)
    if mode == "resident":
        found = search.resident(edges, vectors, asked, entries, pool, keep, metric, spread, width, tri)
    elif mode == "frontier":
        found = search.frontier(edges, vectors, asked, entries, pool, keep, metric, width=width)
    else:
        raise ValueError(f"mode must be resident or frontier, not {mode!r}")
    return found.select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist", F.when(F.col("rank") == 1, F.col("ndc")).otherwise(0).alias("ndc"))


#: Vertices in a bin of :func:`random_cross`, on average.
BIN = 8


def random_cross(vectors: DataFrame, pool: int, metric: str = "l2", seed: int = 7) -> DataFrame:
    """``pool`` foreign vertices of every vertex, picked by hash instead of by search.

    Each part's vertices fall into bins of a few; bins are numbered part by part. A vertex draws bins outside its part's
    range and one member of each, by an equal join on the bin: no global order and no cross join. Repeats and empty bins
    cost draws, so twice the pool and a few more are made; a pool near the number of foreign vertices may stay short.
    """
    from shardweave.functions import distance

    # One row a part.
    sizes = vectors.groupBy("part").agg(F.ceil(F.count("*") / BIN).cast("long").alias("bins"))
    before = F.coalesce(F.sum("bins").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranges = sizes.select(F.col("part").alias("p"), "bins", before.alias("first"), F.sum("bins").over(Window.partitionBy()).alias("every"))
    placed = vectors.select("vec_id", "part").join(F.broadcast(ranges), F.col("part") == F.col("p"))
    packed = placed.groupBy((F.col("first") + F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.col("bins"))).alias("bin")).agg(F.array_sort(F.collect_list("vec_id")).alias("members"))
    draws = placed.where("every > bins").select("vec_id", "bins", "first", "every", F.explode(F.sequence(F.lit(1), F.lit(2 * pool + 4))).alias("step"))
    draw = draws.withColumn("r", F.pmod(F.xxhash64("vec_id", "step", F.lit(seed)), F.col("every") - F.col("bins")))
    draw = draw.select("vec_id", "step", F.when(F.col("r") < F.col("first"), F.col("r")).otherwise(F.col("r") + F.col("bins")).alias("bin"))
    met = draw.join(packed, "bin")
    member = F.get("members", F.pmod(F.xxhash64("step", "vec_id", F.lit(seed)), F.size("members")).cast("int"))
    once = met.select(F.col("vec_id").alias("src"), member.alias("dst"), "step").groupBy("src", "dst").agg(F.min("step").alias("step"))
    order = Window.partitionBy("src").orderBy("step")
    some = once.withColumn("r", F.row_number().over(order)).where(F.col("r") <= pool).select("src", "dst")
    x = vectors.select(F.col("vec_id").alias("src"), "x")
    y = vectors.select(F.col("vec_id").alias("dst"), F.col("x").alias("y"))
    return distance.measured(some.join(x, "src").join(y, "dst").select("src", "dst", "x", "y"), "x", "y", metric=metric)


def run(edges: DataFrame, candidates: DataFrame, k: int) -> DataFrame:
    """The best k of own edges and candidates, ``(src, dst, dist, rank)``."""
    return best(own(edges).unionByName(candidates.select("src", "dst", "dist")), k)
