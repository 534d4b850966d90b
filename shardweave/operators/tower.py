"""Upper layers of a layered graph, rebuilt after a merge: levels by a geometric law, a small graph a level."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardweave.operators import exact, search, thin
from shardweave.staging import stage

#: Vertices of a layer that an exact neighbour search may cover.
EXACT_LIMIT = 50_000


def level(uniform: Column, k: int) -> Column:
    """``P(level >= l) = k ** -l`` for a uniform number in (0, 1)."""
    return F.floor(-F.log(uniform) / math.log(k)).cast("int")


def hashed(vec_id: Column, seed: int = 0) -> Column:
    return (F.pmod(F.xxhash64(vec_id, F.lit(seed)), F.lit(1 << 40)).cast("double") + 0.5) / float(1 << 40)


def rebuild(vectors: DataFrame, k: int, seed: int = 0, metric: str = "l2", mode: str = "exact") -> DataFrame:
    """``(layer, src, dst, dist)`` of all layers above the base; about n / k vertices in all.

    ``exact``: a layer is thinned exact neighbours with reverse edges, up to :data:`EXACT_LIMIT` vertices a layer. ``insert``:
    vertices enter one by one, by greedy descent to their level and a beam search on each layer from there down, and the rule
    prunes both ends of their edges; one task holds the layers. ``parts``: a layer is split in parts that are merged as the base is.
    """
    if mode not in ("exact", "insert", "parts"):
        raise ValueError(f"mode must be exact, insert or parts, not {mode!r}")
    placed = stage(vectors.withColumn("level", level(hashed(F.col("vec_id"), seed), k)).where("level >= 1").select("vec_id", "x", "level"), "tower")
    if mode == "insert":
        return _inserted(placed, k, metric)
    out = vectors.sparkSession.createDataFrame([], "layer int, src long, dst long, dist double")
    # A row a level.
    counts = {r["level"]: r["count"] for r in placed.groupBy("level").count().collect()}
    for at in range(1, max(counts, default=0) + 1):
        members = placed.where(F.col("level") >= at).select("vec_id", "x")
        n = sum(c for level_, c in counts.items() if level_ >= at)
        if n < 2:
            continue
        if mode == "exact":
            if n > EXACT_LIMIT:
                raise ValueError(f"layer {at} has {n} vertices, more than {EXACT_LIMIT}; rebuild it in parts")
            near = exact.graph(members, min(k, n - 1), metric)
        else:
            from shardweave.plans import fuse

            near = fuse.tree(members, k, parts=max(2, -(-n // EXACT_LIMIT)), metric=metric).edges
        slim = thin.reciprocate(thin.select(near, members, k, metric=metric), k)
        out = out.unionByName(slim.select(F.lit(at).alias("layer"), "src", "dst", "dist"))
    return out


def _inserted(placed: DataFrame, k: int, metric: str) -> DataFrame:
    from shardweave.plans import builders

    def run(t: pa.Table) -> pa.Table:
        ids, x = builders.shard_arrays(t)
        graph = builders.Layered(builders.Net(x, metric), k, 4 * k, 0, wide=False)
        graph.levels = t.column("level").to_numpy()[np.argsort(t.column("vec_id").to_numpy(), kind="stable")] - 1
        for v in range(len(ids)):
            graph.insert(v)
        return builders.packed(graph.net, ids, graph.layers, 0)

    built = placed.groupBy(F.lit("all")).applyInArrow(run, builders.EDGES)
    return built.select((F.col("layer") + 1).cast("int").alias("layer"), "src", "dst", "dist")


def descend(layers: DataFrame, vectors: DataFrame, queries: DataFrame, base_entry: DataFrame, pool: int = 1, metric: str = "l2") -> DataFrame:
    """``(q_id, ep, ndc)``: each query's entry into the base, by descent from the top layer; where a layer ends, the next begins.

    ``layers`` has a handful of levels; without any, every query enters at ``base_entry``.
    """
    at = None
    # A row a level; there are log(n) / log(k) of them.
    for layer in [r[0] for r in layers.select("layer").distinct().orderBy(F.desc("layer")).collect()]:
        own = layers.where(F.col("layer") == layer)
        members = vectors.select("vec_id", "x").join(own.select(F.col("src").alias("vec_id")).distinct(), "vec_id", "left_semi")
        asked = queries.select("vec_id", "x")
        if at is not None:
            asked = asked.join(at.select(F.col("q_id").alias("vec_id"), "ep"), "vec_id", "left")
        found = search.resident(own, members, asked, search.lowest(members), max(pool, 1), 1, metric)
        step = found.select("q_id", F.col("vec_id").alias("ep"), "ndc")
        if at is not None:
            step = step.join(at.select("q_id", F.col("ndc").alias("before")), "q_id").select("q_id", "ep", (F.col("ndc") + F.col("before")).alias("ndc"))
        at = stage(step, "descend")
    if at is None:
        return queries.select(F.col("vec_id").alias("q_id")).join(F.broadcast(base_entry.select("ep")), F.lit(True)).withColumn("ndc", F.lit(0).cast("long"))
    return at


def layered(base: DataFrame, layers: DataFrame, vectors: DataFrame, queries: DataFrame, base_entry: DataFrame, pool: int, k: int, metric: str = "l2") -> DataFrame:
    """Search of a layered graph: descent, then a beam in the base from where it ends; ``ndc`` counts both."""
    at = descend(layers, vectors, queries, base_entry, 1, metric)
    asked = queries.select("vec_id", "x").join(at.select(F.col("q_id").alias("vec_id"), "ep"), "vec_id", "left")
    found = search.resident(base, vectors.select("vec_id", "x"), asked, base_entry, pool, k, metric)
    cost = at.select(F.col("q_id").alias("q"), F.col("ndc").alias("above"))
    return found.join(cost, F.col("q_id") == F.col("q")).withColumn("ndc", F.col("ndc") + F.col("above")).drop("q", "above")
