"""Exact top-k by inner product: ball trees with branch and bound, shard by shard.

Vectors become integers, ``floor(scale * x)``, so scores are exact. Every task turns its rows into shards of bounded size
with a ball tree each. Queries come in blocks of bounded size, one broadcast a block, released when the block's results are
written. A first pass over a bounded sample of the candidates gives every query a k-th score to start from; that score and
those found later are shared by all nodes. Nodes wait in order of their upper bound ``q . centre + |q| radius``, the mean
over the queries that still ask there; the best is opened first, and a query leaves a node whose bound stays below its k-th
score. Tasks send only rows that reach the shared score, and the best k are taken at the end.

The bound is rounded: a product of doubles errs by less than ``dim * 2**-52 * |q| (|centre| + radius)``, and ``SLACK`` times
that product of norms is added, which covers any dimension below four million.

Defined cases: vectors that are null or hold null or non-finite components take no part, nor do rows of null id; shorter
vectors count as padded with zeros; equal scores go to the smaller id; a query never meets rows of its own id; rows
repeated under one id count one by one; scores beyond a long are cut to its range; an empty table gives an empty result;
other columns take no part.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shardweave.staging import drop, fresh_path, stage

K = 5
SCALE = 256
#: Bounds: queries in a broadcast, rows of a shard, of a leaf, and of the sample that gives the first scores.
QUERIES, SHARD, LEAF, PILOT = 16_384, 32_768, 512, 16_384
FOUND = "query_id long, vec_id long, score long"
EXACT = float(1 << 53)
SLACK = 1e-9
LOW, HIGH = -(1 << 63), (1 << 63) - 1


def integers(df: DataFrame, id_col: str = "vec_id", vector: str = "embedding", scale: int = SCALE) -> DataFrame:
    """``(vec_id, v)`` of the rows that take part."""
    x = F.col(vector)
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c.cast("double")) | (F.abs(c.cast("double")) == float("inf")))
    good = df.where(x.isNotNull() & F.col(id_col).isNotNull()).where(~F.coalesce(bad, F.lit(False)))
    whole = F.transform(x, lambda c: (F.floor(c.cast("double") * scale)).cast("double"))
    return good.select(F.col(id_col).cast("long").alias("vec_id"), whole.alias("v"))


def matrix(column: pa.ListArray | pa.ChunkedArray, dim: int) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.diff(flat.offsets.to_numpy())
    values = flat.flatten().to_numpy(zero_copy_only=False)
    if len(sizes) and (sizes == dim).all():
        return values.reshape(-1, dim).astype(np.float64)
    out = np.zeros((len(sizes), dim))
    at = 0
    for i, n in enumerate(sizes):
        out[i, : min(n, dim)] = values[at : at + n][:dim]
        at += n
    return out


def products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer inner products as longs."""
    if not len(q) or not len(x) or np.abs(q).max(initial=0) * np.abs(x).max(initial=0) * max(1, q.shape[1]) < EXACT:
        return (q @ x.T).astype(np.int64)
    whole = np.vectorize(int, otypes=[object])
    return np.clip(whole(q).dot(whole(x).T), LOW, HIGH).astype(np.int64)


class Best:
    """The best k of every query so far, as flat triples in order of query, falling score and id."""

    def __init__(self, ids: np.ndarray, floor: np.ndarray, k: int):
        self.ids, self.floor, self.k = ids, floor.copy(), k
        self.q, self.score, self.vec = (np.zeros(0, np.int64) for _ in range(3))

    def add(self, q: np.ndarray, score: np.ndarray, vec: np.ndarray) -> None:
        q, score, vec = (np.concatenate(x) for x in ((self.q, q), (self.score, score), (self.vec, vec)))
        # ``~score`` falls where the score rises, without overflow.
        order = np.lexsort((vec, ~score, q))
        q, score, vec = q[order], score[order], vec[order]
        rank = np.arange(len(q)) - np.searchsorted(q, q)
        keep = rank < self.k
        self.q, self.score, self.vec = q[keep], score[keep], vec[keep]
        last = self.q[(rank[keep] == self.k - 1)]
        self.floor[last] = np.maximum(self.floor[last], self.score[rank[keep] == self.k - 1])


def search(q: np.ndarray, best: Best, x: np.ndarray, vec: np.ndarray) -> int:
    """Branch and bound over a ball tree that is grown as it is opened; returns the number of products."""
    if not len(x) or not len(q):
        return 0
    norms = np.sqrt((q * q).sum(axis=1))
    waiting: list[tuple[float, int, np.ndarray, np.ndarray, np.ndarray, np.ndarray, float]] = []
    made = done = 0

    def wait(rows: np.ndarray, active: np.ndarray) -> None:
        nonlocal made
        centre = x[rows].mean(axis=0)
        radius = float(np.sqrt(((x[rows] - centre) ** 2).sum(axis=1).max()))
        bound = q[active] @ centre + norms[active] * (radius + SLACK * (radius + float(np.sqrt(centre @ centre)))) + 1e-3
        heapq.heappush(waiting, (-float(bound.mean()), made, rows, active, bound, centre, radius))
        made += 1

    wait(np.arange(len(x)), np.arange(len(q)))
    while waiting:
        _, _, rows, active, bound, centre, radius = heapq.heappop(waiting)
        # The k-th scores may have risen since the node began to wait.
        active = active[bound >= best.floor[active]]
        if not len(active):
            continue
        if len(rows) <= LEAF or radius == 0:
            for at in range(0, len(active), 4096):
                some = active[at : at + 4096]
                for lo in range(0, len(rows), 4 * LEAF):
                    part = rows[lo : lo + 4 * LEAF]
                    score = products(q[some], x[part])
                    done += score.size
                    hit = (score >= best.floor[some][:, None]) & (vec[part][None, :] != best.ids[some][:, None])
                    i, j = np.nonzero(hit)
                    best.add(some[i], score[i, j], vec[part][j])
            continue
        own = x[rows]
        a = own[((own - centre) ** 2).sum(axis=1).argmax()]
        b = own[((own - a) ** 2).sum(axis=1).argmax()]
        side = own @ (b - a)
        cut = np.median(side)
        left = side <= cut
        if left.all():
            left = side < cut
        if not left.any():  # the split is below what doubles tell apart
            left = np.arange(len(rows)) < len(rows) // 2
        wait(rows[left], active)
        wait(rows[~left], active)
    return done


def _run(candidates: DataFrame, ids: np.ndarray, q: np.ndarray, floor: np.ndarray, k: int, path: str) -> DataFrame:
    """The best of every task under ``path``; the block's broadcast is gone when they are written."""
    spark = candidates.sparkSession
    held = spark.sparkContext.broadcast((ids, q, floor))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q, floor = held.value
        best, xs, vecs, n = Best(ids, floor, k), [], [], 0

        def flush() -> None:
            if xs:
                search(q, best, np.concatenate(xs), np.concatenate(vecs))
                xs.clear()
                vecs.clear()

        for batch in batches:
            xs.append(matrix(batch.column("v"), q.shape[1]))
            vecs.append(batch.column("vec_id").to_numpy())
            n += batch.num_rows
            if n >= SHARD:
                flush()
                n = 0
        flush()
        yield pa.RecordBatch.from_arrays([pa.array(ids[best.q]), pa.array(best.vec), pa.array(best.score)], names=["query_id", "vec_id", "score"])

    candidates.mapInArrow(find, FOUND).write.mode("append").parquet(path)
    held.destroy()
    return spark.read.schema(FOUND).parquet(path)


def _top(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def top_k(df: DataFrame, is_query: Column, id_col: str = "vec_id", vector: str = "embedding", k: int = K, scale: int = SCALE, block: int = QUERIES) -> DataFrame:
    """``(query_id, rank, vec_id, score)`` of the k best rows for every row that ``is_query`` picks.

    Queries that share an id must be one row; of several, the smallest vector asks. One pass over the candidates a block;
    the blocks' results are files of one table, so the plan doesn't grow with the queries.
    """
    spark = df.sparkSession
    candidates = stage(integers(df, id_col, vector, scale), "balltree")
    asked = integers(df.where(is_query), id_col, vector, scale).groupBy("vec_id").agg(F.min("v").alias("v"))
    facts = candidates.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("dim")).first()
    parts = max(1, -(-asked.count() // block))
    asked = stage(asked.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int")).repartition(parts, "block"), "balltree-queries", ["block"])
    dim = facts["dim"] or 0
    every = max(1, facts["n"] // PILOT)
    pilot = candidates.where(F.pmod(F.xxhash64("vec_id"), F.lit(every)) == 0) if every > 1 else None
    path = fresh_path(spark, "balltree-found")
    spark.createDataFrame([], FOUND).write.parquet(path)
    for part in range(parts):
        some = asked.where(F.col("block") == part).orderBy("vec_id").toArrow()
        if not some.num_rows:
            continue
        ids, q = some.column("vec_id").to_numpy(), matrix(some.column("v"), dim)
        floor = np.full(len(ids), LOW, np.int64)
        if pilot is not None:
            tried = _run(pilot, ids, q, floor, k, fresh_path(spark, "balltree-pilot"))
            first = _top(tried, k).where(F.col("rank") == k).select("query_id", "score").toArrow()
            drop(tried)
            floor[np.searchsorted(ids, first.column("query_id").to_numpy())] = first.column("score").to_numpy()
        _run(candidates, ids, q, floor, k, path)
    drop(asked)
    drop(candidates)
    return _top(spark.read.schema(FOUND).parquet(path), k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
