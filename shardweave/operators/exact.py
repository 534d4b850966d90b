"""Exact nearest neighbours: blocks of queries against all vectors.

A block of queries is bounded and broadcast; every task keeps the best of its own vectors, and the best of all tasks are
taken at the end. This is the ground truth for recall, the brute-force baseline, and the exact neighbour graph.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.staging import drop, fresh_path, stage

#: Queries of one broadcast, vectors of one matrix product, pairs that are measured at a time.
BLOCK, ROWS, PAIRS = 8192, 1024, 1 << 19


def nearest(
    metric: str, q: np.ndarray, qid: np.ndarray, x: np.ndarray, xid: np.ndarray, k: int, drop: np.ndarray | None = None, limit: np.ndarray | None = None
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(row of the query, id, distance)`` of the k nearest of ``x``, by distance and id; ``drop`` marks pairs to leave out.

    A matrix product gives rough distances. All candidates whose rough distance may belong to the first k, given the error of
    the product, are measured in full, so ties go by id however many there are. With a ``limit`` a query only those up to it
    are asked for.
    """
    empty = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    if not len(q) or not len(xid):
        return empty
    rough, slack = distance.rough(metric, q, x)
    if drop is not None:
        rough[drop] = np.inf
    last = min(k, len(xid)) - 1
    maybe = None
    if limit is not None:
        reach = (limit * limit if metric == "l2" else limit) + 2 * slack
        maybe = (rough <= reach[:, None]) & np.isfinite(rough)
    if maybe is None or np.count_nonzero(maybe) > 2 * k * len(q):
        reach = np.partition(rough, last, axis=1)[:, last] + 2 * slack
        near = (rough <= reach[:, None]) & np.isfinite(rough)
        maybe = near if maybe is None else maybe & near
    ends = np.cumsum(maybe.sum(axis=1))
    out = []
    lo = 0
    while lo < len(q):  # so many queries at a time as have a bounded number of candidates
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + PAIRS, "right")))
        r, c = np.nonzero(maybe[lo:hi])
        r += lo
        d = distance.rows(metric, q[r], x[c])
        order = np.lexsort((xid[c], d, r))
        r, c, d = r[order], c[order], d[order]
        keep = np.arange(len(r)) - np.searchsorted(r, r) < k
        out.append((r[keep], xid[c[keep]], d[keep]))
        lo = hi
    return tuple(np.concatenate(z) for z in zip(*out, strict=True))


def blocks(vectors: DataFrame, queries: DataFrame, block: int, schema: str, ask) -> DataFrame:
    """``ask(vectors, pack)`` for blocks of ``queries``, ``pack`` a broadcast Arrow table of one. Several blocks write one
    table each after the other and release what they hold, so plan and driver don't grow with the queries."""
    spark = vectors.sparkSession
    n = queries.count()
    if n <= block:
        return ask(vectors, spark.sparkContext.broadcast(queries.toArrow().combine_chunks()))
    parts = -(-n // block)
    dealt = stage(queries.withColumn("_block", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int")).repartition(parts, "_block"), "query-blocks", ["_block"])
    path = fresh_path(spark, "exact")
    spark.createDataFrame([], schema).write.parquet(path)
    for at in range(parts):
        pack = spark.sparkContext.broadcast(dealt.where(F.col("_block") == at).drop("_block").toArrow().combine_chunks())
        ask(vectors, pack).write.mode("append").parquet(path)
        pack.destroy()
    drop(dealt)
    return spark.read.schema(schema).parquet(path)


class Best:
    """The k nearest so far of n queries, as finds of :func:`nearest` come in."""

    def __init__(self, n: int, k: int):
        self.ids, self.far = np.zeros((n, k), np.int64), np.full((n, k), np.inf)
        self.more: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def add(self, r: np.ndarray, ids: np.ndarray, far: np.ndarray) -> None:
        self.more.append((r, ids, far))
        if 2 * sum(len(m[0]) for m in self.more) >= self.ids.size:
            self.settle()

    def settle(self) -> None:
        if not self.more:
            return
        r, v, d = (np.concatenate(z) for z in zip(self.kept(), *self.more, strict=True))
        order = np.lexsort((v, d, r))
        r, v, d = r[order], v[order], d[order]
        at = np.arange(len(r)) - np.searchsorted(r, r)
        few = at < self.ids.shape[1]
        self.ids[r[few], at[few]], self.far[r[few], at[few]] = v[few], d[few]
        self.more = []

    def kept(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        r, c = np.nonzero(np.isfinite(self.far))
        return r, self.ids[r, c], self.far[r, c]


FOUND = "q_id long, part int, vec_id long, dist double"


def _candidates(vectors: DataFrame, pack, k: int, metric: str, exclude_self: bool, scope: str, per_part: bool = False) -> DataFrame:
    """A task's k nearest of each query, or of each query and part: what it gives doesn't grow with its vectors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = pack.value
        ids, q, part = held.column("vec_id").to_numpy(), distance.matrix(held.column("x")), held.column("part").to_numpy()
        best: dict[int, Best] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                some = batch.slice(at, ROWS)
                x, xid, xpart = distance.matrix(some.column("x")), some.column("vec_id").to_numpy(), some.column("part").to_numpy()
                for p in np.unique(xpart):
                    mine = xpart == p
                    ask = np.flatnonzero({"any": part == part, "same": part == p, "other": part != p}[scope])
                    if not len(ask):
                        continue
                    drop = ids[ask][:, None] == xid[mine][None, :] if exclude_self else None
                    one = best.setdefault(int(p) if per_part else 0, Best(len(ids), k))
                    r, v, d = nearest(metric, q[ask], ids[ask], x[mine], xid[mine], k, drop, one.far[ask, -1])
                    one.add(ask[r], v, d)
        for p, one in best.items():
            one.settle()
            r, v, d = one.kept()
            yield pa.RecordBatch.from_arrays([pa.array(ids[r], pa.int64()), pa.array(np.full(len(r), p, np.int32)), pa.array(v, pa.int64()), pa.array(d)], names=["q_id", "part", "vec_id", "dist"])

    return vectors.mapInArrow(run, FOUND)


def knn(vectors: DataFrame, queries: DataFrame, k: int, metric: str = "l2", exclude_self: bool = False, scope: str = "any", per_part: bool = False, block: int = BLOCK) -> DataFrame:
    """``(q_id, rank, vec_id, dist)``; for ``ip`` the distance is the negative product.

    ``vectors`` and ``queries`` are ``(vec_id, x)``, with ``part`` for a ``scope`` of ``same`` or ``other`` parts only;
    ``per_part`` ranks each part of the vectors apart and keeps its number.
    """
    distance.known(metric)
    if k < 1:
        raise ValueError(f"k must be at least 1, not {k}")
    with_part = lambda df: df if "part" in df.columns else df.withColumn("part", F.lit(0))
    shape = lambda df: with_part(df).select("vec_id", F.col("part").cast("int").alias("part"), "x")
    vectors, queries = shape(vectors), shape(queries)
    found = blocks(vectors, queries, block, FOUND, lambda v, pack: _candidates(v, pack, k, metric, exclude_self, scope, per_part))
    keys = ["q_id", "part"] if per_part else ["q_id"]
    best = Window.partitionBy(*keys).orderBy("dist", "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return ranked.select(*keys, F.col("rank").cast("int").alias("rank"), "vec_id", "dist")


def twin_knn(vectors: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """:func:`knn` of all vectors without themselves, where many are equal: pairs of distinct vectors are measured, not of rows.

    Distinct vectors go by the lowest id of each. What lies behind k + 1 of them in order of distance and that id has k + 1 rows
    before it, so their k + 1 lowest ids each are enough, for a row itself and its k nearest.
    """
    v = vectors.select("vec_id", "x")
    spark = v.sparkSession
    lowest = v.withColumn("n", F.row_number().over(Window.partitionBy("x").orderBy("vec_id"))).where(F.col("n") <= k + 1)
    kinds = lowest.groupBy("x").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))
    kinds = stage(kinds.select(F.col("ids")[0].alias("vec_id"), "x", "ids").repartition(spark.sparkContext.defaultParallelism, "x"), "twin-kinds")
    near = knn(kinds, kinds, k + 1, metric)
    rows = near.join(kinds.select("vec_id", "ids"), "vec_id").select("q_id", "dist", F.explode("ids").alias("vec_id"))
    first = rows.withColumn("n", F.row_number().over(Window.partitionBy("q_id").orderBy("dist", "vec_id"))).where(F.col("n") <= k + 1)
    lists = first.groupBy(F.col("q_id").alias("kind")).agg(F.array_sort(F.collect_list(F.struct("dist", "vec_id"))).alias("near"))
    mine = v.join(kinds.select("x", F.col("vec_id").alias("kind")), "x").select("vec_id", "kind").join(lists, "kind")
    others = F.slice(F.filter("near", lambda n: n.vec_id != F.col("vec_id")), 1, k)
    out = mine.select(F.col("vec_id").alias("q_id"), F.posexplode(others).alias("rank", "n"))
    return out.select("q_id", (F.col("rank") + 1).alias("rank"), F.col("n.vec_id").alias("vec_id"), F.col("n.dist").alias("dist"))


def graph(vectors: DataFrame, k: int, metric: str = "l2", scope: str = "any") -> DataFrame:
    """The exact neighbour graph ``(src, dst, dist, rank)``, over all vectors or inside the parts."""
    found = knn(vectors, vectors, k, metric, exclude_self=True, scope=scope)
    return found.select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist", "rank")


def within(vectors: DataFrame, queries: DataFrame, radius: float, metric: str = "l2", block: int = BLOCK) -> DataFrame:
    """All pairs ``(q_id, vec_id, dist)`` within a radius, queries in bounded blocks."""
    distance.known(metric)
    schema = "q_id long, vec_id long, dist double"

    def ask(vectors: DataFrame, pack) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = pack.value
            ids, q = held.column("vec_id").to_numpy(), distance.matrix(held.column("x"))
            for batch in batches:
                for at in range(0, batch.num_rows, ROWS):
                    some = batch.slice(at, ROWS)
                    x, xid = distance.matrix(some.column("x")), some.column("vec_id").to_numpy()
                    if not len(x) or not len(q):
                        continue
                    rough, slack = distance.rough(metric, q, x)
                    limit = radius * radius if metric == "l2" else radius
                    r, c = np.nonzero(rough <= limit + slack[:, None] + 1e-12 * abs(limit))
                    for lo in range(0, len(r), PAIRS):
                        a, b = r[lo : lo + PAIRS], c[lo : lo + PAIRS]
                        d = distance.rows(metric, q[a], x[b])
                        keep = d <= radius
                        yield pa.RecordBatch.from_arrays([pa.array(ids[a[keep]], pa.int64()), pa.array(xid[b[keep]], pa.int64()), pa.array(d[keep])], names=["q_id", "vec_id", "dist"])

        return vectors.mapInArrow(run, schema)

    return blocks(vectors.select("vec_id", "x"), queries.select("vec_id", "x"), block, schema, ask)
