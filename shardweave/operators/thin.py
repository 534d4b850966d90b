"""Thinning a neighbour graph to a search graph: occlusion rules, and reverse edges under the degree bound."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import refine

RULES = ("kept", "lune", "alpha", "tau")


def occluded(near: np.ndarray, between: np.ndarray, rule: str, alpha: float, tau: float, by: np.ndarray | None = None) -> np.ndarray:
    """``[.., w, v]``: whether w, nearer than v, hides v. ``near`` are distances to the source, ``between`` those of neighbours;
    ``by`` are the distances of w where these are not all of ``near``."""
    to_v, to_w = near[..., None, :], (near if by is None else by)[..., :, None]
    if rule == "kept":
        return between <= to_v
    if rule == "alpha":
        return alpha * between <= to_v
    if rule == "tau":
        return (to_w < to_v) & (between < to_v - 3 * tau)
    return (to_w < to_v) & (between < to_v)


def choose(near: np.ndarray, between: np.ndarray, real: np.ndarray, guarded: np.ndarray, cap: int, rule: str = "kept", alpha: float = 1.0, tau: float = 0.0) -> np.ndarray:
    """Which neighbours stay, for many sources at once; neighbours are in order of distance, ``real`` marks those that exist."""
    hides = occluded(near, between, rule, alpha, tau) & real[..., :, None]
    kept = np.zeros(real.shape, bool)
    for v in range(real.shape[1]):
        by = np.ones_like(kept[:, :v]) if rule == "lune" else kept[:, :v]
        hidden = (hides[:, :v, v] & by).any(axis=1)
        kept[:, v] = real[:, v] & (guarded[:, v] | ~hidden) & (kept[:, :v].sum(axis=1) < cap)
    return kept


def select(edges: DataFrame, vectors: DataFrame, k: int | None = None, rule: str = "kept", guard: str = "static", alpha: float = 1.0, tau: float = 0.0, metric: str = "l2") -> DataFrame:
    """The edges that a rule keeps, ``(src, dst, dist)``. ``guard``: an only in-edge stays (``static``, by the indegrees
    before), also if it becomes one on the way (``live``, sources in order of id, in one task), or not (``off``).

    Lists are bounded by the degree, so a row holds a source with the vectors of its neighbours.
    """
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}, not {rule!r}")
    if guard not in ("static", "live", "off"):
        raise ValueError(f"guard must be static, live or off, not {guard!r}")
    cap = k or 1 << 30
    e = edges.select("src", "dst", "dist")
    degree = e.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("indeg"))
    met = e.join(degree, F.col("dst") == F.col("id")).join(vectors.select(F.col("vec_id").alias("v"), "x"), F.col("dst") == F.col("v"))
    row = F.struct("dist", "dst", "indeg", "x")
    lists = met.groupBy("src").agg(F.array_sort(F.collect_list(row)).alias("n"))
    flat = lists.select("src", F.transform("n", lambda s: s.dist).alias("dist"), F.transform("n", lambda s: s.dst).alias("dst"), F.transform("n", lambda s: s.indeg).alias("indeg"), F.flatten(F.transform("n", lambda s: s.x)).alias("x"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spare: dict[int, int] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            sizes = np.diff(batch.column("dst").offsets.to_numpy())
            most = int(sizes.max())
            at = np.arange(most)[None, :] < sizes[:, None]
            padded = lambda name, kind, at=at: _pad(batch.column(name).flatten().to_numpy(zero_copy_only=False), at, kind)  # noqa: E731, B023
            near, dst, indeg = padded("dist", np.float64), padded("dst", np.int64), padded("indeg", np.int64)
            values = batch.column("x").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(int(sizes.sum()), -1)
            x = np.zeros((*at.shape, values.shape[1]))
            x[at] = values
            src = batch.column("src").to_numpy()
            keep = np.zeros_like(at)
            step = max(1, (4 << 20) // max(1, most * most * x.shape[2]))
            for lo in range(0, len(src), 1 if guard == "live" else step):
                some = slice(lo, lo + (1 if guard == "live" else step))
                between = distance.rows(metric, x[some][:, :, None, :], x[some][:, None, :, :])
                if guard == "live":
                    left = np.array([[spare.get(int(d), int(n)) for d, n in zip(dst[lo], indeg[lo], strict=True)]])
                    keep[some] = choose(near[some], between, at[some], left == 1, cap, rule, alpha, tau)
                    for d, n, stays, real in zip(dst[lo].tolist(), left[0].tolist(), keep[lo], at[lo], strict=True):
                        if real and not stays:
                            spare[d] = n - 1
                else:
                    guarded = (indeg[some] == 1) & (guard == "static")
                    keep[some] = choose(near[some], between, at[some], guarded, cap, rule, alpha, tau)
            rows = np.broadcast_to(src[:, None], at.shape)
            yield pa.RecordBatch.from_arrays([pa.array(rows[keep]), pa.array(dst[keep]), pa.array(near[keep])], names=["src", "dst", "dist"])

    ordered = flat.coalesce(1).sortWithinPartitions("src") if guard == "live" else flat
    return ordered.mapInArrow(run, "src long, dst long, dist double")


def _pad(values: np.ndarray, at: np.ndarray, kind) -> np.ndarray:
    out = np.zeros(at.shape, kind)
    out[at] = values
    return out


def reciprocate(edges: DataFrame, k: int) -> DataFrame:
    """Edges and their reverses, the nearest k of every vertex, ``(src, dst, dist, rank)``.

    A hub's reverse edges are cut in two steps: the rank filter prunes each task's part before the shuffle.
    """
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")
    both = edges.select("src", "dst", "dist").unionByName(back).groupBy("src", "dst").agg(F.min("dist").alias("dist"))
    order = Window.partitionBy("src").orderBy("dist", "dst")
    return both.withColumn("rank", F.row_number().over(order).cast("int")).where(F.col("rank") <= k)


def new_orphans(before: DataFrame, after: DataFrame, vectors: DataFrame) -> DataFrame:
    """Vertices that thinning left without an in-edge."""
    return refine.orphans(after, vectors).join(refine.orphans(before, vectors), "id", "left_anti")
