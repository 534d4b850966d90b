"""Measures of graphs and of search results."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardweave.staging import drop, stage

#: Edges that one task may walk for strong components.
SCC_LIMIT = 5_000_000


def recall(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """One row ``(k, recall)``: shared ids of the k returned and the k true ones, over k, mean over queries."""
    t = truth.where(F.col("rank") <= k).select("q_id", "vec_id")
    f = found.where(F.col("rank") <= k).select("q_id", "vec_id").withColumn("hit", F.lit(1))
    each = t.join(f, ["q_id", "vec_id"], "left").groupBy("q_id").agg((F.sum(F.coalesce("hit", F.lit(0))) / k).alias("r"))
    return each.agg(F.lit(k).alias("k"), F.avg("r").alias("recall"))


def graph_recall(edges: DataFrame, exact: DataFrame) -> DataFrame:
    """The share of the exact graph's edges that ``edges`` has."""
    met = exact.select("src", "dst").join(edges.select("src", "dst", F.lit(1).alias("hit")), ["src", "dst"], "left")
    return met.agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count("*")).alias("recall"))


def composition(sub: DataFrame, full: DataFrame, origin: DataFrame) -> DataFrame:
    """Of a full graph's edges, the shares that the parts' graphs had, that are new inside a part, and new across parts."""
    part = origin.select("vec_id", "part")
    met = full.select("src", "dst").join(sub.select("src", "dst", F.lit(1).alias("had")), ["src", "dst"], "left")
    met = met.join(part.select(F.col("vec_id").alias("src"), F.col("part").alias("p")), "src").join(part.select(F.col("vec_id").alias("dst"), F.col("part").alias("q")), "dst")
    share = lambda c: (F.sum(c.cast("long")) / F.count("*"))
    had = F.col("had").isNotNull()
    return met.agg(share(had).alias("kept"), share(~had & (F.col("p") == F.col("q"))).alias("new_same"), share(~had & (F.col("p") != F.col("q"))).alias("new_cross"))


def degrees(edges: DataFrame, vectors: DataFrame) -> DataFrame:
    """One row: edges, orphans, rows without an out-edge, greatest and mean degrees. Aggregates by vertex, salted by the partial step."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e")).select("e.*")
    each = vectors.select(F.col("vec_id").alias("id"), F.lit(0).alias("o"), F.lit(0).alias("i")).unionByName(ends).groupBy("id").agg(F.sum("o").alias("o"), F.sum("i").alias("i"))
    return each.agg(
        F.sum("o").alias("n_edges"), F.sum((F.col("i") == 0).cast("long")).alias("n_orphans"), F.sum((F.col("o") == 0).cast("long")).alias("n_dead_ends"),
        F.max("i").alias("max_indegree"), F.max("o").alias("max_outdegree"), F.avg("o").alias("mean_degree"),
    )


def size(edges: DataFrame, bytes_an_edge: int = 12) -> DataFrame:
    return edges.agg(F.count("*").alias("n_edges"), (F.count("*") * bytes_an_edge).alias("n_bytes"))


def stored(spark: SparkSession, path: str) -> DataFrame:
    """One row ``(n_files, n_bytes)`` of the Parquet files under a path."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").load(path)
    return files.agg(F.count("*").alias("n_files"), F.sum("length").alias("n_bytes"))


def objective(spark: SparkSession, build_cost: float, merge_cost: float, qps: float, recall: float) -> DataFrame:
    """What a merge is after, in one row: what it saves against a build of the whole, at which rate and recall."""
    row = (float(build_cost), float(merge_cost), float(build_cost - merge_cost), float(build_cost / max(merge_cost, 1e-12)), float(qps), float(recall))
    return spark.createDataFrame([row], "build_cost double, merge_cost double, saved double, speedup double, qps double, recall double")


def delta(with_it: DataFrame, without: DataFrame) -> DataFrame:
    """The change of recall between two one-row results of :func:`recall`."""
    return with_it.select("k", F.col("recall").alias("a")).join(without.select("k", F.col("recall").alias("b")), "k").select("k", (F.col("a") - F.col("b")).alias("change"))


def reachable(edges: DataFrame, start: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """Vertices ``(id)`` on directed paths from ``start (id)``: one join of the frontier a round."""
    seen = stage(start.select("id").distinct(), "reach")
    front = seen
    for _ in range(max_rounds):
        new = front.join(edges, F.col("id") == F.col("src")).select(F.col("dst").alias("v")).distinct()
        new = stage(new.join(seen, F.col("v") == F.col("id"), "left_anti").select(F.col("v").alias("id")), "reach-front")
        if new.isEmpty():
            break
        front, seen = new, stage(seen.unionByName(new), "reach")
    return seen


def strong_components(edges: DataFrame, vectors: DataFrame, limit: int = SCC_LIMIT) -> DataFrame:
    """One row ``(n_scc)``. Vertices that can't lie on a cycle are trimmed by joins first; the rest goes through one task
    while its edges fit ``limit``, and by colours in joins beyond, with the same result."""
    import pyarrow as pa

    core = stage(edges.select("src", "dst").where("src <> dst").distinct(), "scc")
    while True:
        n = core.count()
        out = core.select(F.col("src").alias("v")).distinct()
        into = core.select(F.col("dst").alias("v")).distinct()
        both = out.intersect(into)
        left = core.join(both, F.col("src") == F.col("v"), "left_semi").join(both, F.col("dst") == F.col("v"), "left_semi")
        left = stage(left, "scc")
        drop(core)
        core = left
        if core.count() == n:
            break
    inside = core.select(F.col("src").alias("v")).distinct()
    alone = vectors.select(F.col("vec_id").alias("v")).join(inside, "v", "left_anti").count()
    if n <= limit:

        def walk(t: pa.Table) -> pa.Table:
            return pa.table({"n": pa.array([tarjan(t.column("src").to_pylist(), t.column("dst").to_pylist())], pa.int64())})

        found = core.groupBy(F.lit("all")).applyInArrow(walk, "n long").first()
        count = found["n"] if found else 0
    else:
        count = _by_colour(core, inside)
    return vectors.sparkSession.createDataFrame([(alone + count,)], "n_scc long")


def _by_colour(core: DataFrame, inside: DataFrame) -> int:
    """Every vertex takes the smallest id that reaches it as its colour; what reaches a colour's own vertex back, inside the
    colour, is one component. All colours at once, until no vertex is left: rounds by components on a path, not by components."""
    count = 0
    while not inside.isEmpty():
        colour = stage(inside.select("v", F.col("v").alias("c")), "scc-colour")
        while True:  # the smallest id moves along all edges
            met = core.join(colour, F.col("src") == F.col("v")).groupBy(F.col("dst").alias("w")).agg(F.min("c").alias("d"))
            new = stage(colour.join(met, F.col("v") == F.col("w"), "left").select("v", F.least("c", F.coalesce("d", "c")).alias("c")), "scc-colour")
            still = new.join(colour.withColumnsRenamed({"v": "u", "c": "e"}), (F.col("v") == F.col("u")) & (F.col("c") == F.col("e")), "left_anti").isEmpty()
            drop(colour)
            colour = new
            if still:
                break
        one, two = colour.withColumnsRenamed({"v": "src", "c": "a"}), colour.withColumnsRenamed({"v": "dst", "c": "b"})
        same = stage(core.join(one, "src").join(two, "dst").where("a = b").select(F.col("dst").alias("src"), F.col("src").alias("dst")), "scc-same")
        back = reachable(same, colour.where("v = c").select(F.col("v").alias("id")))
        count += colour.where("v = c").count()
        inside = stage(inside.join(back, F.col("v") == F.col("id"), "left_anti"), "scc-left")
        core = stage(core.join(back, F.col("src") == F.col("id"), "left_anti").join(back, F.col("dst") == F.col("id"), "left_anti"), "scc-core")
    return count


def tarjan(src: list[int], dst: list[int]) -> int:
    """The number of strong components of the vertices that edges name, without recursion."""
    to: dict[int, list[int]] = {}
    for a, b in zip(src, dst, strict=True):
        to.setdefault(a, []).append(b)
        to.setdefault(b, [])
    index: dict[int, int] = {}
    low: dict[int, int] = {}
    on: set[int] = set()
    stack: list[int] = []
    count = 0
    for root in sorted(to):
        if root in index:
            continue
        work = [(root, iter(to[root]))]
        index[root] = low[root] = len(index)
        stack.append(root)
        on.add(root)
        while work:
            v, rest = work[-1]
            for u in rest:
                if u not in index:
                    index[u] = low[u] = len(index)
                    stack.append(u)
                    on.add(u)
                    work.append((u, iter(to[u])))
                    break
                if u in on:
                    low[v] = min(low[v], index[u])
            else:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[v])
                if low[v] == index[v]:
                    count += 1
                    while True:
                        u = stack.pop()
                        on.discard(u)
                        if u == v:
                            break
    return count


def predict(spark: SparkSession, sizes: list[int], k: int, dim: int, rounds: int = 8, cost: float = 1.0) -> DataFrame:
    """The cost model of lift, refine and tower for indexes of the given sizes."""
    n, h = sum(sizes), len(sizes)
    lift = sum(a * b ** (2 / dim) * math.log(b) for i, a in enumerate(sizes) for j, b in enumerate(sizes) if i != j) * k * cost / max(1, h - 1)
    row = (n, h, k, dim, lift, rounds * n * k * k * cost, n / k * math.log(max(2, n / k)))
    return spark.createDataFrame([row], "n long, h int, k int, dim int, lift_cost double, refine_cost double, tower_cost double")


def interpolated(curve: DataFrame, at: float, given: str, wanted: str) -> DataFrame:
    """``wanted`` where ``given`` is ``at``, linear between the neighbouring points of a curve."""
    order = Window.orderBy(given)  # the points of one sweep
    step = curve.withColumns({"_x": F.lead(given).over(order), "_y": F.lead(wanted).over(order)})
    met = step.where((F.col(given) <= at) & (F.col("_x") > at))
    value = F.col(wanted) + (F.lit(at) - F.col(given)) * (F.col("_y") - F.col(wanted)) / (F.col("_x") - F.col(given))
    return met.select(F.lit(at).alias(given), value.alias(wanted))


def timed(action: Callable[[], object]) -> float:
    start = time.perf_counter()
    action()
    return time.perf_counter() - start


def qps(query: Callable[[], DataFrame], n: int, runs: int = 3) -> float:
    """Queries a second at the median of warm runs, results forced by the noop sink."""
    force = lambda: query().write.format("noop").mode("overwrite").save()
    force()
    return n / statistics.median(timed(force) for _ in range(runs))
