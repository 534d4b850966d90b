"""The strategies that a merge is compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import exact, lift, refine, search, thin
from shardweave.plans import builders
from shardweave.plans.builders import EDGES, Layered, Net, insert_flat, medoid, packed, refit, shard_arrays
from shardweave.staging import drop, stage


def rebuild(vectors: DataFrame, kind: str, metric: str = "l2", **how) -> DataFrame:
    """The index of all vectors, built anew in one shard."""
    return builders.build(vectors.select("vec_id", "x"), kind, metric, **how)


def _one_shard(vectors: DataFrame, kernel, metric: str) -> DataFrame:
    """Run ``kernel(net, parts)`` over all vectors in one task; ``parts`` are the positions' indexes."""

    def run(t: pa.Table) -> pa.Table:
        ids, x = shard_arrays(t)
        part = t.column("part").to_numpy()[np.argsort(t.column("vec_id").to_numpy(), kind="stable")]
        net = Net(x, metric)
        layers = kernel(net, part)
        return packed(net, ids, layers, 0)

    return vectors.select("vec_id", "x", F.col("part").cast("int").alias("part")).groupBy(F.lit("all")).applyInArrow(run, EDGES)


def insert_all(vectors: DataFrame, kind: str = "hnsw", m: int = 16, ef: int = 200, seed: int = 1, metric: str = "l2", low_ef: int | None = None) -> DataFrame:
    """Build the largest part's index, then insert the vectors of the other parts one by one; only insertions are counted.

    ``low_ef`` inserts with less effort, as a segment merge does.
    """

    def kernel(net: Net, part: np.ndarray) -> dict:
        kinds, counts = np.unique(part, return_counts=True)
        first = kinds[np.lexsort((kinds, -counts))][0]
        order = [*np.flatnonzero(part == first).tolist(), *np.flatnonzero(part != first).tolist()]
        own = int((part == first).sum())
        if kind == "nsw":
            for i, v in enumerate(order):
                if i == own:
                    net.ndc = 0
                insert_flat(net, v, m, low_ef or ef if i >= own else ef, order[0])
            return {0: net.to}
        graph = Layered(net, m, ef, seed)
        graph.grow(order[:own])
        net.ndc = 0
        graph.grow(order[own:], low_ef)
        return graph.built()

    return _one_shard(vectors, kernel, metric)


def segment_merge(vectors: DataFrame, m: int = 16, ef: int = 200, low_ef: int = 50, seed: int = 1, metric: str = "l2") -> DataFrame:
    return insert_all(vectors, "hnsw", m, ef, seed, metric, low_ef)


def fresh_merge(edges: DataFrame, vectors: DataFrame, degree: int = 16, size: int = 50, alpha: float = 1.2, deleted: DataFrame | None = None, metric: str = "l2") -> DataFrame:
    """Batch insertion into the graph of part 0: bridge deleted vertices, search and prune the other parts' vectors on
    the old graph, then patch the reverse edges. Three passes, as on storage."""
    marked = deleted.select("vec_id").distinct().withColumn("dead", F.lit(True)) if deleted is not None else vectors.limit(0).select("vec_id", F.lit(True).alias("dead"))
    lists = edges.groupBy("src").agg(F.collect_list("dst").alias("to"))
    rows = vectors.join(lists, vectors["vec_id"] == lists["src"], "left").join(marked, "vec_id", "left")
    rows = rows.select("vec_id", "x", F.col("part").cast("int").alias("part"), F.coalesce("to", F.array().cast("array<long>")).alias("to"), F.coalesce("dead", F.lit(False)).alias("dead"))

    def run(t: pa.Table) -> pa.Table:
        ids, x = shard_arrays(t)
        order = np.argsort(t.column("vec_id").to_numpy(), kind="stable")
        lists = t.column("to").to_pylist()
        part, to = t.column("part").to_numpy()[order], [lists[i] for i in order]
        at = {int(v): i for i, v in enumerate(ids)}
        net = Net(x, metric)
        dead = set(np.flatnonzero(t.column("dead").to_numpy(zero_copy_only=False)[order]).tolist())
        net.to = {i: [at[u] for u in to[i] if u in at] for i in range(len(ids)) if part[i] == 0}
        insert_frozen(net, [v for v in np.flatnonzero(part != 0).tolist() if v not in dead], dead, degree, size, alpha)
        return packed(net, ids, {0: net.to}, 0)

    return rows.groupBy(F.lit("all")).applyInArrow(run, EDGES)


def insert_frozen(net: Net, new: list[int], dead: set[int], degree: int, size: int, alpha: float) -> None:
    """The three passes of :func:`fresh_merge` on positions. All new vertices are searched on the graph without them, so in step."""
    for v in list(net.to):
        if v not in dead and any(u in dead for u in net.to[v]):
            wide = [u for u in net.to[v] if u not in dead] + [w for u in net.to[v] if u in dead for w in net.to.get(u, []) if w not in dead]
            net.to[v] = net.prune(net.sorted(v, wide), degree, "alpha", alpha)
    for v in dead:
        net.to.pop(v, None)
    alive = sorted(net.to)
    entry = alive[medoid(net.x[alive])] if alive else 0
    if not new:
        return
    src, dst = np.repeat(alive, [len(net.to[v]) for v in alive]).astype(np.int64), np.array([u for v in alive for u in net.to[v]], np.int64)
    old, own = search.Shard(np.arange(len(net.x)), net.x, src, dst, net.metric), np.array(new)
    _, _, ndc, _, seen = search.beams(net.x, old.links, net.x[own], np.full((len(own), 1), entry), size, net.metric, True, single=net.single)
    net.ndc += int(ndc.sum())
    lists = builders.Lists(net, degree)
    back = {v: row[row >= 0].tolist() for v, row in zip(new, lists.pruned(*seen, own, "alpha", alpha), strict=True)}
    net.to |= {v: list(us) for v, us in back.items()}
    delta: dict[int, list[int]] = {}
    for v, us in back.items():
        for u in us:
            delta.setdefault(u, []).append(v)
    for u, vs in delta.items():
        net.to[u] = list(dict.fromkeys(net.to[u] + vs))
    full = [u for u in delta if len(net.to[u]) > degree]
    rows = np.repeat(np.arange(len(full)), [len(net.to[u]) for u in full]).astype(np.int64)
    every = np.array([w for u in full for w in net.to[u]], np.int64)
    for u, row in zip(full, lists.pruned(rows, every, np.array(full, np.int64), "alpha", alpha), strict=True):
        net.to[u] = row[row >= 0].tolist()


def prefix_doubling(vectors: DataFrame, degree: int = 16, size: int = 50, alpha: float = 1.2, seed: int = 1, metric: str = "l2") -> DataFrame:
    """Batches of doubling size, each searched on the graph of the batches before it, frozen."""

    def kernel(net: Net, part: np.ndarray) -> dict:
        order = builders.mixed(len(net.x), seed).tolist()
        done = 1
        net.to = {order[0]: []} if order else {}
        while done < len(order):
            batch = order[done : 2 * done]
            frozen = {v: list(us) for v, us in net.to.items()}
            found = {}
            for v in batch:
                net.to = frozen
                seen: list[tuple[float, int]] = []
                net.search(v, [order[0]], size, seen)
                found[v] = net.prune(net.sorted(v, [u for _, u in seen]), degree, "alpha", alpha)
            net.to = frozen | {v: list(us) for v, us in found.items()}
            delta: dict[int, list[int]] = {}
            for v, us in found.items():
                for u in us:
                    delta.setdefault(u, []).append(v)
            for u, vs in delta.items():
                both = list(dict.fromkeys(net.to[u] + vs))
                net.to[u] = both if len(both) <= degree else net.prune(net.sorted(u, both), degree, "alpha", alpha)
            done += len(batch)
        if order:
            for v in order:
                refit(net, v, order[0], degree, size, alpha)
        return {0: net.to}

    return _one_shard(vectors if "part" in vectors.columns else vectors.withColumn("part", F.lit(0)), kernel, metric)


def insert_batch(edges: DataFrame, vectors: DataFrame, batch: DataFrame, degree: int, size: int, alpha: float, metric: str) -> tuple[DataFrame, int]:
    """A batch of new vectors into a stored graph, by two scans over it: each new vertex is searched on the graph as it was and
    pruned; reverse edges are sent to their sources, and lists that overflow are pruned. Edges, and distances evaluated."""
    entry = stage(search.medoids(vectors.select("vec_id", "x"), metric), "batch-entry")
    met = stage(search.resident(edges, vectors.select("vec_id", "x"), batch.select("vec_id", "x"), entry, size, size, metric), "batch-found")
    found = met.select(F.col("q_id").alias("src"), F.col("vec_id").alias("dst"), "dist")
    every = vectors.select("vec_id", "x").unionByName(batch.select("vec_id", "x"))
    own = stage(thin.select(found, every, degree, "alpha", "off", alpha, metric=metric), "batch-own")
    back = own.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")
    both = edges.select("src", "dst", "dist").unionByName(own).unionByName(back).groupBy("src", "dst").agg(F.min("dist").alias("dist"))
    sized = stage(both.withColumn("n", F.count("*").over(Window.partitionBy("src"))), "batch-both")
    full = sized.where(F.col("n") > degree)
    pruned = thin.select(full.select("src", "dst", "dist"), every, degree, "alpha", "off", alpha, metric=metric)
    out = stage(sized.where(F.col("n") <= degree).select("src", "dst", "dist").unionByName(pruned), "batch")
    pairs = lambda df: df.groupBy("src").count().agg(F.sum(F.floor(F.col("count") * (F.col("count") - 1) / 2))).first()[0] or 0
    cost = (met.where("rank = 1").agg(F.sum("ndc")).first()[0] or 0) + pairs(found) + pairs(full)
    for used in (entry, met, own, sized):
        drop(used)
    return out, int(cost)


def bridged(edges: DataFrame, vectors: DataFrame, deleted: DataFrame, degree: int, alpha: float, metric: str = "l2") -> DataFrame:
    """One scan that takes deleted vertices ``(vec_id)`` out: who pointed to one gets its neighbours as candidates and is pruned."""
    gone = deleted.select(F.col("vec_id").alias("v")).distinct()
    e = edges.select("src", "dst", "dist").join(gone, F.col("src") == F.col("v"), "left_anti")
    lost = e.join(gone, F.col("dst") == F.col("v"), "left_semi")
    live = e.join(gone, F.col("dst") == F.col("v"), "left_anti")
    over = lost.select(F.col("src").alias("s"), F.col("dst").alias("d")).join(edges.select("src", "dst"), F.col("d") == F.col("src")).select(F.col("s").alias("src"), "dst").where("src <> dst")
    over = over.join(gone, F.col("dst") == F.col("v"), "left_anti").distinct()
    x, y = vectors.select(F.col("vec_id").alias("src"), "x"), vectors.select(F.col("vec_id").alias("dst"), F.col("x").alias("y"))
    measured = distance.measured(over.join(x, "src").join(y, "dst").select("src", "dst", "x", "y"), "x", "y", metric=metric)
    touched = lost.select(F.col("src").alias("t")).distinct()
    wide = live.join(touched, F.col("src") == F.col("t"), "left_semi").unionByName(measured).groupBy("src", "dst").agg(F.min("dist").alias("dist"))
    return live.join(touched, F.col("src") == F.col("t"), "left_anti").unionByName(thin.select(wide, vectors, degree, "alpha", "off", alpha, metric=metric))


def fresh_scans(edges: DataFrame, vectors: DataFrame, degree: int = 16, size: int = 50, alpha: float = 1.2, deleted: DataFrame | None = None, metric: str = "l2") -> tuple[DataFrame, int]:
    """:func:`fresh_merge` over stored tables: a scan that bridges deleted vertices, one that searches and prunes the vectors of
    the other parts, one that patches. No task holds more than a shard's search; edges, and distances evaluated."""
    now = edges
    if deleted is not None:
        now = stage(bridged(edges, vectors, deleted, degree, alpha, metric), "bridged")
        vectors = vectors.join(deleted.select("vec_id"), "vec_id", "left_anti")
    old = vectors.where("part = 0")
    inside = now.join(old.select(F.col("vec_id").alias("src")), "src", "left_semi").select("src", "dst", "dist")
    return insert_batch(inside, old, vectors.where("part <> 0"), degree, size, alpha, metric)


def parallel_doubling(vectors: DataFrame, degree: int = 16, size: int = 50, alpha: float = 1.2, seed: int = 1, metric: str = "l2") -> tuple[DataFrame, int]:
    """Batches of doubling size, the vectors of a batch searched in parallel by all tasks. Batches go by a hash of the id, so
    there is no global order. Edges, and distances evaluated."""
    v = vectors.select("vec_id", "x")
    n = v.count()
    turn = (F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(1 << 40)).cast("double") + 0.5) / float(1 << 40) * n
    start = 2 * degree
    dealt = stage(v.withColumn("turn", F.greatest(F.lit(0), F.ceil(F.log2(turn / start))).cast("int")), "doubling")
    first = dealt.where("turn = 0")
    now = stage(exact.graph(first, degree, metric).select("src", "dst", "dist"), "batch")
    cost = first.count() ** 2 // 2
    for at in range(1, (dealt.agg(F.max("turn")).first()[0] or 0) + 1):
        new, more = insert_batch(now, dealt.where(F.col("turn") < at), dealt.where(F.col("turn") == at), degree, size, alpha, metric)
        drop(now)
        now, cost = new, cost + more
    drop(dealt)
    return now, cost


def knng_merge(edges: DataFrame, vectors: DataFrame, k: int, max_rounds: int = 8, metric: str = "l2", seed: int = 7) -> tuple[DataFrame, list[dict]]:
    """Near halves of the lists, random foreign ids, then local joins over all pairs; neither thinning nor repair."""
    half = lift.best(edges, max(1, k // 2))
    start = lift.best(half.select("src", "dst", "dist").unionByName(lift.random_cross(vectors, k - k // 2, metric, seed).select("src", "dst", "dist")), k)
    log: list[dict] = []
    return refine.run(start.select("src", "dst", "dist"), vectors, vectors.select("vec_id", "part"), k, max_rounds, "all", "off", metric, log=log.append), log


def naive_union(edges: DataFrame) -> DataFrame:
    """The graphs side by side: no edge crosses parts."""
    return edges.select("src", "dst", "dist").distinct()


def clusters(vectors: DataFrame, c: int, ell: int = 2, rounds: int = 8) -> DataFrame:
    """``(vec_id, x, part)``: every vector in its ``ell`` nearest of c clusters. Centres (c rows) start far apart and move to their means."""
    x = vectors.select("vec_id", F.col("x").cast("array<double>").alias("x"))
    first = np.array(x.orderBy("vec_id").first()["x"])
    centres = [first]
    for _ in range(c - 1):
        pack = np.array(centres)
        far = _nearest(x, pack, 1).orderBy(F.desc("dist"), "vec_id").limit(1).join(x.withColumnRenamed("vec_id", "v"), F.col("vec_id") == F.col("v")).first()
        centres.append(np.array(far["x"]))
    for _ in range(rounds):
        near = _nearest(x, np.array(centres), 1).join(x.withColumnRenamed("vec_id", "v"), F.col("vec_id") == F.col("v"))
        flat = near.select("part", F.posexplode("x").alias("pos", "value")).groupBy("part", "pos").agg(F.avg("value").alias("avg"))
        for r in flat.groupBy("part").agg(F.array_sort(F.collect_list(F.struct("pos", "avg"))).alias("s")).collect():
            centres[r["part"]] = np.array([p["avg"] for p in r["s"]])
    return _nearest(x, np.array(centres), ell).join(vectors.select(F.col("vec_id").alias("v"), F.col("x")), F.col("vec_id") == F.col("v")).select("vec_id", "x", "part")


def _nearest(x: DataFrame, centres: np.ndarray, ell: int) -> DataFrame:
    def run(batches):
        for b in batches:
            if b.num_rows:
                d = distance.block("l2", distance.matrix(b.column("x")), centres)
                at = np.argsort(d, axis=1, kind="stable")[:, :ell]
                r = np.repeat(np.arange(len(d)), at.shape[1])
                yield pa.RecordBatch.from_arrays([b.column("vec_id").take(pa.array(r)), pa.array(at.ravel().astype(np.int32)), pa.array(d[r, at.ravel()])], names=["vec_id", "part", "dist"])

    return x.mapInArrow(run, "vec_id long, part int, dist double")


def overlap_build(vectors: DataFrame, c: int, ell: int, kind: str = "vamana", degree: int = 16, metric: str = "l2", **how) -> DataFrame:
    """A graph a cluster, vectors in ``ell`` clusters each, edges united and thinned to the degree."""
    parts = stage(clusters(vectors, c, ell), "clusters")
    built = builders.build(parts, kind, metric, **({"degree": degree} | how)).where("layer = 0")
    once = built.groupBy("src", "dst").agg(F.min("dist").alias("dist"))
    return thin.select(once, vectors, degree, "alpha", "off", 1.2, metric=metric)


def base_layer(index: DataFrame) -> DataFrame:
    return index.where("layer = 0").select("src", "dst", "dist")


def cost(index: DataFrame) -> int:
    return index.agg(F.sum("ndc")).first()[0] or 0


def best_rank(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("q_id").orderBy("dist", "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


__all__ = [
    "rebuild", "insert_all", "segment_merge", "fresh_merge", "prefix_doubling", "knng_merge", "naive_union", "clusters", "overlap_build", "base_layer", "cost", "best_rank", "search",
]
