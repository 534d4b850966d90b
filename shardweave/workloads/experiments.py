"""Experiments on the embeddings: strategies, sweeps and ablations as tables of measures.

All cost figures are counts of distances, so they hold on any machine; times are for ``bench.py``. A merge's count has
its foreign searches, its local joins and, as if each list were compared in full, its thinning; a builder's has its
searches and the comparisons that its selection makes. Building the inputs counts for none.

Strategies that don't wait for each other run side by side, since many work in a single task: a session's other cores then
have the rest of the work. Only rates are measured alone.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from concurrent.futures import Future, ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardweave.operators import exact, idmap, lift, quality, refine, search, thin, tower
from shardweave.plans import baselines, builders, fuse
from shardweave.sources import tables
from shardweave.staging import stage

#: Degree, pool of a search, results asked for.
K, POOL, ASK = 16, 40, 10
#: Construction effort of the insertion builders, as published.
EFFORT = 200


#: Runs at a time of one experiment.
AT_ONCE = 4


def together(runs: Iterable[Callable[[], list]]) -> list:
    """What independent runs list, in their order; their jobs share the cores."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return [row for rows in [pool.submit(inheritable_thread_target(SparkSession.active())(run)) for run in runs] for row in rows.result()]


def aside(run: Callable) -> Future:
    """``run`` while its caller goes on."""
    pool = ThreadPoolExecutor(1)
    made = pool.submit(inheritable_thread_target(SparkSession.active())(run))
    pool.shutdown(wait=False)
    return made


def beside(run: Callable[[], DataFrame], label: str) -> Future:
    """``run`` staged while its caller goes on."""
    return aside(lambda: stage(run(), label))


def questions(base: DataFrame, asked: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The queries, their exact answers, and where searches of the base begin; none depends on how it is split."""
    asked = stage(asked, "asked")
    return asked, stage(exact.knn(base.select("vec_id", "x"), asked, 100), "truth"), stage(search.medoids(base.select("vec_id", "x")), "entry")


class Bench:
    """Base vectors in parts, queries, truth, and a built input index. ``other``, a strategy over the base, runs beside it all;
    ``known`` are the :func:`questions` of the base where several benches share them."""

    def __init__(self, spark: SparkSession, sf_dir: str, h: int = 2, kind: str = "vamana", k: int = K, larger=None, other: Callable[[DataFrame], DataFrame] | None = None, known: Future | None = None, **how):
        base, asked = tables.base_and_queries(spark, sf_dir)
        base = larger(base) if larger else base
        self.spark, self.k = spark, k
        self.base = stage(idmap.by_hash(base, h, 3) if h > 1 else base.withColumn("part", F.lit(0)), "base")
        self.other = beside(lambda: other(self.base), "other") if other else None
        index = beside(lambda: builders.build(self.base, kind, **({"degree": k, "m": k // 2, "k": k} | how)), "index")
        self.asked, self.truth, self.whole = known.result() if known else questions(self.base, asked)
        self.index = index.result()
        self.edges = baselines.base_layer(self.index)

    def answers(self, edges: DataFrame, pool: int = POOL, ask: int = ASK) -> DataFrame:
        return search.resident(edges, self.base.select("vec_id", "x"), self.asked, self.whole, max(pool, ask), ask)

    def measured(self, name: str, edges: DataFrame, cost: int, pools: Iterable[int] = (POOL,), ask: int = ASK, **more) -> list[dict]:
        edges = stage(edges.select("src", "dst", "dist"), "measured")
        n = edges.count()
        out = []
        for pool in pools:
            got = stage(self.answers(edges, pool, ask), "answers")
            r = quality.recall(got, self.truth, ask).first()["recall"]
            c = got.where("rank = 1").agg(F.avg("ndc").alias("ndc"), F.avg("hops").alias("hops")).first()
            out.append({"method": name, "pool": pool, "ask": ask, "recall": float(r), "search_ndc": float(c["ndc"] or 0), "hops": float(c["hops"] or 0), "n_edges": n, "merge_ndc": int(cost)} | more)
        return out

    def merged(self, k: int | None = None, **how) -> tuple[DataFrame, int, dict]:
        got = fuse.merge(self.edges, self.base, k or self.k, **how)
        return got.edges, sum(got.facts[f"ndc_{s}"] for s in ("lift", "refine", "thin")), got.facts


COLUMNS = "setting string, method string, pool int, ask int, recall double, search_ndc double, hops double, n_edges long, merge_ndc long"


def report(spark: SparkSession, rows: list[dict], setting: str = "") -> DataFrame:
    names = [c.strip().split(" ")[0] for c in COLUMNS.split(",")]
    return spark.createDataFrame([tuple(({"setting": setting} | r)[n] for n in names) for r in rows], COLUMNS)


def merge2_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two halves: the merge against incremental insertion of either kind and batch insertion."""
    inserted = lambda kind: lambda base: baselines.insert_all(base, kind, K // 2, EFFORT)

    def run(kind: str, method: str, other: Callable[[DataFrame], DataFrame] | None, **how) -> list[dict]:
        b = Bench(spark, sf_dir, 2, kind, other=other, **how)
        edges, cost, _ = b.merged()
        rows = b.measured("merge", edges, cost, setting=kind)
        # Batch insertion goes into the graph of a half.
        made = b.other.result() if b.other else stage(baselines.fresh_merge(b.edges, b.base, K), "fresh")
        return rows + b.measured(method, baselines.base_layer(made), baselines.cost(made), setting=kind)

    return report(spark, together([
        lambda: run("hnsw", "insert_all", inserted("hnsw")), lambda: run("nsw", "insert_all", inserted("nsw"), ef=50), lambda: run("vamana", "fresh_merge", None),
    ]))


def search_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall against pool and distances, 10 and 100 results, of a merge and of insertion."""
    b = Bench(spark, sf_dir, 2, "hnsw")
    edges, cost, _ = b.merged()
    inserted = stage(baselines.insert_all(b.base, "hnsw", K // 2, EFFORT), "inserted")
    rows = []
    for ask, pools in ((10, (10, 20, 40, 80, 160, 320)), (100, (100, 160, 320))):
        rows += b.measured("merge", edges, cost, pools, ask)
        rows += b.measured("insert_all", baselines.base_layer(inserted), baselines.cost(inserted), pools, ask)
    return report(spark, rows)


def strategy_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Incremental insertion, neighbour-graph merge, union of graphs, segment merge, the merge, and no merge at all."""
    b = Bench(spark, sf_dir, 2, "hnsw")
    rows = []
    inserted = stage(baselines.insert_all(b.base, "hnsw", K // 2, EFFORT), "inserted")
    rows += b.measured("insert_all", baselines.base_layer(inserted), baselines.cost(inserted))
    near, log = baselines.knng_merge(b.edges, b.base, K)
    rows += b.measured("knng_merge", near, sum(r["pairs"] for r in log))
    rows += b.measured("naive_union", baselines.naive_union(b.edges), 0)
    rows += b.measured("overlap_union", baselines.overlap_build(b.base.select("vec_id", "x"), 4, 2, degree=K), 0)
    segment = stage(baselines.segment_merge(b.base, K // 2, EFFORT, EFFORT // 4), "segment")
    rows += b.measured("segment_merge", baselines.base_layer(segment), baselines.cost(segment))
    edges, cost, _ = b.merged()
    rows += b.measured("merge", edges, cost)
    found = stage(search.scatter_gather(b.edges, b.base, b.asked, search.medoids(b.base), POOL, ASK), "scatter")
    r = quality.recall(found, b.truth, ASK).first()["recall"]
    c = found.where("rank = 1").agg(F.avg("ndc").alias("n"), F.avg("hops").alias("h")).first()
    rows.append({"method": "scatter_gather", "pool": POOL, "ask": ASK, "recall": float(r), "search_ndc": float(c["n"]), "hops": float(c["h"]), "n_edges": b.edges.count(), "merge_ndc": 0})
    return report(spark, rows, "halves")


def multi_merge(h: int):
    """h indexes merged at once, against insertion of all but the largest."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        b = Bench(spark, sf_dir, h, "hnsw", other=lambda base: baselines.insert_all(base, "hnsw", K // 2, EFFORT))
        edges, cost, _ = b.merged()
        rows = b.measured("merge", edges, cost)
        inserted = b.other.result()
        rows += b.measured("insert_all", baselines.base_layer(inserted), baselines.cost(inserted))
        return report(spark, rows, f"h={h}")

    return run


def multi_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Search quality of merges of two to seven indexes."""

    known = aside(lambda: questions(*tables.base_and_queries(spark, sf_dir)))

    def run(h: int) -> list[dict]:
        b = Bench(spark, sf_dir, h, "vamana", known=known)
        edges, cost, _ = b.merged()
        return b.measured("merge", edges, cost, (20, 80), setting=f"h={h}")

    return report(spark, together([lambda h=h: run(h) for h in range(2, 8)]))


#: Methods of the comparison with building anew, and the degrees that each is tried with.
REBUILT = {"vamana": {}, "tau_graph": {"size": 50}, "nn_descent": {}, "nsw": {"ef": 50}}
DEGREES = (8, 12, 16, 24)


def rebuild_curve(kind: str):
    """The merge of halves against building anew, in four settings, searched with a pool of 200."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        def one(k: int) -> list[dict]:
            how = {"degree": k, "m": k // 2, "k": k} | REBUILT[kind]
            b = Bench(spark, sf_dir, 2, kind, k=k, other=lambda base: baselines.rebuild(base, kind, **how), **REBUILT[kind])
            edges, cost, _ = b.merged()
            rows = b.measured("merge", edges, cost, (200,), setting=f"{kind} k={k}")
            again = b.other.result()
            return rows + b.measured("rebuild", baselines.base_layer(again), baselines.cost(again), (200,), setting=f"{kind} k={k}")

        return report(spark, together([lambda k=k: one(k) for k in DEGREES]))

    return run


def method_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Search quality of merges and of rebuilt indexes of four methods over pools."""

    def run(kind: str, more: dict) -> list[dict]:
        b = Bench(spark, sf_dir, 2, kind, other=lambda base: baselines.rebuild(base, kind, **({"degree": K, "m": K // 2, "k": K} | more)), **more)
        edges, cost, _ = b.merged()
        rows = b.measured("merge", edges, cost, (10, 20, 80, 320), setting=kind)
        again = b.other.result()
        return rows + b.measured("rebuild", baselines.base_layer(again), baselines.cost(again), (10, 20, 80, 320), setting=kind)

    return report(spark, together([lambda kind=kind, more=more: run(kind, more) for kind, more in REBUILT.items()]))


def changed_merge(form: str):
    """An index of all vectors merged with one of every r-th, under a map: ``delete`` drops those vectors, ``overlap`` keeps the
    newer copy of each. Recall is over the vectors that are left."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        def one(r: int) -> list[dict]:
            b = Bench(spark, sf_dir, 1, "random")
            v = stage(idmap.full_and_subset(b.base.select("vec_id", "x"), r), "changed")
            built = stage(builders.build(v, "vamana", degree=K), "changed-index").where("layer = 0").select("src", "dst", "dist", F.col("index_id").alias("part"))
            members = v.select(F.col("part").alias("index_id"), F.col("vec_id").alias("local_id"), F.col("vec_id").alias("key"), F.col("part").alias("ts"))
            if form == "delete":
                mapped = idmap.build(members.withColumn("global_id", F.col("local_id")), "explicit", F.col("local_id") % r != 0)
                b.base = stage(b.base.where(F.col("vec_id") % r != 0), "left")
                b.truth = stage(exact.knn(b.base.select("vec_id", "x"), b.asked, 100), "truth")
                b.whole = stage(search.medoids(b.base.select("vec_id", "x")), "entry")
            else:
                mapped = idmap.build(members, "newest")
            # Deleted vertices take places in the pools of the searches; twice the size leaves enough of the others.
            got = fuse.merge(built, v, K, mapped=mapped, pool=2 * lift.pool_size(K, 2))
            cost = sum(c for name, c in got.facts.items() if name.startswith("ndc"))
            return b.measured("merge", got.edges, cost, (POOL, 200), setting=f"{form} 1/{r}")

        return report(spark, together([lambda r=r: one(r) for r in (4, 3, 2)]))

    return run


def composition_built(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the edges of an index of all vectors the shares that indexes of two to five parts had, by builder."""
    base = stage(tables.base_and_queries(spark, sf_dir)[0], "base")
    kinds = {"hnsw": {"m": K // 2, "ef": 50}, "vamana": {"degree": K}}

    def built(kind: str, h: int) -> list[tuple]:
        v = stage(idmap.by_hash(base, h, 3) if h > 1 else base.withColumn("part", F.lit(0)), "parts")
        return [((kind, h), v, stage(baselines.base_layer(builders.build(v, kind, **kinds[kind])), "built"))]

    # The whole indexes first, as each is one task.
    made = {key: (v, edges) for key, v, edges in together([lambda kind=kind, h=h: built(kind, h) for h in (1, 2, 3, 4, 5) for kind in kinds])}
    out = None
    for kind in kinds:
        for h in (2, 3, 4, 5):
            v, sub = made[kind, h]
            row = quality.composition(sub, made[kind, 1][1], v).select(F.lit(kind).alias("method"), F.lit(h).alias("h"), "kept", "new_same", "new_cross")
            out = row if out is None else out.unionByName(row)
    return out


def merge_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the merge of halves saves against building anew, with its recall and its queries a second."""
    b = Bench(spark, sf_dir, 2, "vamana", other=lambda base: baselines.rebuild(base, "vamana", degree=K))
    edges, cost, _ = b.merged()
    again = b.other.result()
    row = b.measured("merge", edges, cost)[0]
    rate = quality.qps(lambda: b.answers(edges), b.asked.count(), 1)
    return quality.objective(spark, baselines.cost(again), cost, rate, row["recall"])


def fresh_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Batch insertion over stored tables in scans, and batches of doubling size searched in parallel, against the merge."""
    b = Bench(spark, sf_dir, 2, "vamana")
    runs = {"merge": lambda: b.merged()[:2], "fresh_scans": lambda: baselines.fresh_scans(b.edges, b.base, K), "parallel_doubling": lambda: baselines.parallel_doubling(b.base, K)}
    return report(spark, together([lambda name=name, run=run: b.measured(name, *run()) for name, run in runs.items()]), "halves")


#: Numbers of tasks that the runs by number of tasks allow at once.
TASKS = (2, 4, 8)


def tasks_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The merge of halves against batches of doubling size searched in parallel, by the number of tasks that a shuffle makes.

    Seconds are of this session and its cores; more tasks than cores change nothing. Distances and recall stay the same.
    """
    b = Bench(spark, sf_dir, 2, "vamana")
    name = "spark.sql.shuffle.partitions"
    before = spark.conf.get(name)
    out = []
    try:
        for n in TASKS:
            spark.conf.set(name, str(n))
            for method, run in (("merge", lambda: b.merged()[:2]), ("parallel_doubling", lambda: baselines.parallel_doubling(b.base, K))):
                began = time.perf_counter()
                edges, cost = run()
                spent = time.perf_counter() - began
                recall = float(quality.recall(b.answers(edges), b.truth, ASK).first()["recall"])
                out.append((n, method, recall, int(cost), spent))
    finally:
        spark.conf.set(name, before)
    return spark.createDataFrame(out, "tasks int, method string, recall double, merge_ndc long, seconds double")


def consolidation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors on nodes by the nation of a customer, an index a node; the nodes of each region are merged to one index."""
    customer, nation, region = (tables.table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    v = tables.vectors(spark, sf_dir).withColumn("owner", F.col("vec_id") % F.lit(customer.count()) + 1)
    placed = v.join(customer, F.col("owner") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    placed = stage(placed.select("vec_id", "x", F.col("n_nationkey").cast("int").alias("part"), "r_name"), "nodes")
    edges = baselines.base_layer(stage(builders.build(placed, "vamana", degree=K), "nodes-index"))
    out = []
    for name in [r[0] for r in placed.select("r_name").distinct().orderBy("r_name").collect()]:  # five regions
        own = stage(placed.where(F.col("r_name") == name).select("vec_id", "x", "part"), "region")
        got = fuse.merge(edges.join(own.select(F.col("vec_id").alias("src")), "src", "left_semi"), own, K)
        truth = exact.knn(own, own.select("vec_id", "x"), ASK)
        found = search.resident(got.edges, own.select("vec_id", "x"), own.select("vec_id", "x"), stage(got.entries, "entry"), POOL, ASK)
        out.append((name, own.select("part").distinct().count(), own.count(), got.edges.count(), float(quality.recall(found, truth, ASK).first()["recall"])))
    return spark.createDataFrame(out, "region string, n_nodes long, n_vectors long, n_edges long, recall double")


def probe_options(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The options of foreign searches: distances, and the same graph. Joins, pruning by triangles, several vertices a round, routing."""
    b = Bench(spark, sf_dir, 3, "vamana")
    options = (("resident", {}), ("joins", {"probe": "frontier"}), ("tri", {"tri": True}), ("width 4", {"width": 4}), ("reach 1", {"reach": 1}), ("cap 24", {"cap": 24}), ("stop 1 %", {"stop_fraction": 0.01}), ("cache", {"storage": "cache"}))

    def run(name: str, how: dict) -> list[dict]:
        edges, cost, _ = b.merged(**how)
        return b.measured("merge", edges, cost, setting=name)

    # How frames are kept holds for the session, so that option runs alone.
    rows = together([lambda name=name, how=how: run(name, how) for name, how in options if "storage" not in how])
    return report(spark, rows + [row for name, how in options if "storage" in how for row in run(name, how)])


def growth(form: str, sizes: tuple[int, ...], kind: str = "hnsw"):
    """The merge of halves against insertion (``hnsw``) or building anew, as the base grows by vectors between others, or by near twins."""
    grow = {"blend": tables.blended, "twins": tables.jittered}[form]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        def one(n: int) -> list[dict]:
            other = (lambda base: baselines.insert_all(base, "hnsw", K // 2, EFFORT)) if kind == "hnsw" else lambda base: baselines.rebuild(base, kind, degree=K)
            b = Bench(spark, sf_dir, 2, kind, larger=lambda base: grow(base, n), other=other)
            edges, cost, _ = b.merged()
            # Pools from small to large, so that distances can be compared at equal recall.
            rows = b.measured("merge", edges, cost, (POOL, 2 * POOL), setting=f"{form} x{n}")
            made = b.other.result()
            return rows + b.measured("insert_all" if kind == "hnsw" else "rebuild", baselines.base_layer(made), baselines.cost(made), (POOL, 2 * POOL), setting=f"{form} x{n}")

        return report(spark, together([lambda n=n: one(n) for n in sizes]))

    return run


def layered_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A merged graph searched from its medoid, and by descent through rebuilt upper layers."""
    b = Bench(spark, sf_dir, 2, "vamana")
    edges, cost, _ = b.merged()
    rows = b.measured("medoid", edges, cost)
    layers = stage(tower.rebuild(b.base.select("vec_id", "x"), K // 2, seed=1), "tower")
    found = stage(tower.layered(edges, layers, b.base, b.asked, b.whole, POOL, ASK), "layered")
    c = found.where("rank = 1").agg(F.avg("ndc").alias("n"), F.avg("hops").alias("h")).first()
    rows.append(rows[0] | {"method": "layered", "recall": float(quality.recall(found, b.truth, ASK).first()["recall"]), "search_ndc": float(c["n"]), "hops": float(c["h"])})
    return report(spark, rows, "halves")


def hub_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degrees by sketches of fixed size instead of exact tables: distinct targets, median and tail of the indegree."""
    v = tables.vectors(spark, sf_dir)
    near = stage(exact.graph(v, K), "near")
    tail = refine.indegrees(near, v).agg(*[F.percentile_approx("indeg", q, 10_000).cast("long").alias(f"p{round(100 * q)}") for q in (0.5, 0.9, 0.99)])
    seen = near.agg(F.approx_count_distinct("dst", 0.02).alias("n_targets"), F.hll_sketch_estimate(F.hll_sketch_agg("dst")).alias("n_targets_hll"))
    return seen.join(F.broadcast(tail), F.lit(True))


def builders_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every builder on all base vectors in one shard."""
    kinds = (("exact", {}), ("nn_descent", {}), ("nsw", {"ef": 50}), ("hnsw", {"ef": 50}), ("vamana", {}), ("nsg", {}), ("tau_graph", {}), ("random", {}))

    def run(kind: str, how: dict) -> list[dict]:
        b = Bench(spark, sf_dir, 1, kind, **how)
        return b.measured(kind, b.edges, baselines.cost(b.index))

    return report(spark, together([lambda kind=kind, how=how: run(kind, how) for kind, how in kinds]), "one shard")


def doubling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Batches of doubling size against one merge of halves."""
    b = Bench(spark, sf_dir, 2, "vamana", other=lambda base: baselines.prefix_doubling(base, K))
    edges, cost, _ = b.merged()
    rows = b.measured("merge", edges, cost)
    batch = b.other.result()
    return report(spark, rows + b.measured("prefix_doubling", baselines.base_layer(batch), baselines.cost(batch)), "halves")


def effort_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A builder's effort against the accuracy of its graph as a neighbour graph."""
    out = None
    for size in (16, 32, 64):
        b = Bench(spark, sf_dir, 1, "vamana", size=size)
        near = quality.graph_recall(b.edges, exact.graph(b.base.select("vec_id", "x"), ASK))
        row = near.select(F.lit("vamana").alias("method"), F.lit(size).alias("effort"), "recall", F.lit(baselines.cost(b.index)).alias("build_ndc"))
        out = row if out is None else out.unionByName(row)
    return out


def pool_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pools of the foreign search from the smallest on."""
    b = Bench(spark, sf_dir, 4, "vamana")
    least = lift.pool_size(K, 4)
    rows = []
    for pool in (least, 2 * least, 4 * least):
        edges, cost, _ = b.merged(pool=pool)
        rows += b.measured("merge", edges, cost, setting=f"pool={pool}")
    return report(spark, rows)


def ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Random foreign candidates or searched ones, with and without flags."""
    b = Bench(spark, sf_dir, 2, "vamana")
    rows = []
    for name, how in fuse.PRESETS.items():
        edges, cost, _ = b.merged(**how)
        rows += b.measured("merge", edges, cost, setting=name)
    return report(spark, rows)


def stage_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stages on and off."""
    b = Bench(spark, sf_dir, 2, "vamana")
    rows = []
    for stages in (("lift",), ("lift", "refine"), ("lift", "thin"), ("lift", "refine", "thin")):
        edges, cost, _ = b.merged(stages=stages)
        rows += b.measured("merge", edges, cost, setting="+".join(stages))
    return report(spark, rows)


def repair_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strong components, orphans and recall with and without repair, small degrees."""
    out = []
    for k in (4, 8):
        b = Bench(spark, sf_dir, 2, "exact", k=k)
        for repair in ("every", "last", "off"):
            edges, _, _ = b.merged(k=k, repair=repair)
            r = quality.recall(b.answers(edges), b.truth, ASK).first()["recall"]
            scc = quality.strong_components(edges, b.base).first()["n_scc"]
            out.append((k, repair, scc, refine.orphans(edges, b.base).count(), float(r)))
    return spark.createDataFrame(out, "k int, repair string, n_scc long, n_orphans long, recall double")


def rule_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Thinning rules and guards on one exact neighbour graph: edges kept, orphans made."""
    v = tables.vectors(spark, sf_dir)
    near = stage(exact.graph(v, K), "near")
    out = []
    for rule, guard, how in (("kept", "static", {}), ("kept", "live", {}), ("kept", "off", {}), ("lune", "off", {}), ("alpha", "static", {"alpha": 1.2}), ("tau", "static", {"tau": 0.02})):
        slim = stage(thin.select(near, v, K, rule, guard, **how), "slim")
        out.append((rule, guard, slim.count(), thin.new_orphans(near, slim, v).count()))
    return spark.createDataFrame(out, "rule string, guard string, n_edges long, new_orphans long")


def heterogeneous(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Halves of different builders, and an uneven split, merged."""
    known = aside(lambda: questions(*tables.base_and_queries(spark, sf_dir)))

    def mixed() -> list[dict]:
        b = Bench(spark, sf_dir, 2, "vamana", known=known, other=lambda base: builders.build(base.where("part = 1"), "hnsw", m=K // 2, ef=50))
        left = b.edges.join(b.base.where("part = 0").select(F.col("vec_id").alias("src")), "src", "left_semi")
        b.edges = stage(left.select("src", "dst", "dist").unionByName(baselines.base_layer(b.other.result())), "both")
        edges, cost, _ = b.merged()
        return b.measured("merge", edges, cost, setting="vamana+hnsw")

    def uneven() -> list[dict]:
        split = lambda base: idmap.skewed(base.select("vec_id", "x"))
        c = Bench(spark, sf_dir, 1, "random", known=known, other=lambda base: builders.build(split(base), "vamana", degree=K))
        c.base = stage(split(c.base), "skewed")
        c.edges = baselines.base_layer(c.other.result())
        edges, cost, _ = c.merged()
        return c.measured("merge", edges, cost, setting="7:1")

    return report(spark, together([mixed, uneven]))


def tower_layers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices and edges of the rebuilt upper layers."""
    layers = tower.rebuild(tables.vectors(spark, sf_dir), K // 2, seed=1)
    return layers.groupBy("layer").agg(F.countDistinct("src").alias("n_vertices"), F.count("*").alias("n_edges"))


def beam_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two forms of search on one graph: rows in which they differ."""
    base, asked = tables.base_and_queries(spark, sf_dir)
    near = stage(exact.graph(base, K), "near")
    entry = stage(search.medoids(base), "entry")
    one = search.resident(near, base, asked, entry, 20, ASK).drop("index_id")
    two = search.frontier(near, base, asked, entry, 20, ASK).drop("index_id").select(*one.columns)
    return one.exceptAll(two).withColumn("mode", F.lit("resident")).unionByName(two.exceptAll(one).withColumn("mode", F.lit("frontier")))


def merge_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four parts merged two at a time."""
    b = Bench(spark, sf_dir, 1, "random")
    got = fuse.tree(b.base.select("vec_id", "x"), K, 4, 2)
    return report(spark, b.measured("merge_tree", got.edges, got.facts["ndc"]), "4 parts, fan-in 2")


def document_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hashed text vectors of documents in two parts: twins at distance zero stay one vertex under the map."""
    docs = tables.table(spark, sf_dir, "documents").select("doc_id", "text")
    v = stage(tables.document_vectors(docs), "docs")
    twins = v.groupBy("x").agg(F.min("vec_id").alias("vec_id"))
    near = exact.graph(twins.select("vec_id", "x"), ASK)
    return near.agg(F.lit(v.count()).alias("n_vectors"), F.countDistinct("src").alias("n_vertices"), F.sum((F.col("dist") == 0).cast("long")).alias("n_twins"), F.round(F.avg("dist"), 6).alias("mean_dist"))


QUERIES = {
    "merge2_cost": merge2_cost, "search_curve": search_curve, "strategy_table": strategy_table,
    **{f"multi_merge_h{h}": multi_merge(h) for h in (3, 5, 7)},
    "multi_recall": multi_recall, **{f"rebuild_{kind}": rebuild_curve(kind) for kind in REBUILT}, "builders_table": builders_table, "prefix_doubling": doubling, "effort_sweep": effort_sweep,
    "pool_sweep": pool_sweep, "ablation": ablation, "stage_ablation": stage_ablation, "repair_ablation": repair_ablation, "rule_table": rule_table,
    "heterogeneous": heterogeneous, "tower_layers": tower_layers, "beam_modes": beam_modes, "merge_tree": merge_tree,
    "method_curve": method_curve, "growth": growth("blend", (1, 2, 4)), "growth_twins": growth("twins", (2,)), "growth_vamana": growth("blend", (1, 2), "vamana"),
    "delete_merge": changed_merge("delete"), "overlap_merge": changed_merge("overlap"), "composition_built": composition_built, "merge_objective": merge_objective,
    "fresh_table": fresh_table, "tasks_curve": tasks_curve, "consolidation": consolidation, "probe_options": probe_options, "layered_search": layered_search, "hub_sketch": hub_sketch, "document_overlap": document_overlap,
}
