"""Queries of the core methods on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import exact, idmap, lift, quality, refine, search, thin, tower
from shardweave.plans import baselines
from shardweave.sources import tables
from shardweave.staging import stage
from shardweave.workloads import sql

K = sql.K
Query = DataFrame


def split(spark: SparkSession, sf_dir: str, h: int) -> DataFrame:
    return idmap.by_modulus(tables.vectors(spark, sf_dir), h)


def rounded(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, 6) for n in names or ("dist",)})


def own_exact(v: DataFrame, k: int) -> DataFrame:
    return exact.graph(v, k, scope="same")


def lifted(spark: SparkSession, sf_dir: str, h: int, k: int = K) -> DataFrame:
    v = split(spark, sf_dir, h)
    return lift.run(own_exact(v, k), lift.cross_exact(v, lift.pool_size(k, h)), k)


def start_arithmetic(v: DataFrame, k: int = K) -> DataFrame:
    """The nearest half of the own list, and foreign ids by a formula that flips parity."""
    n = v.count()
    half = own_exact(v, k // 2).select("src", "dst", "dist")
    far = v.select(F.col("vec_id").alias("src"), "x", F.explode(F.sequence(F.lit(0), F.lit(k - k // 2 - 1))).alias("j"))
    far = far.withColumn("dst", (F.col("src") * 17 + 62 * F.col("j") + 1) % n)
    met = far.join(v.select(F.col("vec_id").alias("dst"), F.col("x").alias("y")), "dst")
    return half.unionByName(distance.measured(met.select("src", "dst", "x", "y"), "x", "y")).withColumn("is_new", F.lit(True))


def refined(spark: SparkSession, sf_dir: str, rounds: int, scope: str = "cross") -> DataFrame:
    v = split(spark, sf_dir, 2)
    now = stage(start_arithmetic(v), "start")
    for _ in range(rounds):
        now = stage(refine.once(now, v, v.select("vec_id", "part"), K, scope), "round")
    return rounded(now.select("src", "dst", "dist", "is_new"))


def refine_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = split(spark, sf_dir, 2)
    truth = stage(exact.graph(v, K), "truth")
    now, out = stage(start_arithmetic(v), "start"), None
    for turn in (1, 2):
        now = stage(refine.once(now, v, v.select("vec_id", "part"), K), "round")
        row = now.agg(F.lit(turn).alias("round"), F.sum(F.col("is_new").cast("long")).alias("accepted")).join(F.broadcast(quality.graph_recall(now, truth)), F.lit(True))
        out = row if out is None else out.unionByName(row)
    return out.select("round", "accepted", F.round("recall", 6).alias("knng_recall"))


def thin_query(rule: str, **how):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = tables.vectors(spark, sf_dir)
        return rounded(thin.select(exact.graph(v, 16), v, 16, rule, **how))

    return run


def knn_query(metric: str, name: str = "dist"):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        base, asked = tables.base_and_queries(spark, sf_dir)
        return rounded(exact.knn(base, asked, 10, metric)).withColumnRenamed("dist", name)

    return run


def mips_topk10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By inner product, through the transform to l2."""
    base, asked = tables.base_and_queries(spark, sf_dir)
    found = exact.knn(distance.mips_to_l2(base), distance.mips_query(asked), 10)
    met = found.join(base.select("vec_id", "x"), "vec_id").join(asked.select(F.col("vec_id").alias("q_id"), F.col("x").alias("y")), "q_id")
    return met.select("q_id", "rank", "vec_id", F.round(distance.expr("ip", F.col("x"), F.col("y")), 6).alias("ip"))


def l2_pairs_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hundred closest pairs: each vector's nearest ones are enough to hold them."""
    near = exact.graph(tables.vectors(spark, sf_dir), 100)
    return rounded(near.where("src < dst").orderBy("dist", "src", "dst").limit(100).select(F.col("src").alias("u"), F.col("dst").alias("v"), "dist"))


def recall_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    base, asked = tables.base_and_queries(spark, sf_dir)
    truth = exact.knn(base, asked, 10)
    part = exact.knn(idmap.by_modulus(base, 2), idmap.by_modulus(asked, 2), 10, scope="same")
    return rounded(quality.recall(part, truth, 10), "recall")


def pool_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pools that foreign searches need, by the number of a vector's k nearest that its own part has; ``n`` vectors each."""
    near = exact.graph(tables.vectors(spark, sf_dir), 32)
    shapes = [(h, k) for h in range(2, 8) for k in (8, 16, 32)]
    own = lambda h, k: F.count_if((F.col("rank") <= k) & (F.pmod("src", F.lit(h)) == F.pmod("dst", F.lit(h)))).cast("int")
    found = near.groupBy("src").agg(*[own(h, k).alias(f"m_{h}_{k}") for h, k in shapes])
    each = F.explode(F.array(*[F.struct(F.lit(h).alias("h"), F.lit(k).alias("k"), F.col(f"m_{h}_{k}").alias("m")) for h, k in shapes])).alias("e")
    groups = found.select(each).groupBy("e.h", "e.k", "e.m").count().collect()  # 354 rows at most
    rows = [(h, k, m, lift.pool_size(k, h), lift.pool_size(k, h, m), n) for h, k, m, n in groups]
    return spark.createDataFrame(rows, "h int, k int, min_deg int, l_worst int, l_tight int, n long")


def idmap_offsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = split(spark, sf_dir, 3)
    members = v.select(F.col("part").alias("index_id"), F.floor(F.col("vec_id") / 3).alias("local_id"), "vec_id")
    return idmap.build(members, "offset", F.col("vec_id") % 10 != 0)


def refine_pools1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return refine.pools(start_arithmetic(split(spark, sf_dir, 2))).select("pivot", "member", "is_new")


def composition(h: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = split(spark, sf_dir, h)
        out = quality.composition(own_exact(v, 16), exact.graph(v, 16), v.select("vec_id", "part"))
        return rounded(out, "kept", "new_same", "new_cross").select(F.lit(h).alias("h"), "kept", "new_same", "new_cross")

    return run


def fused_exact_h2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lift on exact inputs, thin, reciprocate."""
    v = tables.vectors(spark, sf_dir)
    near = stage(lifted(spark, sf_dir, 2), "lifted")
    return rounded(thin.reciprocate(thin.select(near, v, K), K).select("src", "dst", "dist"))


def reciprocate_k16(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = tables.vectors(spark, sf_dir)
    return rounded(thin.reciprocate(thin.select(exact.graph(v, 16), v, 16), 16)).select("src", "dst", "dist", "rank")


def level_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = (F.pmod(F.col("vec_id") * 7919 + 13, F.lit(10007)).cast("double") + 0.5) / 10007.0
    return tables.vectors(spark, sf_dir).groupBy(tower.level(u, K).alias("level")).agg(F.count("*").alias("n"))


def degree_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = tables.vectors(spark, sf_dir)
    return rounded(quality.degrees(exact.graph(v, 4), v), "mean_degree")


def reach_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = tables.vectors(spark, sf_dir)
    g = stage(exact.graph(v, K), "reach-graph")
    return quality.reachable(g, search.medoids(v).select(F.col("ep").alias("id"))).agg(F.count("*").alias("reached"))


def repair_scc(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = tables.vectors(spark, sf_dir)
    return quality.strong_components(exact.graph(v, K), v)


def naive_union_recall(h: int):
    """The parts' graphs side by side, searched from one entry with a pool that holds all it reaches."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        base, asked = tables.base_and_queries(spark, sf_dir)
        parts = idmap.by_modulus(base, h)
        union = stage(baselines.naive_union(own_exact(parts, K)), "union")
        entry = stage(search.lowest(base), "entry")
        found = search.resident(union, base, asked, entry, base.count(), 10)
        return quality.recall(found, exact.knn(base, asked, 10), 10).select(F.lit(h).alias("h"), F.round("recall", 6).alias("recall"))

    return run


def cross_exhaustive(mode: str):
    """Foreign candidates by beams whose pool holds the whole index: the nearest of what an entry reaches."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = stage(split(spark, sf_dir, 2), "vectors")
        own = stage(own_exact(v, K), "own")
        found = lift.cross(own, v, stage(search.lowest(v), "entries"), v.count(), mode=mode, keep=K)
        return rounded(lift.best(found.select("src", "dst", "dist"), K).select("src", "dst", "dist"))

    return run


def changed(r: int, form: str):
    """The exact lift of all vectors and the multiples of r, under a map that drops those or keeps one copy of each."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = idmap.full_and_subset(tables.vectors(spark, sf_dir), r)
        members = v.select(F.col("part").alias("index_id"), F.col("vec_id").alias("local_id"), F.col("vec_id").alias("key"), F.col("part").alias("ts"))
        if form == "delete":
            named = idmap.build(members.withColumn("global_id", F.col("local_id")), "explicit", F.col("local_id") % r != 0)
        else:
            named = idmap.build(members, "newest")
        good = named.where("valid")
        kept = v.join(good, (v["part"] == good["index_id"]) & (v["vec_id"] == good["local_id"])).select(F.col("global_id").alias("vec_id"), "x", "part")
        # Candidates are cut at k after the map, so that invalid vertices take no place.
        mine = exact.graph(kept, K, scope="same").select("src", "dst", "dist")
        other = lift.cross_exact(kept, K)
        return rounded(lift.run(mine, other, K).select("src", "dst", "dist"))

    return run


def cost_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cost model for halves and quarters of the vectors, by their number and dimension."""
    n, dim = tables.vectors(spark, sf_dir).agg(F.count("*"), F.max(F.size("x"))).first()
    out = None
    for h in (2, 4):
        one = quality.predict(spark, [n // h] * h, 16, dim)
        out = one if out is None else out.unionByName(one)
    return rounded(out, "lift_cost", "refine_cost", "tower_cost")


def curve_at_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances a query takes at a recall of 0.97, between the points of a sweep that asks the first of eight parts, the first
    two, and so on, exactly: of the nearest ten those are found whose part is asked."""
    base, asked = tables.base_and_queries(spark, sf_dir)
    base = idmap.by_modulus(base, 8)
    truth = exact.knn(base.select("vec_id", "x"), asked, 10).select("vec_id").join(base.select("vec_id", "part"), "vec_id")
    sizes = base.groupBy("part").agg(F.count("*").alias("n"))
    found = sizes.join(truth.groupBy("part").agg(F.count("*").alias("hits")), "part", "left")  # eight rows
    upto = Window.orderBy("part")
    share = F.sum(F.coalesce("hits", F.lit(0))).over(upto).cast("double") / F.sum("hits").over(Window.partitionBy())
    curve = found.select(share.alias("recall"), F.sum("n").over(upto).cast("double").alias("distances"))
    return rounded(quality.interpolated(curve, 0.97, "recall", "distances"), "recall", "distances")


def medoid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search.medoids(split(spark, sf_dir, 3)).select("index_id", "ep")


def centroid(spark: SparkSession, sf_dir: str) -> DataFrame:
    flat = search.centroids(split(spark, sf_dir, 3)).select("index_id", F.posexplode("centre").alias("pos", "avg"))
    return rounded(flat, "avg")


QUERIES = {
    "l2_pairs_topk": l2_pairs_topk,
    "exact_knn10": knn_query("l2"),
    "cosine_knn10": knn_query("cosine"),
    "mips_topk10": mips_topk10,
    "exact_knng8": lambda s, d: rounded(exact.graph(tables.vectors(s, d), K)),
    "recall_exact": recall_exact,
    "pool_size": pool_size,
    "idmap_offsets": idmap_offsets,
    "lift_own": lambda s, d: rounded(lift.own(own_exact(split(s, d, 2), K))),
    "lift_exact_h2": lambda s, d: rounded(lifted(s, d, 2)),
    "lift_exact_h4": lambda s, d: rounded(lifted(s, d, 4)),
    "refine_pools1": refine_pools1,
    "refine_round1": lambda s, d: refined(s, d, 1),
    "refine_round2": lambda s, d: refined(s, d, 2),
    "refine_all_round1": lambda s, d: refined(s, d, 1, "all"),
    "refine_log": refine_log,
    "indegree_all": lambda s, d: refine.indegrees(exact.graph(tables.vectors(s, d), 4), tables.vectors(s, d)),
    "orphans": lambda s, d: refine.orphans(exact.graph(tables.vectors(s, d), 4), tables.vectors(s, d)),
    "degree_stats": degree_query,
    "thin_kept_k16": thin_query("kept"),
    "thin_lune_k16": thin_query("lune"),
    "thin_alpha_k16": thin_query("alpha", alpha=1.2),
    "thin_tau_k16": thin_query("tau", tau=0.02),
    "reciprocate_k16": reciprocate_k16,
    "fused_exact_h2": fused_exact_h2,
    "level_counts": level_counts,
    **{f"composition_h{h}": composition(h) for h in (2, 3, 4, 5)},
    "graph_recall_init": lambda s, d: rounded(quality.graph_recall(start_arithmetic(split(s, d, 2)), exact.graph(tables.vectors(s, d), K)), "recall"),
    "repair_scc": repair_scc,
    "reach_recursive": reach_query,
    **{f"naive_union_recall_h{h}": naive_union_recall(h) for h in (2, 3, 4)},
    "cross_exhaustive_h2": cross_exhaustive("resident"),
    **{f"delete_{r}": changed(r, "delete") for r in (4, 3, 2)},
    **{f"overlap_{r}": changed(r, "overlap") for r in (4, 3, 2)},
    "cost_model": cost_model,
    "curve_at_recall": curve_at_recall,
    "medoid": medoid,
    "centroid": centroid,
    "index_size": lambda s, d: quality.size(exact.graph(tables.vectors(s, d), K)),
}

_V = "SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings"
_BASE = sql.EXACT_KNN10

ORACLES = {
    "l2_pairs_topk": f"WITH {sql.PAIRS} SELECT src AS u, dst AS v, round(dist, 6) AS dist FROM p WHERE src < dst ORDER BY p.dist, src, dst LIMIT 100",
    "exact_knn10": sql.knn10("list_distance(q.x, b.x)"),
    "cosine_knn10": sql.knn10("1 - list_inner_product(q.x, b.x) / sqrt(list_inner_product(q.x, q.x) * list_inner_product(b.x, b.x))"),
    "mips_topk10": sql.knn10("-list_inner_product(q.x, b.x)", "ip", "-d"),
    "exact_knng8": sql.exact_graph(K) + sql.RANK_OUT.format("g"),
    "recall_exact": f"""WITH v AS ({_V}), d AS (
  SELECT q.vec_id AS q_id, b.vec_id, list_distance(q.x, b.x) AS d FROM v q JOIN v b ON q.vec_id % 11 = 7 AND b.vec_id % 11 <> 7),
t AS (SELECT q_id, vec_id FROM d QUALIFY row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id) <= 10),
f AS (SELECT q_id, vec_id FROM d WHERE q_id % 2 = vec_id % 2 QUALIFY row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id) <= 10)
SELECT 10 AS k, round(avg(r), 6) AS recall FROM (SELECT t.q_id, count(f.vec_id) / 10.0::DOUBLE AS r FROM t LEFT JOIN f USING (q_id, vec_id) GROUP BY t.q_id)""",
    "pool_size": f"""WITH {sql.PAIRS}, g AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS r FROM p QUALIFY r <= 32),
o AS (SELECT h, k, src, count(*) FILTER (src % h = dst % h) AS m FROM g, range(2, 8) AS a(h), (VALUES (8), (16), (32)) AS b(k) WHERE r <= k GROUP BY h, k, src)
SELECT h::INTEGER AS h, k::INTEGER AS k, m::INTEGER AS min_deg, greatest(1, ceil(k / (h - 1.0)))::INTEGER AS l_worst, greatest(1, ceil((k - m) / (h - 1.0)))::INTEGER AS l_tight, count(*)::BIGINT AS n
FROM o GROUP BY h, k, m""",
    "idmap_offsets": """WITH m AS (SELECT (vec_id % 3)::INTEGER AS index_id, vec_id // 3 AS local_id, vec_id % 10 <> 0 AS valid FROM embeddings),
s AS (SELECT index_id, max(local_id) + 1 AS n FROM m GROUP BY index_id),
o AS (SELECT index_id, coalesce(sum(n) OVER (ORDER BY index_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS off FROM s)
SELECT index_id, local_id, valid, (local_id + off)::BIGINT AS global_id FROM m JOIN o USING (index_id)""",
    "lift_own": f"WITH {sql.PAIRS}, g AS ({sql.graph(K, 2)})" + sql.EDGE_OUT.format("g"),
    "lift_exact_h2": sql.lift_result(2),
    "lift_exact_h4": sql.lift_result(4),
    "refine_pools1": f"""WITH {sql.PAIRS}, {sql.START}
SELECT "pivot", member, bool_or(is_new) AS is_new FROM (SELECT src AS "pivot", dst AS member, is_new FROM start UNION ALL SELECT dst, src, is_new FROM start) GROUP BY "pivot", member""",
    "refine_round1": sql.refined(1) + " SELECT src, dst, round(dist, 6) AS dist, is_new FROM r1",
    "refine_round2": sql.refined(2) + " SELECT src, dst, round(dist, 6) AS dist, is_new FROM r2",
    "refine_all_round1": sql.refined(1, "all") + " SELECT src, dst, round(dist, 6) AS dist, is_new FROM r1",
    "refine_log": sql.refined(2) + f""", g AS ({sql.graph(K)})
SELECT round::INTEGER AS round, accepted::BIGINT AS accepted, round(hits / (SELECT count(*) FROM g), 6) AS knng_recall FROM (
  SELECT 1 AS round, (SELECT count(*) FROM r1 WHERE is_new) AS accepted, (SELECT count(*)::DOUBLE FROM g JOIN r1 USING (src, dst)) AS hits
  UNION ALL SELECT 2, (SELECT count(*) FROM r2 WHERE is_new), (SELECT count(*)::DOUBLE FROM g JOIN r2 USING (src, dst)))""",
    "indegree_all": sql.exact_graph(4) + " SELECT v.vec_id AS id, count(g.dst)::BIGINT AS indeg FROM v LEFT JOIN g ON g.dst = v.vec_id GROUP BY v.vec_id",
    "orphans": sql.exact_graph(4) + " SELECT vec_id AS id FROM v WHERE vec_id NOT IN (SELECT dst FROM g)",
    "degree_stats": sql.exact_graph(4) + """, i AS (SELECT v.vec_id, count(g.dst) AS n FROM v LEFT JOIN g ON g.dst = v.vec_id GROUP BY v.vec_id), o AS (SELECT v.vec_id, count(g.src) AS n FROM v LEFT JOIN g ON g.src = v.vec_id GROUP BY v.vec_id)
SELECT (SELECT count(*) FROM g)::BIGINT AS n_edges, (SELECT count(*) FROM i WHERE n = 0)::BIGINT AS n_orphans, (SELECT count(*) FROM o WHERE n = 0)::BIGINT AS n_dead_ends,
  (SELECT max(n) FROM i)::BIGINT AS max_indegree, (SELECT max(n) FROM o)::BIGINT AS max_outdegree, round((SELECT avg(n) FROM o), 6) AS mean_degree""",
    **{f"thin_{r}_k16": sql.recursive(sql.exact_graph(16) + "," + sql.thinned("g", r)) + sql.EDGE_OUT.format("t") for r in ("kept", "lune", "alpha", "tau")},
    "reciprocate_k16": sql.recursive(sql.exact_graph(16) + "," + sql.thinned("g", "kept") + "," + sql.back("t", 16)) + sql.RANK_OUT.format("b"),
    "fused_exact_h2": sql.recursive(sql.lifted(2) + "," + sql.thinned("lifted", "kept") + "," + sql.back("t", K)) + sql.EDGE_OUT.format("b"),
    "level_counts": f"SELECT floor(-ln((((vec_id * 7919 + 13) % 10007) + 0.5::DOUBLE) / 10007.0::DOUBLE) / ln({K}))::INTEGER AS level, count(*)::BIGINT AS n FROM embeddings GROUP BY 1",
    **{f"composition_h{h}": f"SELECT h, round(kept, 6) AS kept, round(new_same, 6) AS new_same, round(new_cross, 6) AS new_cross FROM ({sql.composition(h)})" for h in (2, 3, 4, 5)},
    "graph_recall_init": f"WITH {sql.PAIRS}, {sql.START}, g AS ({sql.graph(K)}) SELECT round((SELECT count(*) FROM g JOIN start USING (src, dst))::DOUBLE / (SELECT count(*) FROM g), 6) AS recall",
    "repair_scc": sql.recursive(sql.exact_graph(K) + sql.SCC),
    "reach_recursive": sql.recursive(sql.exact_graph(K) + sql.REACH) + " SELECT count(*)::BIGINT AS reached FROM reach",
    **{f"naive_union_recall_h{h}": f"""WITH RECURSIVE v AS ({_V}), b AS (SELECT * FROM v WHERE vec_id % 11 <> 7),
g AS (SELECT x.vec_id AS src, y.vec_id AS dst FROM b x JOIN b y ON x.vec_id <> y.vec_id AND x.vec_id % {h} = y.vec_id % {h}
  QUALIFY row_number() OVER (PARTITION BY x.vec_id ORDER BY list_distance(x.x, y.x), y.vec_id) <= {K}),
reach AS (SELECT min(vec_id) AS id FROM b UNION SELECT g.dst FROM reach JOIN g ON g.src = reach.id),
d AS (SELECT q.vec_id AS q_id, b.vec_id, list_distance(q.x, b.x) AS d FROM v q JOIN b ON q.vec_id % 11 = 7),
t AS (SELECT q_id, vec_id FROM d QUALIFY row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id) <= 10),
f AS (SELECT q_id, vec_id FROM d JOIN reach ON id = vec_id QUALIFY row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id) <= 10)
SELECT {h} AS h, round(count(f.vec_id) / count(*)::DOUBLE, 6) AS recall FROM t LEFT JOIN f USING (q_id, vec_id)""" for h in (2, 3, 4)},
    "cross_exhaustive_h2": sql.recursive(f"""WITH {sql.PAIRS}, g AS ({sql.graph(K, 2)}),
reach AS (SELECT min(vec_id) AS id FROM v GROUP BY vec_id % 2 UNION SELECT g.dst FROM reach JOIN g ON g.src = reach.id)
SELECT src, dst, round(dist, 6) AS dist FROM p JOIN reach ON id = dst WHERE src % 2 <> dst % 2 QUALIFY row_number() OVER (PARTITION BY src ORDER BY p.dist, dst) <= {K}"""),
    **{f"delete_{r}": sql.changed(r, "delete") for r in (4, 3, 2)},
    **{f"overlap_{r}": sql.changed(r, "overlap") for r in (4, 3, 2)},
    "cost_model": """WITH c AS (SELECT count(*) AS n FROM embeddings), m AS (SELECT h, (n // h) AS s, (n // h) * h AS n FROM c, (VALUES (2), (4)) AS t(h))
SELECT n::BIGINT AS n, h::INTEGER AS h, 16 AS k, 64 AS dim, round(h * (h - 1) * s * pow(s, 2.0 / 64) * ln(s) * 16 / (h - 1), 6)::DOUBLE AS lift_cost, round(8.0 * n * 256, 6)::DOUBLE AS refine_cost, round(n / 16.0::DOUBLE * ln(n / 16.0::DOUBLE), 6) AS tower_cost FROM m""",
    "curve_at_recall": f"""WITH v AS ({_V}), d AS (SELECT q.vec_id AS q_id, b.vec_id, list_distance(q.x, b.x) AS d FROM v q JOIN v b ON q.vec_id % 11 = 7 AND b.vec_id % 11 <> 7),
t AS (SELECT vec_id FROM d QUALIFY row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id) <= 10),
c AS (SELECT (SELECT count(*) FROM t WHERE vec_id % 8 < p)::DOUBLE / (SELECT count(*) FROM t) AS recall, (SELECT count(*) FROM v WHERE vec_id % 11 <> 7 AND vec_id % 8 < p)::DOUBLE AS distances FROM range(1, 9) AS r(p)),
l AS (SELECT *, lead(recall) OVER (ORDER BY recall) AS x, lead(distances) OVER (ORDER BY recall) AS y FROM c)
SELECT 0.97::DOUBLE AS recall, round(distances + (0.97 - recall) * (y - distances) / (x - recall), 6) AS distances FROM l WHERE recall <= 0.97 AND x > 0.97""",
    "medoid": f"""WITH v AS ({_V}), m AS (SELECT vec_id % 3 AS part, list(a ORDER BY i) AS c FROM (SELECT vec_id % 3 AS vec_id, i, avg(x[i]) AS a FROM v, range(1, 65) AS t(i) GROUP BY 1, 2) GROUP BY 1)
SELECT part::INTEGER AS index_id, arg_min(vec_id, (d, vec_id)) AS ep FROM (SELECT v.vec_id, part, list_distance(x, c) AS d FROM v JOIN m ON v.vec_id % 3 = part) GROUP BY part""",
    "centroid": f"WITH v AS ({_V}) SELECT (vec_id % 3)::INTEGER AS index_id, (i - 1)::INTEGER AS pos, round(avg(x[i]), 6) AS avg FROM v, range(1, 65) AS t(i) GROUP BY 1, 2",
    "index_size": f"SELECT (count(*) * {K})::BIGINT AS n_edges, (count(*) * {K} * 12)::BIGINT AS n_bytes FROM embeddings",
}
