"""The operators around the methods, on the given tables, each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import exact, idmap
from shardweave.sources import store, tables
from shardweave.staging import fresh_path, stage
from shardweave.streaming import segments
from shardweave.workloads import sql

K = 4
_LOG = "SELECT event_id, ts, event_id % 500 AS vec_id, CASE WHEN event_type = 'error' THEN 'delete' ELSE 'upsert' END AS op, user_id, event_type, value, props FROM events"


def near(spark: SparkSession, sf_dir: str, k: int = K) -> DataFrame:
    return exact.graph(tables.vectors(spark, sf_dir), k)


def log(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.write_log(spark, sf_dir, 500)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "events")


def scan_vectors(s: SparkSession, d: str) -> DataFrame:
    """Filter and columns reach the scan."""
    e = tables.table(s, d, "embeddings")
    return e.where(F.col("label") == 3).select("vec_id", "label")


def scan_json_props(s: SparkSession, d: str) -> DataFrame:
    """Properties written as JSON lines and read back with a schema."""
    path = fresh_path(s, "json")
    events(s, d).select("event_id", "user_id", "event_type").write.json(path)
    return s.read.schema("event_id long, user_id long, event_type string").json(path).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("user_id").alias("users"))


def roundtrip(kind: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        path = fresh_path(s, kind)
        edges = near(s, d).select("src", "dst", F.round("dist", 6).alias("dist"))
        if kind == "index":
            store.save(edges, path, {"metric": "l2", "k": K})
            return store.load(s, path, "l2")[0].select("src", "dst", "dist")
        getattr(edges.write.option("header", True) if kind == "csv" else edges.write, kind)(path)
        reader = s.read.schema("src long, dst long, dist double")
        return getattr(reader.option("header", True) if kind == "csv" else reader, kind)(path)

    return run


def pack_unpack(s: SparkSession, d: str) -> DataFrame:
    return store.unpack(store.pack(near(s, d))).select("src", "dst", F.round("dist", 6).alias("dist"), F.col("rank").cast("int").alias("rank"))


def filter_valid(s: SparkSession, d: str) -> DataFrame:
    good, bad = tables.checked(tables.vectors(s, d).withColumn("x", F.when(F.col("vec_id") % 50 == 0, F.lit(None)).otherwise(F.col("x"))))
    return good.agg(F.count("*").alias("n_good")).join(F.broadcast(bad.groupBy("reason").agg(F.count("*").alias("n_bad"))), F.lit(True))


def filtered_knn(s: SparkSession, d: str) -> DataFrame:
    """Neighbours among vectors that a predicate keeps."""
    e = tables.table(s, d, "embeddings").select("vec_id", F.col("embedding").alias("x"), "label")
    found = exact.knn(e.where("label in (1, 2)").select("vec_id", "x"), e.where("vec_id % 50 = 7").select("vec_id", "x"), 5)
    return found.withColumn("dist", F.round("dist", 6))


def edge_vectors(s: SparkSession, d: str) -> DataFrame:
    v = tables.table(s, d, "embeddings").select("vec_id", "label")
    e = near(s, d)
    met = e.join(v, F.col("src") == F.col("vec_id")).select("src", "dst", F.col("label").alias("a")).join(v.select(F.col("vec_id").alias("w"), F.col("label").alias("b")), F.col("dst") == F.col("w"))
    return met.groupBy("a", "b").agg(F.count("*").alias("n"))


def new_pairs(s: SparkSession, d: str) -> DataFrame:
    e = near(s, d).select("src", "dst")
    return e.join(e.select(F.col("dst").alias("a"), F.col("src").alias("b")), (F.col("src") == F.col("a")) & (F.col("dst") == F.col("b")), "left_anti")


def route_pairs(s: SparkSession, d: str) -> DataFrame:
    v = idmap.by_modulus(tables.vectors(s, d), 3)
    parts = s.range(3).select(F.col("id").cast("int").alias("target"))  # one row an index
    return v.join(F.broadcast(parts), F.col("part") != F.col("target")).groupBy("part", "target").agg(F.count("*").alias("n"))


def range_search(s: SparkSession, d: str) -> DataFrame:
    base, asked = tables.base_and_queries(s, d)
    return exact.within(base, asked, 1.2).withColumn("dist", F.round("dist", 6))


def asof_valid(s: SparkSession, d: str) -> DataFrame:
    """The last change of every vector before a moment decides whether it is valid."""
    moment = log(s, d).agg(F.max(F.when(F.col("event_id") % 1000 == 500, F.col("ts"))).alias("moment"))
    before = log(s, d).join(F.broadcast(moment), F.col("ts") <= F.col("moment"))
    last = before.groupBy("vec_id").agg(F.max_by("op", F.struct("ts", "event_id")).alias("op"))
    return last.select("vec_id", (F.col("op") == "upsert").alias("valid"))


def segment_join(s: SparkSession, d: str) -> DataFrame:
    """Changes to the segments whose interval holds them."""
    days = log(s, d).select(F.date_trunc("day", "ts").alias("from")).distinct().withColumn("to", F.col("from") + F.expr("interval 1 day"))
    met = log(s, d).join(F.broadcast(days), (F.col("ts") >= F.col("from")) & (F.col("ts") < F.col("to")))
    return met.groupBy(F.date_format("from", "yyyy-MM-dd").alias("day"), "op").agg(F.count("*").alias("n"))


def local_join_pairs(s: SparkSession, d: str) -> DataFrame:
    e = near(s, d).select("src", "dst")
    met = e.join(e.select(F.col("src").alias("p"), F.col("dst").alias("b")), F.col("src") == F.col("p")).where("dst < b")
    return met.select(F.col("dst").alias("a"), "b").distinct()


def metrics(form: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        v = idmap.by_modulus(tables.table(s, d, "embeddings").withColumn("b", F.col("label") % 2), 2)
        if form == "gsets":
            v.createOrReplaceTempView("_parts")
            return s.sql("SELECT part, b, count(*) AS n FROM _parts GROUP BY GROUPING SETS ((part, b), (part), ())")
        return getattr(v, form)("part", "b").agg(F.count("*").alias("n"))

    return run


def curve_pivot(s: SparkSession, d: str) -> DataFrame:
    e = events(s, d).withColumn("half", F.col("user_id") % 2)
    return e.groupBy("event_type").pivot("half", [0, 1]).agg(F.count("event_id")).select("event_type", F.col("0").alias("even"), F.col("1").alias("odd"))


def unpivoted(s: SparkSession, d: str) -> DataFrame:
    return curve_pivot(s, d).unpivot(["event_type"], ["even", "odd"], "half", "n")


def topk_edges(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("dst").orderBy("dist", "src")
    return near(s, d, 8).withColumn("r", F.row_number().over(order)).where("r <= 3").select("dst", "src", F.col("r").cast("int").alias("r"))


def rank_family(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("event_type").orderBy("user_id")
    w = events(s, d).select(
        "event_id", F.rank().over(order).alias("rank"), F.dense_rank().over(order).alias("dense"), F.round(F.percent_rank().over(order), 6).alias("pct"), F.round(F.cume_dist().over(order), 6).alias("cume"),
        F.ntile(4).over(Window.partitionBy("event_type").orderBy("user_id", "event_id")).alias("tile"),
    )
    return w


def curve_lead(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(s, d).select(
        "event_id", F.lag("event_id").over(order).alias("before"), F.lead("event_id").over(order).alias("after"), F.first("event_id").over(order).alias("first"), F.nth_value("event_id", 2).over(order).alias("second"),
    )


def running_writes(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("vec_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return log(s, d).select("event_id", F.count("*").over(order).alias("n"), F.sum((F.col("op") == "delete").cast("long")).over(order).alias("n_deletes"))


def global_topk(s: SparkSession, d: str) -> DataFrame:
    return events(s, d).orderBy(F.desc("value"), "event_id").select("event_id", F.round("value", 6).alias("value")).offset(5).limit(20)


def edges_set(form: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        a = near(s, d).select("src", "dst")
        b = a.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        return {"union": a.unionByName(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}[form]

    return run


def recursive_reach(s: SparkSession, d: str) -> DataFrame:
    """Vertices within three steps of vertex 0, as a recursive query."""
    stage(near(s, d), "reach").createOrReplaceTempView("_edges")
    return s.sql("""WITH RECURSIVE r(id, step) AS (SELECT 0L, 0 UNION ALL SELECT e.dst, r.step + 1 FROM r JOIN _edges e ON e.src = r.id WHERE r.step < 3)
        SELECT id, min(step) AS step FROM r GROUP BY id""")


def doc_tokens(s: SparkSession, d: str) -> DataFrame:
    docs = tables.table(s, d, "documents")
    words = docs.select(F.explode(F.split(F.lower(F.regexp_replace("text", r"[^\p{L}]+", " ")), " +")).alias("w")).where("w <> ''")
    return words.groupBy("w").agg(F.count("*").alias("n"))


def page_host(s: SparkSession, d: str) -> DataFrame:
    return tables.table(s, d, "pages").groupBy(F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count("*").alias("n"), F.sum(F.length("html")).alias("chars"))


def writes_by_day(s: SparkSession, d: str) -> DataFrame:
    return log(s, d).groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"), F.date_format(F.min("ts"), "HH:mm:ss").alias("first"))


def array_suite(s: SparkSession, d: str) -> DataFrame:
    a = near(s, d).groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("n"))
    return a.select("src", F.size(F.filter("n", lambda x: x % 2 == 0)).alias("even"), F.element_at("n", 1).alias("least"), F.aggregate("n", F.lit(0).cast("long"), lambda t, x: t + x).alias("total"), F.exists("n", lambda x: x > 400).alias("high"))


def norms(s: SparkSession, d: str) -> DataFrame:
    x = F.col("x")
    return tables.vectors(s, d).select("vec_id", F.round(F.sqrt(distance.expr("ip", x, x)), 6).alias("norm"))


def map_suite(s: SparkSession, d: str) -> DataFrame:
    m = F.map_from_arrays(F.array(F.lit("src"), F.lit("dst")), F.array("src", "dst"))
    doubled = F.transform_values(F.map_filter(m, lambda k, v: v % 2 == 0), lambda k, v: v * 2)
    return near(s, d).select("src", "dst", F.size(doubled).alias("n"), F.coalesce(F.try_element_at(doubled, F.lit("src")), F.lit(-1)).cast("long").alias("s"))


def props_json(s: SparkSession, d: str) -> DataFrame:
    e = events(s, d)
    return e.select("event_id", (F.get_json_object("props", "$") .isNotNull()).alias("valid"), F.size(F.json_object_keys("props")).alias("n_keys"))


def sql_l2(s: SparkSession, d: str) -> DataFrame:
    """The ends of all edges of the exact graph, measured by SQL functions."""
    distance.register(s)
    tables.vectors(s, d).select("vec_id", F.col("x").cast("array<double>").alias("x")).createOrReplaceTempView("_vectors")
    near(s, d).createOrReplaceTempView("_edges")
    return s.sql("""SELECT src AS u, dst AS v, round(l2(a.x, b.x), 6) AS l2, round(cosine_dist(a.x, b.x), 6) AS cosine, round(norm2(a.x), 6) AS norm
        FROM _edges JOIN _vectors a ON a.vec_id = src JOIN _vectors b ON b.vec_id = dst""")


def udtf_neighbors(s: SparkSession, d: str) -> DataFrame:
    """The neighbours of all vertices through a table function over packed lists."""

    @F.udtf(returnType="src: bigint, dst: bigint, rank: int")
    class Neighbours:
        def eval(self, src: int, nbrs: list):
            for i, dst in enumerate(nbrs):
                yield src, dst, i + 1

    s.udtf.register("graph_neighbors", Neighbours)
    store.pack(near(s, d)).select("src", F.transform("nbrs", lambda n: n.dst).alias("to")).createOrReplaceTempView("_packed")
    return s.sql("SELECT n.src, n.dst, n.rank FROM _packed p, LATERAL graph_neighbors(p.src, p.to) n")


def shards_by_region(s: SparkSession, d: str) -> DataFrame:
    """Customers' shards by nation, brought together by region: sizes before and after."""
    c, n, r = (tables.table(s, d, t) for t in ("customer", "nation", "region"))
    met = c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return met.groupBy("r_name").agg(F.countDistinct("n_nationkey").alias("n_shards"), F.count("*").alias("n_vectors"))


def part_neighbors(s: SparkSession, d: str) -> DataFrame:
    """Exact neighbours over numeric columns of ``part``; ties and twins go by id."""
    return exact.twin_knn(tables.part_vectors(s, d), 5).withColumn("dist", F.round("dist", 6))


def order_shards(s: SparkSession, d: str) -> DataFrame:
    """Line items of open orders by the supplier's nation: a star join with pushed filters."""
    l, o, sup, n = (tables.table(s, d, t) for t in ("lineitem", "orders", "supplier", "nation"))
    met = l.join(o.where("o_orderstatus = 'O'"), F.col("l_orderkey") == F.col("o_orderkey")).join(sup, F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey"))
    return met.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


QUERIES = {
    "scan_vectors": scan_vectors, "scan_json_props": scan_json_props, "roundtrip_index": roundtrip("index"), "roundtrip_csv": roundtrip("csv"), "roundtrip_orc": roundtrip("orc"),
    "pack_unpack": pack_unpack, "filter_valid": filter_valid, "filtered_knn": filtered_knn, "edge_vectors": edge_vectors, "new_pairs": new_pairs, "route_pairs": route_pairs,
    "range_search": range_search, "asof_valid": asof_valid, "segment_join": segment_join, "local_join_pairs": local_join_pairs,
    "distinct_pairs": lambda s, d: near(s, d).select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct(),
    "metrics_rollup": metrics("rollup"), "metrics_cube": metrics("cube"), "metrics_gsets": metrics("gsets"), "curve_pivot": curve_pivot, "curve_unpivot": unpivoted,
    "topk_edges": topk_edges, "rank_family": rank_family, "curve_lead": curve_lead, "running_writes": running_writes, "global_topk": global_topk,
    "edge_union": edges_set("union"), "edge_intersect": edges_set("intersect"), "edge_except": edges_set("except"), "recursive_reach": recursive_reach,
    "split_mod": lambda s, d: idmap.by_modulus(tables.vectors(s, d), 5).groupBy("part").agg(F.count("*").alias("n")),
    "doc_tokens": doc_tokens, "page_host": page_host, "writes_by_day": writes_by_day, "array_suite": array_suite, "norms": norms, "map_suite": map_suite, "props_json": props_json,
    "sql_l2": sql_l2, "udtf_neighbors": udtf_neighbors, "consolidate_region": shards_by_region, "part_neighbors": part_neighbors, "order_shards": order_shards,
    "segments_by_window": lambda s, d: segments.by_window(log(s, d)), "win_tumbling": lambda s, d: segments.by_window(log(s, d), "1 day").select("window_start", "n"), "win_sliding": lambda s, d: segments.by_sliding(log(s, d)), "win_session": lambda s, d: segments.sessions(events(s, d)),
}

_NEAR = sql.exact_graph(K)

ORACLES = {
    "scan_vectors": "SELECT vec_id, label FROM embeddings WHERE label = 3",
    "scan_json_props": "SELECT event_type, count(*)::BIGINT AS n, sum(user_id)::BIGINT AS users FROM events GROUP BY event_type",
    **{f"roundtrip_{k}": _NEAR + sql.EDGE_OUT.format("g") for k in ("index", "csv", "orc")},
    "pack_unpack": _NEAR + sql.RANK_OUT.format("g"),
    "filter_valid": "SELECT (SELECT count(*) FROM embeddings WHERE vec_id % 50 <> 0)::BIGINT AS n_good, 'null' AS reason, (SELECT count(*) FROM embeddings WHERE vec_id % 50 = 0)::BIGINT AS n_bad",
    "filtered_knn": """WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x, label FROM embeddings), d AS (SELECT q.vec_id AS q_id, b.vec_id, list_distance(q.x, b.x) AS d FROM v q JOIN v b ON q.vec_id % 50 = 7 AND b.label IN (1, 2)),
r AS (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id)::INTEGER AS rank FROM d) SELECT q_id, rank, vec_id, round(d, 6) AS dist FROM r WHERE rank <= 5""",
    "edge_vectors": _NEAR + " SELECT a.label AS a, b.label AS b, count(*)::BIGINT AS n FROM g JOIN embeddings a ON a.vec_id = src JOIN embeddings b ON b.vec_id = dst GROUP BY 1, 2",
    "new_pairs": _NEAR + " SELECT src, dst FROM g WHERE NOT EXISTS (SELECT 1 FROM g h WHERE h.src = g.dst AND h.dst = g.src)",
    "route_pairs": "SELECT (vec_id % 3)::INTEGER AS part, t::INTEGER AS target, count(*)::BIGINT AS n FROM embeddings, range(3) AS r(t) WHERE vec_id % 3 <> t GROUP BY 1, 2",
    "range_search": "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings) SELECT q.vec_id AS q_id, b.vec_id, round(list_distance(q.x, b.x), 6) AS dist FROM v q JOIN v b ON q.vec_id % 11 = 7 AND b.vec_id % 11 <> 7 WHERE list_distance(q.x, b.x) <= 1.2",
    "asof_valid": f"WITH l AS ({_LOG}), m AS (SELECT max(ts) AS moment FROM l WHERE event_id % 1000 = 500) SELECT vec_id, arg_max(op, (ts, event_id)) = 'upsert' AS valid FROM l, m WHERE ts <= moment GROUP BY vec_id",
    "segment_join": f"WITH l AS ({_LOG}) SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, op, count(*)::BIGINT AS n FROM l GROUP BY 1, 2",
    "local_join_pairs": _NEAR + " SELECT DISTINCT a.dst AS a, b.dst AS b FROM g a JOIN g b ON a.src = b.src AND a.dst < b.dst",
    "distinct_pairs": _NEAR + " SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM g",
    **{f"metrics_{n}": f"SELECT part, b, count(*)::BIGINT AS n FROM (SELECT (vec_id % 2)::INTEGER AS part, label % 2 AS b FROM embeddings) GROUP BY {g}" for n, g in (("rollup", "ROLLUP (part, b)"), ("cube", "CUBE (part, b)"), ("gsets", "GROUPING SETS ((part, b), (part), ())"))},
    "curve_pivot": "SELECT event_type, count(*) FILTER (user_id % 2 = 0)::BIGINT AS even, count(*) FILTER (user_id % 2 = 1)::BIGINT AS odd FROM events GROUP BY 1",
    "curve_unpivot": "SELECT event_type, CASE user_id % 2 WHEN 0 THEN 'even' ELSE 'odd' END AS half, count(*)::BIGINT AS n FROM events GROUP BY 1, 2",
    "topk_edges": sql.exact_graph(8) + " SELECT dst, src, row_number() OVER (PARTITION BY dst ORDER BY dist, src)::INTEGER AS r FROM g QUALIFY r <= 3",
    "rank_family": """SELECT event_id, rank() OVER w::INTEGER AS rank, dense_rank() OVER w::INTEGER AS dense, round(percent_rank() OVER w, 6) AS pct, round(cume_dist() OVER w, 6) AS cume,
  ntile(4) OVER (PARTITION BY event_type ORDER BY user_id, event_id)::INTEGER AS tile FROM events WINDOW w AS (PARTITION BY event_type ORDER BY user_id)""",
    "curve_lead": """SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
    "running_writes": f"WITH l AS ({_LOG}) SELECT event_id, count(*) OVER w AS n, sum((op = 'delete')::BIGINT) OVER w::BIGINT AS n_deletes FROM l WINDOW w AS (PARTITION BY vec_id ORDER BY event_id ROWS UNBOUNDED PRECEDING)",
    "global_topk": "SELECT event_id, round(value, 6) AS value FROM events ORDER BY events.value DESC, event_id LIMIT 20 OFFSET 5",
    "edge_union": _NEAR + " SELECT src, dst FROM g UNION SELECT dst, src FROM g",
    "edge_intersect": _NEAR + " SELECT src, dst FROM g INTERSECT SELECT dst, src FROM g",
    "edge_except": _NEAR + " SELECT src, dst FROM g EXCEPT ALL SELECT dst, src FROM g",
    "recursive_reach": sql.recursive(_NEAR + ", r AS (SELECT 0::BIGINT AS id, 0 AS step UNION SELECT g.dst, r.step + 1 FROM r JOIN g ON g.src = r.id WHERE r.step < 3) SELECT id, min(step) AS step FROM r GROUP BY id"),
    "split_mod": "SELECT (vec_id % 5)::INTEGER AS part, count(*)::BIGINT AS n FROM embeddings GROUP BY 1",
    "doc_tokens": "SELECT w, count(*)::BIGINT AS n FROM (SELECT unnest(regexp_split_to_array(lower(regexp_replace(text, '[^\\p{L}]+', ' ', 'g')), ' +')) AS w FROM documents) WHERE w <> '' GROUP BY w",
    "page_host": "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*)::BIGINT AS n, sum(length(html))::BIGINT AS chars FROM pages GROUP BY 1",
    "writes_by_day": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*)::BIGINT AS n, strftime(min(ts), '%H:%M:%S') AS first FROM events GROUP BY 1",
    "array_suite": _NEAR + " SELECT src, count(*) FILTER (dst % 2 = 0)::INTEGER AS even, min(dst) AS least, sum(dst)::BIGINT AS total, max(dst) > 400 AS high FROM g GROUP BY src",
    "norms": "SELECT vec_id, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings",
    "map_suite": _NEAR + " SELECT src, dst, ((src % 2 = 0)::INT + (dst % 2 = 0)::INT)::INTEGER AS n, CASE WHEN src % 2 = 0 THEN src * 2 ELSE -1 END::BIGINT AS s FROM g",
    "props_json": "SELECT event_id, json_valid(props) AS valid, len(json_keys(props))::INTEGER AS n_keys FROM events",
    "sql_l2": _NEAR + """ SELECT src AS u, dst AS v, round(list_distance(a.x, b.x), 6) AS l2, round(1 - list_inner_product(a.x, b.x) / sqrt(list_inner_product(a.x, a.x) * list_inner_product(b.x, b.x)), 6) AS cosine,
  round(sqrt(list_inner_product(a.x, a.x)), 6) AS norm FROM g JOIN v a ON a.vec_id = src JOIN v b ON b.vec_id = dst""",
    "udtf_neighbors": _NEAR + " SELECT src, dst, rank::INTEGER AS rank FROM g",
    "consolidate_region": "SELECT r_name, count(DISTINCT n_nationkey)::BIGINT AS n_shards, count(*)::BIGINT AS n_vectors FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    "part_neighbors": """WITH v AS (SELECT p_partkey AS vec_id, [p_size::DOUBLE, floor(p_retailprice / 100)::DOUBLE, (p_partkey % 97)::DOUBLE, length(p_name)::DOUBLE] AS x FROM part),
d AS (SELECT q.vec_id AS q_id, b.vec_id, list_distance(q.x, b.x) AS d FROM v q JOIN v b ON q.vec_id <> b.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id)::INTEGER AS rank FROM d) SELECT q_id, rank, vec_id, round(d, 6) AS dist FROM r WHERE rank <= 5""",
    "order_shards": "SELECT n_name, count(*)::BIGINT AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND o_orderstatus = 'O' JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1",
    "segments_by_window": f"WITH l AS ({_LOG}) SELECT strftime(time_bucket(INTERVAL 1 hour, ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d %H:%M:%S') AS window_start, count(*)::BIGINT AS n, count(DISTINCT vec_id)::BIGINT AS n_vectors FROM l GROUP BY 1",
    "win_tumbling": f"WITH l AS ({_LOG}) SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS window_start, count(*)::BIGINT AS n FROM l GROUP BY 1",
    "win_sliding": f"""WITH l AS ({_LOG}) SELECT strftime(time_bucket(INTERVAL 30 minute, ts, TIMESTAMP '1970-01-01') - o * INTERVAL 30 minute, '%Y-%m-%d %H:%M:%S') AS window_start, count(*)::BIGINT AS n
FROM l, range(2) AS t(o) GROUP BY 1""",
    "win_session": """WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 30 minute AND ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 minute THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS nth FROM m)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS session_start, count(*)::BIGINT AS n FROM s GROUP BY user_id, nth""",
}
