"""The hand-computed fixtures, invariants, and bad inputs of the core."""

import threading
import tracemalloc

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from shardweave import api
from shardweave.functions import distance
from shardweave.operators import exact, idmap, lift, quality, refine, search, thin, tower
from shardweave.plans import baselines, builders, fuse
from shardweave.sources import store, tables
from shardweave.staging import stage
from shardweave.workloads import core, experiments, relational

SF = "/root/testdata/sf0.001"


def line(spark, places):
    """One-dimensional vectors ``(vec_id, x, part)``."""
    return spark.createDataFrame([(i, [float(x)], p) for i, x, p in places], "vec_id long, x array<float>, part int")


@pytest.fixture(scope="module")
def two(spark):
    return line(spark, [(i, 5 * i, 0) for i in range(4)] + [(4 + i, 2 + 5 * i, 1) for i in range(4)])


def pairs(df, *names):
    return sorted(tuple(r[n] for n in (names or ("src", "dst"))) for r in df.collect())


LIFTED = {0: [4, 1], 1: [5, 4], 2: [6, 5], 3: [7, 6], 4: [0, 1], 5: [1, 2], 6: [2, 3], 7: [3, 6]}
THIN = {0: [4], 1: [5, 4], 2: [6, 5], 3: [7, 6], 4: [0, 1], 5: [1, 2], 6: [2, 3], 7: [3]}


def test_lift_thin_reciprocate_search(spark, two):
    own = exact.graph(two, 2, scope="same")
    near = stage(lift.run(own, lift.cross_exact(two, lift.pool_size(2, 2)), 2))
    assert pairs(near) == sorted((s, d) for s, ds in LIFTED.items() for d in ds)
    degree = dict(pairs(refine.indegrees(near, two), "id", "indeg"))
    assert degree == {0: 1, 1: 3, 2: 2, 3: 2, 4: 2, 5: 2, 6: 3, 7: 1}
    slim = stage(thin.select(near, two, 2))
    assert pairs(slim) == sorted((s, d) for s, ds in THIN.items() for d in ds)
    assert pairs(thin.reciprocate(slim, 2)) == pairs(slim)
    assert quality.strong_components(slim, two).first()[0] == 1
    asked = spark.createDataFrame([(99, [16.0])], "vec_id long, x array<float>")
    entry = spark.createDataFrame([(0, 0)], "index_id int, ep long")
    whole = two.select("vec_id", "x")
    for form in (search.resident, search.frontier):
        r = form(slim, whole, asked, entry, 2, 1).first()
        assert (r["vec_id"], r["dist"], r["ndc"], r["hops"]) == (3, 1.0, 8, 8)
    alone = search.resident(baselines.naive_union(own), whole, asked, entry, 2, 1).first()
    assert alone["vec_id"] == 3 and pairs(quality.reachable(own, spark.createDataFrame([(0,)], "id long")), "id") == [(0,), (1,), (2,), (3,)]


def test_cross_search_equals_exact_on_small_shards(spark, two):
    own = stage(exact.graph(two, 2, scope="same"))
    found = lift.cross(own, two, search.medoids(two), 4)
    assert pairs(found) == pairs(lift.cross_exact(two, 4))


@pytest.mark.parametrize("mode", ["exact", "rounds"])
def test_repair(spark, mode):
    v = line(spark, [(0, 0, 0), (1, 2, 0), (2, 5, 0), (3, 20, 0)])
    near = stage(exact.graph(v, 2).select("src", "dst", "dist"))
    assert pairs(refine.orphans(near, v), "id") == [(3,)]
    fixed = stage(refine.repaired(near, v, mode))
    assert pairs(fixed) == [(0, 1), (0, 2), (1, 0), (1, 2), (2, 1), (2, 3), (3, 1), (3, 2)]
    assert pairs(thin.select(fixed, v, 2)) == [(0, 1), (1, 0), (1, 2), (2, 1), (2, 3), (3, 2)]


def test_two_orphans_share_no_victim():
    # Orphans 8 and 9 both reach list 1, whose only victim, 5, has two in-edges.
    src, dst = np.array([8, 9, 1, 1]), np.array([1, 1, 5, 6])
    moves = refine.mend(src, dst, np.array([1.0, 1.0, 2.0, 1.0]), np.array([8, 9]), {1: 2, 5: 2, 6: 1})
    assert moves == [(1, 5, 8, 1.0)]


@pytest.mark.parametrize("mode", ["exact", "rounds"])
def test_repair_keeps_out_degrees(spark, mode):
    v = tables.vectors(spark, SF)
    near = stage(exact.graph(v, 3).select("src", "dst", "dist"))
    fixed = stage(refine.repaired(near, v, mode))
    count = lambda e: sorted(r["count"] for r in e.groupBy("src").count().collect())
    assert count(near) == count(fixed) and fixed.distinct().count() == fixed.count()
    assert refine.orphans(fixed, v).count() < refine.orphans(near, v).count()


def test_refine_fixture(spark):
    v = line(spark, [(0, 0, 0), (1, 10, 0), (2, 1, 1), (3, 11, 1)])
    start = spark.createDataFrame([(0, 1, 10.0), (0, 3, 11.0), (1, 2, 9.0), (1, 0, 10.0), (2, 1, 9.0), (2, 3, 10.0), (3, 2, 10.0), (3, 0, 11.0)], "src long, dst long, dist double").withColumn("is_new", F.lit(True))
    origin = v.select("vec_id", "part")
    one = stage(refine.once(start, v, origin, 2))
    assert pairs(one) == [(0, 1), (0, 2), (1, 2), (1, 3), (2, 0), (2, 1), (3, 1), (3, 2)]
    assert one.where("is_new").count() == 4
    two = stage(refine.once(one, v, origin, 2))
    assert pairs(two) == pairs(one) and two.where("is_new").count() == 0


def test_offers_join_different_origins_and_distances_fall(spark):
    v = stage(idmap.by_modulus(tables.vectors(spark, SF), 2))
    near = stage(lift.run(exact.graph(v, 8, scope="same"), lift.random_cross(v, 4), 8).select("src", "dst", "dist").withColumn("is_new", F.lit(True)))
    found = refine.pairs(near, v.select("vec_id", "part"))
    assert found.where("a % 2 = b % 2").count() == 0
    after = stage(refine.once(near, v, v.select("vec_id", "part"), 8))
    total = lambda e: {r["src"]: r["t"] for r in e.groupBy("src").agg(F.sum("dist").alias("t")).collect()}
    a, b = total(near), total(after)
    assert all(b[s] <= a[s] + 1e-9 for s in a)


def test_merge_identity_on_exact_inputs(spark):
    v = stage(idmap.by_modulus(tables.vectors(spark, SF), 2))
    got = lift.run(exact.graph(v, 8, scope="same"), lift.cross_exact(v, 8), 8)
    assert pairs(got) == pairs(exact.graph(v.select("vec_id", "x"), 8))


def test_thinning_rules(spark):
    v = tables.vectors(spark, SF)
    near = stage(exact.graph(v, 12))
    kept = set(pairs(thin.select(near, v, 12)))
    assert kept == set(pairs(thin.select(near, v, 12, "alpha", alpha=1.0))) == set(pairs(thin.select(near, v, 12, "tau", tau=0.0)))
    assert kept <= set(pairs(near)) and {(r["src"], r["dst"]) for r in near.where("rank = 1").collect()} <= kept
    assert set(pairs(thin.select(near, v, 12, "lune", "off"))) <= set(pairs(thin.select(near, v, 12, "kept", "off")))


def test_live_guard_keeps_the_last_in_edge(spark):
    # Both 0 and 1 drop their edge to 3, which 2 hides; a static guard sees two in-edges.
    v = line(spark, [(0, 0, 0), (1, 0.5, 0), (2, 4, 0), (3, 5, 0)])
    e = spark.createDataFrame([(0, 2, 4.0), (0, 3, 5.0), (1, 2, 3.5), (1, 3, 4.5)], "src long, dst long, dist double")
    assert pairs(thin.new_orphans(e, thin.select(e, v, 2, guard="static"), v), "id") == [(3,)]
    assert pairs(thin.new_orphans(e, thin.select(e, v, 2, guard="live"), v), "id") == []


def test_id_map(spark):
    m = spark.createDataFrame([(0, 0), (0, 1), (0, 2), (0, 3), (1, 0), (1, 1), (1, 2)], "index_id int, local_id long")
    ok = ~((F.col("index_id") == 0) & (F.col("local_id") == 1))
    for mode, want in (("offset", [0, 2, 3, 4, 5, 6]), ("dense", [0, 1, 2, 3, 4, 5])):
        assert sorted(r["global_id"] for r in idmap.build(m, mode, ok).where("valid").collect()) == want
    with pytest.raises(ValueError):
        idmap.build(m, "other")


@pytest.mark.parametrize("kind", ["nsw", "hnsw", "vamana", "nsg", "tau_graph", "nn_descent"])
def test_builders_find_neighbours(spark, kind):
    base, asked = tables.base_and_queries(spark, SF)
    index = stage(builders.build(base.where("vec_id < 200"), kind, degree=12, m=8, ef=40, k=12, size=40))
    few = base.where("vec_id < 200")
    truth = exact.knn(few, asked, 10)
    found = search.resident(baselines.base_layer(index), few, asked, search.medoids(few), 60, 10)
    assert quality.recall(found, truth, 10).first()["recall"] > 0.85


def test_merge_keeps_recall_and_degree(spark):
    base, asked = tables.base_and_queries(spark, SF)
    v = stage(idmap.by_modulus(base.where("vec_id < 300"), 3))
    own = baselines.base_layer(stage(builders.build(v, "vamana", degree=12, size=40)))
    got = fuse.merge(own, v, 12, with_tower=True)
    assert got.edges.groupBy("src").count().agg(F.max("count")).first()[0] <= 12
    found = search.resident(got.edges, v.select("vec_id", "x"), asked, got.entries, 60, 10)
    assert quality.recall(found, exact.knn(v.select("vec_id", "x"), asked, 10), 10).first()["recall"] > 0.9
    assert got.facts["ndc_lift"] > 0 and got.layers.count() > 0


def test_levels_follow_the_law(spark):
    v = spark.range(20000).select(F.col("id").alias("vec_id"))
    share = v.where(tower.level(tower.hashed(F.col("vec_id")), 8) >= 1).count() / 20000
    assert abs(share - 1 / 8) < 4 * (1 / 8 * 7 / 8 / 20000) ** 0.5


def test_bad_vectors_and_arguments(spark, two):
    bad = spark.createDataFrame([(0, [1.0, 2.0]), (1, None), (2, [1.0, float("nan")]), (3, [1.0]), (4, [0.0, 0.0]), (5, [3.0, 1.0])], "vec_id long, x array<double>")
    good, rejected = tables.checked(bad, metric="cosine")
    assert pairs(good, "vec_id") == [(0,), (5,)]
    assert dict(pairs(rejected, "vec_id", "reason")) == {1: "null", 2: "not finite", 3: "dimension", 4: "zero"}
    for call in (lambda: distance.known("other"), lambda: lift.pool_size(8, 1), lambda: exact.knn(two, two, 0), lambda: thin.select(two, two, rule="other"), lambda: fuse.merge(exact.graph(two, 2), two.withColumn("part", F.lit(0)), 2)):
        with pytest.raises(ValueError):
            call()
    empty = two.where("vec_id < 0")
    assert exact.graph(empty, 2).count() == 0 and exact.knn(two, two, 50).count() == 64


def test_ties_go_to_the_lower_id(spark):
    v = line(spark, [(3, 1, 0), (1, -1, 0), (2, 1, 0), (7, -1, 0)])
    asked = spark.createDataFrame([(99, [0.0])], "vec_id long, x array<float>")
    assert [r["vec_id"] for r in exact.knn(v, asked, 3).orderBy("rank").collect()] == [1, 2, 3]


def test_inner_product_and_sql_functions(spark):
    distance.register(spark)
    r = spark.sql("SELECT l2(array(0D, 3D), array(4D, 0D)) a, l2sq(array(1D), array(3D)) b, inner_product(array(1D, 2D), array(3D, 4D)) c, norm2(array(3D, 4D)) d, cosine_dist(array(1D, 0D), array(0D, 2D)) e").first()
    assert tuple(r) == (5.0, 4.0, 11.0, 5.0, 1.0)


def test_store_and_vecs(spark, two, tmp_path):
    own = exact.graph(two, 2)
    store.save(own, str(tmp_path / "i"), {"metric": "l2"})
    back, meta = store.load(spark, str(tmp_path / "i"), "l2")
    assert pairs(back) == pairs(own) and meta == {"metric": "l2"}
    with pytest.raises(ValueError):
        store.load(spark, str(tmp_path / "i"), "cosine")
    x = np.arange(12, dtype=np.float32).reshape(3, 4)
    (tmp_path / "a.fvecs").write_bytes(store.vecs_bytes(x))
    assert [r["x"] for r in store.read_vecs(spark, str(tmp_path / "a.fvecs")).orderBy("row").collect()] == x.tolist()


def test_components_of_a_tree(spark):
    n = quality.tarjan([0, 1, 2, 2, 3], [1, 2, 0, 3, 4])
    assert n == 3


def test_random_candidates_are_foreign(spark):
    v = stage(idmap.skewed(tables.vectors(spark, SF)))
    got = lift.random_cross(v, 6)
    part = {r["vec_id"]: r["part"] for r in v.collect()}
    rows = pairs(got)
    assert len(rows) == len(set(rows)) and all(part[a] != part[b] for a, b in rows)
    assert len(rows) == 6 * v.count() and pairs(lift.random_cross(v, 6)) == rows
    assert lift.random_cross(v.withColumn("part", F.lit(0)), 6).count() == 0


@pytest.mark.parametrize("order", ["id", "dfs"])
def test_sweeps_settle_like_rounds(spark, order):
    v = stage(idmap.by_modulus(tables.vectors(spark, SF), 2))
    origin = v.select("vec_id", "part")
    start = stage(lift.run(exact.graph(v, 8, scope="same"), lift.random_cross(v, 8), 8).select("src", "dst", "dist"))
    truth = exact.graph(v.select("vec_id", "x"), 8)
    rounds, sweeps = [], []
    one = quality.graph_recall(refine.run(start, v, origin, 8, repair="off", log=rounds.append), truth).first()[0]
    swept = refine.run(start, v, origin, 8, repair="off", log=sweeps.append, mode="sweep", order=order)
    two = quality.graph_recall(swept, truth).first()[0]
    assert swept.groupBy("src").count().agg(F.max("count")).first()[0] == 8 and swept.where("src = dst").count() == 0
    assert two > quality.graph_recall(start, truth).first()[0] and abs(one - two) < 0.1
    assert len(sweeps) <= len(rounds) + 1 and sweeps[-1]["accepted"] <= sweeps[0]["accepted"]


def test_sweep_fixture():
    # The refine fixture: one sweep does what two rounds do.
    x, part = np.array([[0.0], [10.0], [1.0], [11.0]]), np.array([0, 0, 1, 1])
    near = [[[10.0, 1, True, True], [11.0, 3, True, True]], [[9.0, 2, True, True], [10.0, 0, True, True]], [[9.0, 1, True, True], [10.0, 3, True, True]], [[10.0, 2, True, True], [11.0, 0, True, True]]]
    refine.sweep(x, part, near, 2, 4, "cross", "l2", 0.0, "id")
    assert [[e[1] for e in row] for row in near] == [[2, 1], [3, 2], [0, 1], [1, 2]]


def test_the_surface(spark, tmp_path):
    base, asked = tables.base_and_queries(spark, SF)
    table = api.VectorTable(base.where("vec_id < 200"))
    parts = table.index("vamana", 2, degree=12, size=40)
    whole = api.merge(parts, 12, with_tower=True)
    truth = exact.knn(table.vectors, asked, 10)
    assert quality.recall(whole.search(asked, 10, 60), truth, 10).first()["recall"] > 0.9
    whole.save(str(tmp_path / "w"))
    back = api.GraphIndex.load(spark, str(tmp_path / "w"), "l2")
    assert pairs(back.edges) == pairs(whole.edges) and back.search(asked, 5, 20).count() == 5 * asked.count()
    assert back.stats().first()["n_edges"] == whole.edges.count()
    again = api.merge([whole, parts[1]], 12)
    assert again.vectors.count() == table.vectors.count()
    with pytest.raises(ValueError):
        api.merge([parts[0]], 12)
    with pytest.raises(ValueError):
        api.merge([parts[0], api.GraphIndex(parts[1].edges, parts[1].vectors, "cosine")], 12)


# --- ties ---


def brute(x, ids, k, metric="l2"):
    out = {}
    for i, a in zip(ids, x, strict=True):
        d = distance.rows(metric, np.repeat(a[None], len(x), 0), x)
        out[i] = sorted((float(w), int(j)) for w, j in zip(d, ids, strict=True) if j != i)[:k]
    return out


@pytest.mark.parametrize("form", ["twins", "grid", "offset"])
def test_exact_neighbours_under_ties(spark, form):
    rng = np.random.default_rng(3)
    x = {"twins": np.zeros((400, 3)) + 0.1, "grid": rng.integers(0, 3, (500, 3)).astype(float), "offset": rng.integers(0, 3, (300, 3)) + 1e4}[form]
    v = stage(spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, x array<double>"))
    want = [(i, j) for i, near in brute(x, range(len(x)), 5).items() for _, j in near]
    assert sorted(want) == pairs(exact.graph(v, 5))
    few = exact.knn(v, v, 5, exclude_self=True, block=70)
    assert pairs(few, "q_id", "vec_id") == sorted(want) and "Union" not in few._jdf.queryExecution().toString()


def test_range_search_in_blocks(spark):
    x = np.random.default_rng(4).integers(0, 4, (200, 2)).astype(float)
    v = stage(spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, x array<double>"))
    want = sorted((i, j) for i in range(200) for j in range(200) if np.sqrt(((x[i] - x[j]) ** 2).sum()) <= 1.0)
    assert pairs(exact.within(v, v, 1.0, block=30), "q_id", "vec_id") == want == pairs(exact.within(v, v, 1.0), "q_id", "vec_id")


# --- searches ---


@pytest.fixture(scope="module")
def halves(spark):
    v = stage(idmap.by_modulus(tables.vectors(spark, SF).where("vec_id < 160"), 2))
    return v, stage(exact.graph(v, 6, scope="same").select("src", "dst", "dist")), stage(search.medoids(v))


def test_a_shard_has_several_tasks(spark, halves):
    v, own, entries = halves
    rows = lambda df: sorted(map(tuple, df.select("src", "dst", "ndc").collect()))
    one = rows(lift.cross(own, v, entries, 4, spread=1))
    assert rows(lift.cross(own, v, entries, 4, spread=5)) == one == rows(lift.cross(own, v, entries, 4))
    assert rows(lift.cross(own, v, entries, 4, mode="frontier")) == one
    plan = lift.cross(own, v, entries, 4, spread=5)._jdf.queryExecution().toString()
    assert "salt" in plan


def test_triangles_and_width_keep_results(spark, halves):
    v, own, entries = halves
    plain, tri, wide = (lift.cross(own, v, entries, 6, **how) for how in ({}, {"tri": True}, {"width": 3}))
    assert pairs(plain) == pairs(tri)
    ndc = lambda df: df.agg(F.sum("ndc")).first()[0]
    assert ndc(tri) <= ndc(plain)
    other = lift.cross(own, v, entries, 6, mode="frontier", width=3)
    assert pairs(wide) == pairs(other) and ndc(wide) == ndc(other)
    with pytest.raises(ValueError):
        search.resident(own, v, v, entries, 4, 4, "cosine", tri=True)


# --- refinement ---


@pytest.mark.parametrize("scope", ["cross", "all"])
def test_hubs_are_split(spark, halves, scope):
    v, own, _ = halves
    start = stage(lift.run(own, lift.random_cross(v, 4), 6).select("src", "dst", "dist").withColumn("is_new", F.lit(True)))
    origin = v.select("vec_id", "part")
    whole, split = (stage(refine.offers(start, v, origin, 6, scope, hub=h)) for h in (10_000, 4))
    found = lambda df: sorted(set(pairs(df.where("src is not null"))))
    assert found(whole) == found(split)
    assert whole.agg(F.sum("tried")).first()[0] == split.agg(F.sum("tried")).first()[0] >= refine.pairs(start, origin, scope).count()
    assert pairs(refine.absorb(start, whole, 6)) == pairs(refine.absorb(start, split, 6))


def test_no_silent_change_of_method(spark, halves, monkeypatch):
    v, own, _ = halves
    monkeypatch.setattr(refine, "SWEEP_LIMIT", 10)
    with pytest.raises(ValueError):
        refine.run(own, v, v.select("vec_id", "part"), 6, mode="sweep")
    slim = own.where("src < 60 and dst < 60")
    with pytest.raises(ValueError):
        refine.repaired(slim.unionByName(own.where("src >= 60 and dst < 40")), v, limit=1)
    monkeypatch.setattr(tower, "EXACT_LIMIT", 1)
    with pytest.raises(ValueError):
        tower.rebuild(v.select("vec_id", "x"), 2)


def test_sweeps_repair_inside(spark):
    """Two lines of neighbours that nobody at the end points to: after every sweep the orphans have an in-edge."""
    x = np.array([[0.0], [1.0], [2.0], [3.0], [50.0]])
    lists = [[[1.0, 1, False, False], [2.0, 2, False, False]], [[1.0, 0, False, False], [1.0, 2, False, False]], [[1.0, 1, False, False], [1.0, 3, False, False]], [[1.0, 2, False, False], [2.0, 1, False, False]], [[47.0, 3, False, False], [48.0, 2, False, False]]]
    off = [[list(e) for e in row] for row in lists]
    refine.sweep(x, np.zeros(5, int), off, 2, 1, "cross", "l2", 0.0, "id", "off")
    refine.sweep(x, np.zeros(5, int), lists, 2, 1, "cross", "l2", 0.0, "id", "every")
    assert not any(e[1] == 4 for row in off for e in row) and any(e[1] == 4 for row in lists for e in row)
    assert [len(r) for r in lists] == [2] * 5


# --- maps, layers, measures, baselines ---


def test_a_merge_under_a_map(spark):
    base = tables.vectors(spark, SF).where("vec_id < 150")
    v = stage(idmap.full_and_subset(base, 3))
    built = stage(builders.build(v, "vamana", degree=8)).where("layer = 0").select("src", "dst", "dist", F.col("index_id").alias("part"))
    members = v.select(F.col("part").alias("index_id"), F.col("vec_id").alias("local_id"), F.col("vec_id").alias("key"), F.col("part").alias("ts"))
    newest = fuse.merge(built, v, 8, mapped=idmap.build(members, "newest"), pool=16).edges
    assert {r["src"] for r in newest.collect()} == set(range(150)) and newest.where("src = dst").count() == 0
    kept = idmap.build(members.withColumn("global_id", F.col("local_id") + 1000), "explicit", F.col("local_id") % 3 != 0)
    left = fuse.merge(built, v, 8, mapped=kept, pool=16, storage="cache").edges
    assert {r["src"] for r in left.collect()} | {r["dst"] for r in left.collect()} == {i + 1000 for i in range(150) if i % 3}


def test_layers_by_insertion(spark):
    v = stage(tables.vectors(spark, SF))
    got = tower.rebuild(v, 4, seed=1, mode="insert")
    by = {r["layer"]: (r["n"], r["d"]) for r in got.groupBy("layer", "src").count().groupBy("layer").agg(F.count("*").alias("n"), F.max("count").alias("d")).collect()}
    assert sorted(by) == list(range(1, max(by) + 1)) and all(by[i][0] >= by[i + 1][0] for i in range(1, max(by))) and max(d for _, d in by.values()) <= 4


def test_components_by_colours(spark):
    rng = np.random.default_rng(5)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 40, (70, 2)) if a != b]
    e = stage(spark.createDataFrame(edges, "src long, dst long"))
    v = spark.range(40).select(F.col("id").alias("vec_id"))
    assert quality.strong_components(e, v, limit=0).first()[0] == quality.strong_components(e, v).first()[0]


def test_objective_and_stored_size(spark, tmp_path):
    row = quality.objective(spark, 100, 40, 5.0, 0.9).first()
    assert (row["saved"], row["speedup"]) == (60, 2.5)
    spark.range(100).write.parquet(str(tmp_path / "p"))
    assert quality.stored(spark, str(tmp_path / "p")).first()["n_bytes"] == sum(f.stat().st_size for f in (tmp_path / "p").glob("*.parquet"))


def test_stored_baselines(spark, halves):
    v, own, _ = halves
    gone = spark.createDataFrame([(2,), (5,)], "vec_id long")
    edges, cost = baselines.fresh_scans(own, v, 8, 30, deleted=gone)
    ends = {r["src"] for r in edges.collect()} | {r["dst"] for r in edges.collect()}
    assert ends == set(range(160)) - {2, 5} and cost > 0 and edges.groupBy("src").count().agg(F.max("count")).first()[0] <= 8
    doubled, _ = baselines.parallel_doubling(v, 8, 30)
    assert doubled.select("src").distinct().count() == 160


def test_pool_of_a_whole_shard_is_searched_exactly(spark):
    rng = np.random.default_rng(5)
    x, far = rng.normal(size=(60, 6)), np.arange(60)
    # Vertices from 40 on can't be reached from the others; twins at one place go by id.
    x[3] = x[30]
    src = np.repeat(far, 3)
    dst = np.where(src < 40, rng.integers(0, 40, 180), rng.integers(0, 60, 180))
    own = search.Shard(far * 2, x, src * 2, dst * 2, "l2")
    q, ids = rng.normal(size=(7, 6)), np.arange(100, 107)
    shape = [("q_id", pa.int64()), ("index_id", pa.int32()), ("rank", pa.int32()), ("vec_id", pa.int64()), ("dist", pa.float64()), ("ndc", pa.int64()), ("hops", pa.int32())]
    entry = np.array([0, 0, 5, 0, 45, 45, 0])
    got = own.exhausted(ids, q, entry, 5, 1, shape).to_pylist()
    want = []
    for i in range(7):
        pool, ndc, hops = own.beam(q[i], int(entry[i]), 60)
        want += [{"q_id": int(ids[i]), "index_id": 1, "rank": r + 1, "vec_id": int(own.ids[v]), "dist": d, "ndc": ndc, "hops": hops} for r, (d, v) in enumerate(pool[:5])]
    key = lambda r: (r["q_id"], r["rank"])
    assert sorted(got, key=key) == sorted(want, key=key)
    v = stage(spark.createDataFrame([(i, x[i].tolist(), i % 2) for i in range(60)], "vec_id long, x array<double>, part int"), "vectors")
    near = stage(exact.graph(v, 4, scope="same"), "near")
    entries = stage(search.lowest(v), "entries")
    found = {mode: lift.cross(near, v, entries, 60, mode=mode, keep=3).orderBy("src", "dst").collect() for mode in ("resident", "frontier")}
    assert found["resident"] == found["frontier"] and len(found["resident"]) == 180


@pytest.fixture(scope="module")
def few(spark, tmp_path_factory):
    """A folder with 44 vectors of three dimensions."""
    folder = str(tmp_path_factory.mktemp("few"))
    x = np.random.default_rng(3).normal(size=(44, 3)).tolist()
    spark.createDataFrame(list(enumerate(x)), "vec_id long, embedding array<float>").write.parquet(f"{folder}/embeddings.parquet")
    return folder, np.array(x, np.float32).astype(float)


def test_cost_model_takes_the_dimension_of_the_table(spark, few):
    for row, h in zip(core.cost_model(spark, few[0]).orderBy("h").collect(), (2, 4), strict=True):
        assert (row["n"], row["h"], row["dim"]) == (44, h, 3)
        assert row["lift_cost"] == pytest.approx(h * (44 // h) ** (1 + 2 / 3) * np.log(44 // h) * 16, abs=1e-5)


def test_curve_is_one_of_the_table(spark, few):
    folder, x = few
    ids = np.arange(44)
    base, asked = ids[ids % 11 != 7], ids[ids % 11 == 7]
    truth = np.array([base[np.argsort(np.linalg.norm(x[base] - x[q], axis=1), kind="stable")[:10]] for q in asked])
    points = [((truth % 8 < p).mean(), (base % 8 < p).sum()) for p in range(1, 9)]
    (a, n), (b, m) = next((s, t) for s, t in zip(points, points[1:], strict=False) if s[0] <= 0.97 < t[0])
    assert core.curve_at_recall(spark, folder).collect() == [(0.97, pytest.approx(n + (0.97 - a) * (m - n) / (b - a), abs=1e-5))]


def test_pools_follow_from_the_table(spark, few):
    folder, x = few
    far = np.linalg.norm(x[:, None] - x[None], axis=2)
    np.fill_diagonal(far, np.inf)
    near = np.argsort(far, axis=1, kind="stable")
    want = {}
    for h in range(2, 8):
        for k in (8, 16, 32):
            for m in (near[:, :k] % h == np.arange(44)[:, None] % h).sum(axis=1).tolist():
                key = (h, k, m, lift.pool_size(k, h), lift.pool_size(k, h, m))
                want[key] = want.get(key, 0) + 1
    assert {tuple(r)[:5]: r["n"] for r in core.pool_size(spark, folder).collect()} == want


def test_kernels_hold_no_table_of_all_pairs():
    x = np.random.default_rng(2).normal(size=(900, 16))
    far = np.linalg.norm(x - x[0], axis=1)
    near = sorted(zip(far[1:].tolist(), range(1, 900), strict=True))
    tracemalloc.start()
    net = builders.Net(x)
    kept = net.prune(near, 12, "alpha", 1.2)
    pruned = tracemalloc.get_traced_memory()[1]
    tracemalloc.reset_peak()
    built = builders.nn_descent(net, 10)[0]
    joined = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert pruned < 5 << 20 and joined < 30 << 20
    want = []
    for d, v in near:
        if len(want) < 12 and not any(1.2 * np.linalg.norm(x[w] - x[v]) <= d for w in want):
            want.append(v)
    assert kept == want
    truth = np.argsort(np.linalg.norm(x[:, None] - x[None], axis=2), axis=1)[:, 1:11]
    assert np.mean([len(set(built[v]) & set(truth[v].tolist())) / 10 for v in range(900)]) > 0.85
    assert all(far == sorted(far) for v, us in built.items() for far in [np.linalg.norm(x[us] - x[v], axis=1).tolist()])


def test_strategies_run_side_by_side(spark):
    met = threading.Barrier(2, timeout=60)
    assert experiments.together([lambda i=i: [(met.wait() >= 0, i)] for i in range(2)]) == [(True, 0), (True, 1)]
    made = experiments.beside(lambda: met.wait() >= 0 and spark.range(3), "side")
    met.wait()
    assert made.result().count() == 3


def test_equal_vectors_are_measured_once(spark, monkeypatch):
    """Ranks, ids and ties as in a plain search, though only distinct vectors meet."""
    asked = []
    plain = exact.knn
    rng = np.random.default_rng(4)
    places = [(int(i), float(x), 0) for i, x in zip(rng.permutation(600), rng.integers(0, 12, 600), strict=True)]
    v = line(spark, [*places, (600, 40.0, 0), (601, 41.0, 0)])
    monkeypatch.setattr(exact, "knn", lambda vectors, queries, *a, **how: asked.append((vectors.count(), queries.count())) or plain(vectors, queries, *a, **how))
    for k in (1, 5, 70):
        got = pairs(exact.twin_knn(v.select("vec_id", "x"), k), "q_id", "rank", "vec_id", "dist")
        assert got == pairs(plain(v, v, k, exclude_self=True), "q_id", "rank", "vec_id", "dist")
    monkeypatch.setattr(relational.tables, "part_vectors", lambda *_: v.select("vec_id", "x"))
    assert relational.part_neighbors(spark, SF).count() == 602 * 5
    assert asked == [(14, 14)] * 4


@pytest.mark.parametrize("metric", ["l2", "cosine", "ip"])
def test_a_task_gives_its_nearest_only(spark, monkeypatch, metric):
    monkeypatch.setattr(exact, "ROWS", 16)
    x = np.random.default_rng(5).integers(1, 4, (400, 3)).astype(float)
    v = spark.createDataFrame([(i, x[i].tolist(), i % 3) for i in range(400)], "vec_id long, x array<float>, part int").coalesce(1)
    pack = spark.sparkContext.broadcast(v.where("vec_id < 20").toArrow().combine_chunks())
    assert exact._candidates(v, pack, 7, metric, True, "any").count() == 20 * 7
    assert exact._candidates(v, pack, 7, metric, True, "other", True).count() == 20 * 7 * 2
    got = pairs(exact.knn(v, v.where("vec_id < 20"), 7, metric, exclude_self=True), "q_id", "rank", "vec_id")
    far = distance.rows(metric, x[:20, None, :], x[None, :, :])
    far[np.arange(20), np.arange(20)] = np.inf
    assert got == [(q, r + 1, int(v)) for q in range(20) for r, v in enumerate(np.lexsort((np.arange(400), far[q]))[:7])]


@pytest.mark.parametrize("metric", ["l2", "ip"])
def test_beams_in_step_find_what_single_ones_find(monkeypatch, metric):
    monkeypatch.setattr(search, "WAVE", 7)
    rng = np.random.default_rng(6)
    for x in (rng.normal(size=(300, 6)), rng.integers(0, 3, (300, 3)).astype(float)):  # the second with many ties
        src = np.repeat(np.arange(300), 6)
        shard = search.Shard(np.arange(300), x, src, rng.integers(0, 300, len(src)), metric)  # some lists name a vertex twice
        q = x[rng.choice(300, 40)] + 0.5
        far, at, ndc, hops, visits = search.beams(shard.x, shard.links, q, np.full((40, 1), 9), 12, metric, True)
        for i in range(40):
            seen = []
            pool, n, h = search.beam(shard.x, shard.neighbours, q[i], [9], 12, metric, seen)
            assert [(d, v) for d, v in zip(far[i].tolist(), at[i].tolist(), strict=True) if v >= 0] == [(d, int(v)) for d, v in pool]
            assert (n, h) == (ndc[i], hops[i]) and visits[1][visits[0] == i].tolist() == [v for _, v in seen]


def test_batches_of_the_builder(monkeypatch):
    """A batch of one vertex gives the sequential graph and count; larger ones a graph as good."""
    x = np.random.default_rng(7).normal(size=(1700, 8))
    few, want = builders.Net(x[:150]), builders.Net(x[:150])
    to = builders.vamana(want, 8, 20)[0]
    lists = builders.Lists(few, 8)
    for v, us in builders._random(few, 8, 1).items():
        lists.to[v, : len(us)] = us
    for a in (1.0, 1.2):
        for v in builders.mixed(150, 1):
            lists.refit(np.array([v]), builders.medoid(few.x), 20, a)
    assert [sorted(row[row >= 0].tolist()) for row in lists.to] == [sorted(to[v]) for v in range(150)] and few.ndc == want.ndc
    recall = {}
    for share in (100, 1 << 20):
        monkeypatch.setattr(builders, "SHARE", share)
        net = builders.Net(x)
        to = builders.vamana(net, 12, 30)[0]
        assert all(len(set(us)) == len(us) <= 12 and v not in us for v, us in to.items())
        truth = np.argsort(np.linalg.norm(x[:, None] - x[None, :80], axis=2), axis=0)[1:11].T
        found = [[u for _, u in search.beam(x, lambda v, to=to: to[v], x[q], [builders.medoid(x)], 40, "l2")[0]] for q in range(80)]
        recall[share] = np.mean([len(set(f) & set(t.tolist())) / 10 for f, t in zip(found, truth, strict=True)])
    assert recall[100] > recall[1 << 20] - 0.02


def test_local_joins_in_blocks_give_the_same_graph(monkeypatch):
    x = np.random.default_rng(8).normal(size=(700, 12))
    whole = builders.Net(x)
    want = builders.nn_descent(whole, 10)[0]
    tracemalloc.start()
    builders.nn_descent(builders.Net(x), 10)
    most = tracemalloc.get_traced_memory()[1]
    sizes, offered = [], builders._offered
    monkeypatch.setattr(builders, "PAIRS", 256)
    monkeypatch.setattr(builders, "OFFERS", 64)
    monkeypatch.setattr(builders, "_offered", lambda *a: (sizes.append(len(o)) or o for o in offered(*a)))
    tracemalloc.reset_peak()
    blocks = builders.Net(x)
    got = builders.nn_descent(blocks, 10)[0]
    least = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert got == want and blocks.ndc == whole.ndc == sum(sizes) + 700 * 10
    # Smaller ends lie among the low ids, so the first blocks are up to twice the mean.
    assert max(sizes) <= 2 * 256 * 64 and least < most / 2


def test_wide_beams_in_step_find_what_single_ones_find(monkeypatch):
    monkeypatch.setattr(search, "WAVE", 7)
    rng = np.random.default_rng(9)
    for x in (rng.normal(size=(300, 6)), rng.integers(0, 3, (300, 3)).astype(float)):
        src = np.repeat(np.arange(300), 6)
        shard = search.Shard(np.arange(300), x, src, rng.integers(0, 300, len(src)), "l2")
        q, starts = x[rng.choice(300, 40)] + 0.5, np.array([[9, -1, 4]] * 40)
        far, at, ndc, hops, visits = search.beams(shard.x, shard.links, q, starts, 12, "l2", True, 4)
        for i in range(40):
            seen = []
            pool, n, h = search.beam(shard.x, shard.neighbours, q[i], [9, 4], 12, "l2", seen, 4)
            assert [(d, v) for d, v in zip(far[i].tolist(), at[i].tolist(), strict=True) if v >= 0] == [(d, int(v)) for d, v in pool]
            assert (n, h) == (ndc[i], hops[i]) and visits[1][visits[0] == i].tolist() == [v for _, v in seen]


@pytest.mark.parametrize("rule", thin.RULES)
@pytest.mark.parametrize("scale", [1.0, 1e30, 1e-25])
def test_lists_are_pruned_with_few_distances(monkeypatch, rule, scale):
    """Products of rounded vectors decide nearly all pairs; kept neighbours and counts are those of one list at a time."""
    rng = np.random.default_rng(10)
    measured, rows = [], distance.rows
    for x, often in ((scale * rng.normal(size=(400, 16)), False), (scale * rng.integers(0, 3, (400, 4)), True)):  # the second with many ties
        for cap, n in ((3, 60), (12, 60)):
            one, many = builders.Net(x), builders.Net(x)
            near = [one.sorted(v, rng.choice(400, n).tolist()) for v in range(50)]
            ids, far = np.full((50, n), -1), np.full((50, n), np.inf)
            for v, own in enumerate(near):
                far[v, : len(own)], ids[v, : len(own)] = zip(*own, strict=True)
            one.ndc = 0
            want = [one.prune(own, cap, rule, 1.2, 0.1 * scale) for own in near]
            with monkeypatch.context() as m:
                m.setattr(distance, "rows", lambda metric, a, b: measured.append(len(a)) or rows(metric, a, b))
                kept = builders.prune_many(many, ids, far, cap, rule, 1.2, 0.1 * scale)
            assert [ids[v][kept[v]].tolist() for v in range(50)] == want and many.ndc == one.ndc
            assert often or scale < 1 or sum(measured) < one.ndc / 10
            measured.clear()


def test_batches_of_layered_insertion(monkeypatch):
    """Batches of one vertex give the graph and count of insertion one by one; larger ones a graph as good."""
    x = np.random.default_rng(11).normal(size=(2400, 8))
    one, few = builders.Layered(builders.Net(x[:300]), 6, 30, 1), builders.Layered(builders.Net(x[:300]), 6, 30, 1)
    for v in range(300):
        one.insert(v)
    few.grow(np.arange(100))
    monkeypatch.setattr(builders, "WIDTH", 1)
    for v in range(100, 300):
        few.insert_many(np.array([v]))
    sets = lambda layers: {at: {v: sorted(us) for v, us in to.items()} for at, to in layers.items()}
    assert sets(few.built()) == sets(one.layers) and few.net.ndc == one.net.ndc and (few.entry, few.top) == (one.entry, one.top)
    monkeypatch.undo()
    recall, sizes, insert_many = {}, [], builders.Layered.insert_many
    monkeypatch.setattr(builders.Layered, "insert_many", lambda self, some, ef=None: sizes.append(len(some)) or insert_many(self, some, ef))
    for share in (100, 1 << 20):
        monkeypatch.setattr(builders, "SHARE", share)
        to = builders.hnsw(builders.Net(x), 8, 40)[0]
        assert len(to) == 2400 and all(len(set(us)) == len(us) <= 16 and v not in us for v, us in to.items())
        truth = np.argsort(np.linalg.norm(x[:, None] - x[None, :80], axis=2), axis=0)[1:11].T
        found = [[u for _, u in search.beam(x, lambda v, to=to: to[v], x[q], [builders.medoid(x)], 40, "l2")[0]] for q in range(80)]
        recall[share] = np.mean([len(set(f) & set(t.tolist())) / 10 for f, t in zip(found, truth, strict=True)])
    assert recall[100] > recall[1 << 20] - 0.02 and sum(sizes) == 800 and max(sizes) > 30


def test_benches_share_their_questions(spark, monkeypatch):
    """The exact answers don't depend on the split, so several merges of one base need them once."""
    asked, knn = [], exact.knn
    monkeypatch.setattr(exact, "knn", lambda *a, **how: asked.append(1) or knn(*a, **how))
    rows = experiments.heterogeneous(spark, SF).collect()
    assert len(asked) == 1 and [r["setting"] for r in rows] == ["vamana+hnsw", "7:1"] and all(r["recall"] > 0.9 for r in rows)


def test_in_edges_are_counted_once_a_repair(spark, monkeypatch):
    v = tables.vectors(spark, SF)
    edges = stage(exact.graph(v, 2).select("src", "dst", "dist"), "few")
    want = pairs(refine.repaired(edges, v))
    labels, kept = [], refine.stage
    monkeypatch.setattr(refine, "stage", lambda df, label: labels.append(label) or kept(df, label))
    assert pairs(refine._kept_or_repaired(edges, v, "exact")) == want and want != pairs(exact.graph(v, 2))
    assert labels == ["repair-degree", "repair-around", "repair", "refine"]


@pytest.mark.parametrize("scope", ["cross", "all"])
def test_pools_share_vectors_in_groups(spark, halves, scope):
    """Groups of pools offer the same and count the same, however many there are; what several pools of a group find leaves it once."""
    v, own, _ = halves
    start = stage(lift.run(own, lift.random_cross(v, 4), 6).select("src", "dst", "dist").withColumn("is_new", F.expr("dst % 3 <> 0")))
    origin = v.select("vec_id", "part")
    want, tried = None, None
    for groups in (1, 3, 40):  # the last more than a list is long
        got = stage(refine.offers(start, v, origin, 6, scope, groups=groups))
        found = pairs(got.where("src is not null"))
        assert groups > 1 or len(found) == len(set(found))
        n = got.agg(F.sum("tried")).first()[0]
        want, tried = want or set(found), tried or n
        assert set(found) == want and n == tried >= refine.pairs(start, origin, scope).count() > 0
    labels = refine.even_labels(spark, 9)
    dealt = spark.createDataFrame([(n,) for n in labels], "id int").select((F.pmod(F.hash("id"), F.lit(4))).alias("task")).groupBy("task").count().collect()
    assert len(set(labels)) == 9 and sorted(r["count"] for r in dealt) == [2, 2, 2, 3]


@pytest.mark.parametrize("scale", [1.0, 1e30, 1e-25])
def test_rounded_vectors_tell_what_is_too_far(monkeypatch, scale):
    """Searches in step measure few of the vectors they meet in full, and find and count the same."""
    rng = np.random.default_rng(12)
    sizes, measure = [], search.measure
    monkeypatch.setattr(search, "measure", lambda metric, a, b: sizes.append(len(a)) or measure(metric, a, b))
    for x, often in ((scale * rng.normal(size=(900, 12)), False), (scale * rng.integers(0, 3, (900, 4)), True)):  # the second with many ties
        src = np.repeat(np.arange(900), 8)
        shard = search.Shard(np.arange(900), x, src, rng.integers(0, 900, len(src)), "l2")
        q, starts = x[:60] + 0.3 * scale, np.full((60, 1), 5)
        with np.errstate(over="ignore"):
            single = x.astype(np.float32)
        one, whole = search.beams(shard.x, shard.links, q, starts, 12, "l2", True, 4), sum(sizes)
        sizes.clear()
        two, few = search.beams(shard.x, shard.links, q, starts, 12, "l2", True, 4, single), sum(sizes)
        sizes.clear()
        assert all((a == b).all() for a, b in zip((*one[:4], *one[4]), (*two[:4], *two[4]), strict=True))
        assert often or scale != 1 or few < whole / 2


def test_parts_are_built_in_tasks_of_their_own(spark):
    """As many parts as a shuffle has tasks don't wait for each other; of more, several go through one task."""
    v = tables.vectors(spark, SF)
    for h in (4, 9):
        split = v.withColumn("part", F.pmod("vec_id", F.lit(h)).cast("int"))
        with_ids = builders.build(split, "random", degree=3).select("index_id", F.col("src") % h, F.col("dst") % h).distinct().collect()
        assert sorted(tuple(r) for r in with_ids) == [(p, p, p) for p in range(h)]
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        four = builders.build(v.withColumn("part", F.pmod("vec_id", F.lit(4)).cast("int")), "random", degree=3)
        assert four.select(F.spark_partition_id().alias("task"), "index_id").distinct().groupBy("task").count().agg(F.count("*")).first()[0] == 4
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_free_places_of_a_pool_name_no_vertex():
    """Searches in step with a pool larger than what they reach find that, as one by one, and nothing that isn't there."""
    rng = np.random.default_rng(3)
    for n in (90, 200, 310, 400):
        x, src = rng.normal(size=(n, 6)), np.repeat(np.arange(n), 30)
        shard = search.Shard(np.arange(n), x, src, rng.integers(0, n, len(src)), "l2")
        q, starts = rng.normal(size=(20, 6)), rng.integers(0, n, (20, 1))
        far, at, ndc, hops, _ = search.beams(x, shard.links, q, starts, 500, "l2", width=4)
        assert at.max() < n and ((at < 0) == np.isinf(far)).all()
        for i in range(20):
            pool, n_measured, n_expanded = shard.beam(q[i], int(starts[i, 0]), 500, 4)
            assert [v for _, v in pool] == at[i, : len(pool)].tolist() and (at[i, len(pool) :] == -1).all()
            assert (n_measured, n_expanded) == (ndc[i], hops[i])


def test_exact_repair_takes_what_it_needs(spark, monkeypatch):
    """Orphans are settled in turn as over their whole surroundings, of which one task gets a small share."""

    def in_turn(edges):
        lists, indeg, lost = {}, {}, []
        for s, d, w in edges:
            lists.setdefault(s, []).append([w, d, False])
            indeg[d] = indeg.get(d, 0) + 1
        lost = [s for s in sorted(lists) if s not in indeg]
        around = sum(len(lists[v]) for v in {e[1] for s in lost for e in lists[s]} | set(lost))
        for row in lists.values():
            row.sort()
        for orphan in lost:
            for w, v, _ in list(lists[orphan]):
                victim = next((e for e in reversed(lists[v]) if not e[2] and indeg[e[1]] > 1), None)
                if victim:
                    indeg[victim[1]] -= 1
                    victim[:] = [w, orphan, True]
                    lists[v].sort()
                    break
        return sorted((s, e[1]) for s, row in lists.items() for e in row), len(lost), around

    rng = np.random.default_rng(5)
    sent, settle = [], refine._settle
    monkeypatch.setattr(refine, "stage", lambda df, label, kept=refine.stage: (sent.append(df.count()) if label == "repair-around" else None) or kept(df, label))
    # Targets that some are more often than others, and forty that all point to, whose lists run out.
    for power, most in ((6, 0.7), (None, 1.1)):
        to = lambda v: {u for u in (400 * rng.random(12) ** power if power else rng.integers(0, 40, 12)).astype(int).tolist() if u != v}  # noqa: B023, E731
        edges = sorted({(v, u, float(rng.integers(1, 50))) for v in range(400) for u in to(v)})
        want, lost, around = in_turn(edges)
        assert lost > 9
        e = stage(spark.createDataFrame(edges, "src long, dst long, dist double"))
        v = spark.range(400).select(F.col("id").alias("vec_id"))
        for near, spare in ((1, 1), (4, 4)):
            monkeypatch.setattr(refine, "NEAR", near)
            monkeypatch.setattr(refine, "SPARE", spare)
            sent.clear()
            assert pairs(refine.repaired(e, v)) == want
            assert most > 1 or max(sent) < most * around, (sent, around)


def test_batch_insertion_searches_in_step(monkeypatch):
    """All searches of a batch run on the graph without it: edges and distances as one by one, deleted vertices too."""
    rng = np.random.default_rng(4)
    x = rng.normal(size=(260, 8))
    graph = builders.vamana(builders.Net(x[:150]), degree=8)[0]
    for dead in (set(), {3, 40, 200}):
        want, got = (builders.Net(x) for _ in range(2))
        for net in (want, got):
            net.to = {v: list(us) for v, us in graph.items()}
        new = [v for v in range(150, 260) if v not in dead]
        for v in list(want.to):
            if v not in dead and any(u in dead for u in want.to[v]):
                wide = [u for u in want.to[v] if u not in dead] + [w for u in want.to[v] if u in dead for w in want.to[u] if w not in dead]
                want.to[v] = want.prune(want.sorted(v, wide), 8, "alpha", 1.2)
        want.to = {v: us for v, us in want.to.items() if v not in dead}
        alive = sorted(want.to)
        back = {}
        for v in new:
            seen = []
            want.search(v, [alive[builders.medoid(x[alive])]], 20, seen)
            back[v] = want.prune(want.sorted(v, [u for _, u in seen]), 8, "alpha", 1.2)
        want.to |= back
        for u in alive:
            both = list(dict.fromkeys(want.to[u] + [v for v, us in back.items() if u in us]))
            want.to[u] = both if len(both) <= 8 else want.prune(want.sorted(u, both), 8, "alpha", 1.2)
        with monkeypatch.context() as m:
            m.setattr(builders.Net, "search", None)
            baselines.insert_frozen(got, new, dead, 8, 20, 1.2)
        assert {v: sorted(us) for v, us in got.to.items()} == {v: sorted(us) for v, us in want.to.items()} and got.ndc == want.ndc


def test_probe_options_try_all_that_they_name(spark, monkeypatch):
    """Foreign searches by joins, pruned, several vertices a round and routed, each in a merge of its own."""
    tried = []

    class Bench:
        def __init__(self, *_, **__):
            pass

        def merged(self, **how):
            tried.append(how)
            return None, 0, {}

        def measured(self, name, edges, cost, setting):
            return [{"setting": setting, "method": name, "pool": 40, "ask": 10, "recall": 1.0, "search_ndc": 0.0, "hops": 0.0, "n_edges": 0, "merge_ndc": cost}]

    monkeypatch.setattr(experiments, "Bench", Bench)
    settings = [r["setting"] for r in experiments.probe_options(spark, SF).collect()]
    assert len(settings) == len(tried) == len(set(settings)) and {"resident", "joins", "tri", "width 4", "reach 1"} <= set(settings)
    assert all(how in tried for how in ({}, {"probe": "frontier"}, {"tri": True}, {"width": 4}, {"reach": 1}))


def test_tau_graph_searches_in_step(monkeypatch):
    """Candidates come from searches of the frozen neighbour graph: lists and distances as one by one."""
    rng = np.random.default_rng(6)
    for x, tau in ((rng.normal(size=(500, 10)), 0.3), (rng.integers(0, 3, (300, 5)).astype(float), 0.4)):  # the second with twins
        want = builders.Net(x)
        builders.nn_descent(want, 8)
        base, entry, out = want.to, builders.medoid(x), {}
        for v in range(len(x)):
            want.to = base
            near = want.sorted(v, [u for _, u in want.search(v, [entry], 20)[:12]] + base[v])
            always = [u for d, u in near if d <= 3 * tau]
            out[v] = list(dict.fromkeys(always + want.prune(near, 8, "tau", tau=tau)))[:8]
        to = {v: list(us) for v, us in out.items()}
        for v, us in out.items():
            for u in us:
                if v not in to[u] and len(to[u]) < 16:
                    to[u].append(v)
        with monkeypatch.context() as m:
            m.setattr(builders.Net, "search", None)
            m.setattr(builders, "HELD", 64)
            got = builders.Net(x)
            assert builders.tau_graph(got, degree=8, size=20, h=12, tau=tau)[0] == to and got.ndc == want.ndc
