"""The merge: lift, refine with repair, thin, reciprocate, and rebuild the upper layers."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardweave.operators import lift, refine, search, thin, tower
from shardweave.staging import drop, stage, storing

#: The ablations: random foreign candidates or searched ones, rounds of joins (all visits, then all updates) or fused sweeps
#: by id or depth first. ``plain`` also forgets which edges are new.
PRESETS = {
    "plain": {"init": "random", "flags": False},
    "o0": {"init": "random"},
    "o1": {"init": "probe"},
    "o2": {"init": "random", "mode": "sweep"},
    "full": {"init": "probe", "mode": "sweep"},
    "full_dfs": {"init": "probe", "mode": "sweep", "order": "dfs"},
}


@dataclass
class Merged:
    """A merged index: base edges, upper layers if any, the entry, and the counts of the merge."""

    edges: DataFrame
    layers: DataFrame | None
    entries: DataFrame
    facts: dict = field(default_factory=dict)


def merge(edges: DataFrame, vectors: DataFrame, k: int, *, storage: str = "parquet", **how) -> Merged:
    """:func:`run` with its tables kept in ``storage``, ``parquet`` or ``cache``."""
    with storing(storage):
        return run(edges, vectors, k, **how)


def run(
    edges: DataFrame, vectors: DataFrame, k: int, *, pool: int | str = "worst", init: str = "probe", flags: bool = True, max_rounds: int = 8, scope: str = "cross",
    repair: str = "every", rule: str = "kept", guard: str = "static", alpha: float = 1.0, tau: float = 0.0, stages: tuple[str, ...] = ("lift", "refine", "thin"),
    with_tower: bool = False, metric: str = "l2", reach: int | None = None, stop_fraction: float = 0.0, cap: int | None = None, seed: int = 7,
    mode: str = "bsp", order: str = "id", settle: str = "exact", probe: str = "resident", width: int = 1, tri: bool = False, mapped: DataFrame | None = None,
) -> Merged:
    """One graph over all parts of ``vectors (vec_id, x, part)`` from ``edges (src, dst, dist)`` inside the parts.

    ``init``: foreign candidates by ``probe`` (beam search), ``random`` or ``exact``. Without ``flags`` every edge counts
    as new in each round. ``reach`` routes a vertex to the nearest foreign indexes only. ``probe``, ``width`` and ``tri``: how
    beams run, see :func:`shardweave.operators.lift.cross`. ``mode``, ``order`` and ``settle``: see
    :func:`shardweave.operators.refine.run`.

    ``mapped (index_id, local_id, valid, global_id)``: ids are local to their parts, edges have ``part`` as well, and the merged
    graph has the global ids. Foreign searches run on the graphs as they are; candidates and edges of an end that isn't valid
    go after them, and copies of one vertex become one.
    """
    if init not in ("probe", "random", "exact"):
        raise ValueError(f"init must be probe, random or exact, not {init!r}")
    facts: dict = {"rounds": []}
    named = None
    if mapped is not None:
        # Ids that are unique over the parts, and what becomes of each.
        top = (vectors.agg(F.max("part")).first()[0] or 0) + 1
        unique = lambda c, part: F.col(c) * top + F.col(part)
        named = stage(mapped.where("valid").select(unique("local_id", "index_id").alias("uid"), "global_id"), "merge-map")
        edges = edges.select(unique("src", "part").alias("src"), unique("dst", "part").alias("dst"), "dist")
        vectors = stage(vectors.select(unique("vec_id", "part").alias("vec_id"), "x", "part"), "merge-vectors")
    base = stage(edges.select("src", "dst", "dist"), "merge-own")
    entries = stage(search.medoids(vectors, metric), "merge-entries")
    h = entries.count()
    if h < 2:
        raise ValueError(f"a merge takes two indexes at least, not {h}")
    size = lift.pool_of(pool, base, k, h)
    if init == "probe":
        found = stage(lift.cross(base, vectors, entries, size, metric, reach, probe, None, width, tri), "merge-cross")
        facts["ndc_lift"] = found.agg(F.sum("ndc")).first()[0] or 0
    elif init == "exact":
        found = stage(lift.cross_exact(vectors, size, metric), "merge-cross")
        facts["ndc_lift"] = 0
    else:
        found = stage(lift.random_cross(vectors, size, metric, seed), "merge-cross")
        facts["ndc_lift"] = found.count()
    own, other = base, found.select("src", "dst", "dist")
    if named is not None:
        own, other = renamed(own, named), renamed(other, named)
        one = vectors.join(named, F.col("vec_id") == F.col("uid")).groupBy(F.col("global_id").alias("vec_id")).agg(F.max_by(F.struct("x", "part"), "part").alias("v"))
        vectors = stage(one.select("vec_id", "v.x", "v.part"), "merge-vectors")
    origin = vectors.select("vec_id", "part")
    now = stage(lift.run(own, other, k).select("src", "dst", "dist"), "merge-lift")
    drop(found)
    if "refine" in stages:
        log = facts["rounds"].append
        if flags:
            now = refine.run(now, vectors, origin, k, max_rounds, scope, repair, metric, stop_fraction, cap, log, mode, order, settle).select("src", "dst", "dist")
        else:
            for _ in range(max_rounds):
                now = refine.run(now.select("src", "dst", "dist"), vectors, origin, k, 1, scope, repair, metric, cap=cap, log=log, settle=settle)
                if not facts["rounds"][-1]["accepted"]:
                    break
            now = now.select("src", "dst", "dist")
    facts["ndc_refine"] = sum(r["pairs"] for r in facts["rounds"])
    facts["ndc_thin"] = 0
    if "thin" in stages:
        # Every pair of a list, the most that the rule can ask for.
        n = F.col("count")
        facts["ndc_thin"] = now.groupBy("src").count().agg(F.sum(F.floor(n * (n - 1) / 2))).first()[0] or 0
        slim = thin.select(now, vectors, k, rule, guard, alpha, tau, metric)
        now = stage(thin.reciprocate(slim, k).select("src", "dst", "dist"), "merge-thin")
    layers = stage(tower.rebuild(vectors.select("vec_id", "x"), k, seed, metric), "merge-tower") if with_tower else None
    whole = search.medoids(vectors.select("vec_id", "x"), metric)
    for used in (base, entries, *([named] if named is not None else [])):
        drop(used)
    facts["pool"] = size
    return Merged(now, layers, whole, facts)


def renamed(edges: DataFrame, named: DataFrame) -> DataFrame:
    """Edges under global ids; those of an end without one go, and those between copies of a vertex."""
    a = named.select(F.col("uid").alias("src"), F.col("global_id").alias("a"))
    b = named.select(F.col("uid").alias("dst"), F.col("global_id").alias("b"))
    return edges.join(a, "src").join(b, "dst").where("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst"), "dist")


def tree(vectors: DataFrame, k: int, parts: int, fan_in: int = 8, kind: str = "nn_descent", metric: str = "l2", **how) -> Merged:
    """Many parts merged level by level, ``fan_in`` at a time, so that foreign searches grow with the levels and not with the square of the parts."""
    from shardweave.plans import builders

    now = vectors.select("vec_id", "x", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("part"))
    edges = builders.build(now, kind, metric, **({"k": k} | how)).select("src", "dst", "dist")
    merged = None
    costs: list[int] = []
    while parts > 1:
        groups = -(-parts // fan_in)
        done = []
        for g in range(groups):
            some = now.where(F.floor(F.col("part") / fan_in) == g)
            own = edges.join(some.select(F.col("vec_id").alias("src")), "src", "left_semi").select("src", "dst", "dist")
            last = g == groups - 1 and parts - g * fan_in == 1
            if last:
                done.append(own)
                continue
            one = merge(own, some, k, metric=metric)
            costs.append(sum(v for name, v in one.facts.items() if name.startswith("ndc")))
            done.append(one.edges)
        edges = done[0]
        for d in done[1:]:
            edges = edges.unionByName(d)
        edges = stage(edges, "tree")
        now = now.withColumn("part", F.floor(F.col("part") / fan_in).cast("int"))
        parts = groups
        merged = Merged(edges, None, search.medoids(vectors.select("vec_id", "x"), metric), {"ndc": sum(costs)})
    return merged or Merged(stage(edges, "tree"), None, search.medoids(vectors.select("vec_id", "x"), metric))
