"""Refining a neighbour graph by local joins between neighbours, and repair of vertices that nobody points to."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.staging import drop, stage

#: Rows of the orphans' surroundings that one task may repair in sequence.
REPAIR_LIMIT = 2_000_000
#: Edges that one task may refine vertex by vertex.
SWEEP_LIMIT = 2_000_000


def pools(edges: DataFrame, cap: int | None = None) -> DataFrame:
    """``(pivot, member, is_new)``: who points to a pivot or is pointed to by it; new if either edge is.

    ``cap`` keeps the nearest reverse members of a pivot, against hubs; without it none is left out.
    """
    ahead = edges.select(F.col("src").alias("pivot"), F.col("dst").alias("member"), "dist", "is_new")
    behind = edges.select(F.col("dst").alias("pivot"), F.col("src").alias("member"), "dist", "is_new")
    if cap:
        order = Window.partitionBy("pivot").orderBy("dist", "member")
        behind = behind.withColumn("r", F.row_number().over(order)).where(F.col("r") <= cap).drop("r")
    # Dealt out by pivot, so that what follows a pool needs no other shuffle.
    return ahead.unionByName(behind).repartition("pivot").groupBy("pivot", "member").agg(F.max("is_new").alias("is_new"))


def pairs(edges: DataFrame, origin: DataFrame, scope: str = "cross", cap: int | None = None) -> DataFrame:
    """Distinct pairs ``a < b`` of members of one pool, one of them new; ``cross``: of different origin.

    Pairs are made inside the pivot's row, and the filter runs inside the generator.
    """
    if scope not in ("cross", "all"):
        raise ValueError(f"pairs must be cross or all, not {scope!r}")
    member = pools(edges, cap).join(origin.select(F.col("vec_id").alias("member"), F.col("part").alias("origin")), "member")
    packed = member.groupBy("pivot").agg(F.collect_list(F.struct(F.col("member").alias("id"), "origin", "is_new")).alias("m")).where(F.exists("m", lambda x: x.is_new))
    one = packed.select("m", F.explode("m").alias("a")).where("a.is_new")
    other = F.filter("m", lambda b: (b.id != F.col("a.id")) & (~b.is_new | (b.id > F.col("a.id"))) & (F.lit(scope == "all") | (b.origin != F.col("a.origin"))))
    two = one.select("a", F.explode(other).alias("b"))
    return two.select(F.least("a.id", "b.id").alias("a"), F.greatest("a.id", "b.id").alias("b")).distinct()


#: Members of a pool that are paired at a time; a larger pool is dealt out as pairs of its blocks.
HUB = 256
#: Pools that a task holds at a time, and pairs that it measures at a time.
HELD, PAIRS = 8192, 1 << 14
OFFERS = "src long, dst long, dist double, tried long"


def offers(edges: DataFrame, vectors: DataFrame, origin: DataFrame, k: int, scope: str = "cross", metric: str = "l2", cap: int | None = None, hub: int = HUB, groups: int | None = None) -> DataFrame:
    """``(src, dst, dist, tried)``: pairs of pool members that would enter a list, and rows without a source that count distances.

    Pools are dealt out to ``groups``, by default so many that each has :data:`HELD` on average and all cores have work. A vector
    travels once to each group whose pools list it, pairs are made and measured there, and only ids that beat the k-th edge
    of an end leave it, once a group. A pair that several pivots share is measured by each. Pools of more than ``hub`` members are
    dealt out: block with block, each pair in one row.
    """
    if scope not in ("cross", "all"):
        raise ValueError(f"pairs must be cross or all, not {scope!r}")
    groups = groups or group_count(vectors)
    labels = even_labels(vectors.sparkSession, groups)
    whole = Window.partitionBy("pivot")
    sized = pools(edges, cap).withColumns({"n": F.count("*").over(whole), "any": F.max("is_new").over(whole)}).where(F.col("any") & (F.col("n") > 1))
    blocks = F.ceil(F.col("n") / hub).cast("int")
    own = F.pmod(F.xxhash64("member"), blocks).cast("int")
    other = F.explode(F.sequence(F.lit(0), blocks - 1))
    dealt = sized.select("pivot", "member", "is_new", own.alias("own"), other.alias("other")).select("pivot", "member", "is_new", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))
    dealt = dealt.withColumn("group", F.array(*map(F.lit, labels))[F.pmod(F.xxhash64("pivot", "i", "j"), F.lit(groups)).cast("int")])
    last = edges.groupBy("src").agg(F.max(F.struct("dist", "dst")).alias("last"), F.count("*").alias("held"))
    facts = vectors.select(F.col("vec_id").alias("member"), "x").join(origin.select(F.col("vec_id").alias("member"), F.col("part").cast("int").alias("part")), "member")
    facts = facts.join(last, F.col("member") == F.col("src"), "left").select("member", "x", "part", F.when(F.col("held") >= k, F.col("last.dist")).alias("far"), F.col("last.dst").alias("far_id"))
    if groups > k:
        facts = facts.join(dealt.groupBy("member").agg(F.collect_set("group").alias("listed")), "member")
    else:  # nearly each group lists each vertex
        facts = facts.withColumn("listed", F.array(*map(F.lit, labels)))
    sent = facts.select(F.explode("listed").alias("group"), "member", "x", "part", "far", "far_id")

    def run(pooled: pa.Table, held: pa.Table) -> pa.Table:
        kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64())
        table = lambda *columns: pa.table({n: pa.array(c, t) for n, c, t in zip(("src", "dst", "dist", "tried"), columns, kinds, strict=True)})
        if not pooled.num_rows or not held.num_rows:
            return table([], [], [], [])
        ids = held.column("member").to_numpy()
        order = np.argsort(ids)
        ids, x = ids[order], held.column("x").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]
        part, far, far_id = held.column("part").to_numpy()[order], held.column("far").to_numpy(zero_copy_only=False).astype(float)[order], held.column("far_id").fill_null(0).to_numpy()[order]
        far = np.where(np.isnan(far), np.inf, far)
        far_id = np.where(np.isinf(far), 0, far_id)
        pivot, i, j, new, block = (pooled.column(n).to_numpy(zero_copy_only=False) for n in ("pivot", "i", "j", "is_new", "own"))
        at = np.searchsorted(ids, pooled.column("member").to_numpy())
        order = np.lexsort((at, j, i, pivot))
        pivot, i, j, new, block, at = (c[order] for c in (pivot, i, j, new.astype(bool), block, at))
        begins = np.flatnonzero(np.concatenate(([True], (pivot[1:] != pivot[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1]))))
        ends = np.append(begins[1:], len(pivot))
        row = np.repeat(np.arange(len(begins)), ends - begins)
        # Each new member meets all of its pool; of two new ones the smaller meets the larger.
        first = np.flatnonzero(new)
        sizes = (ends - begins)[row[first]]
        cuts = np.cumsum(sizes)
        out, tried, lo = [], 0, 0
        while lo < len(first):
            hi = max(lo + 1, int(np.searchsorted(cuts, (cuts[lo - 1] if lo else 0) + PAIRS, "right")))
            n = sizes[lo:hi]
            a = np.repeat(first[lo:hi], n)
            b = np.arange(len(a)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(begins[row[first[lo:hi]]], n)
            lo = hi
            ok = (at[a] != at[b]) & (~new[b] | (at[b] > at[a]))
            if scope == "cross":
                ok &= part[at[a]] != part[at[b]]
            ok &= (i[a] == j[a]) | (block[a] != block[b])
            a, b = at[a[ok]], at[b[ok]]
            d = distance.rows(metric, x.take(a, 0).astype(np.float64), x.take(b, 0).astype(np.float64))
            tried += len(d)
            for p, q in ((a, b), (b, a)):
                enters = np.flatnonzero((d < far[p]) | ((d == far[p]) & (ids[q] < far_id[p])))
                out.append((p[enters], q[enters], d[enters]))
        p, q, d = (np.concatenate(z) for z in zip(*out, strict=True)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        _, once = np.unique(p * len(ids) + q, return_index=True)
        found = table(ids[p[once]], ids[q[once]], d[once], np.zeros(len(once), np.int64))
        return pa.concat_tables([found, table([None], [None], [None], [tried])])

    return dealt.groupBy("group").cogroup(sent.groupBy("group")).applyInArrow(run, OFFERS)


def even_labels(spark: SparkSession, n: int) -> list[int]:
    """n integers that a shuffle deals evenly to its tasks."""
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = spark.range(0, 8 * max(n, tasks), 1, 1).select(F.col("id").cast("int").alias("id"))
    by_task = Window.partitionBy(F.pmod(F.hash("id"), F.lit(tasks))).orderBy("id")
    return [r["id"] for r in rows.withColumn("turn", F.row_number().over(by_task)).orderBy("turn", "id").limit(n).collect()]


def group_count(vectors: DataFrame) -> int:
    """So many groups of pools that each has :data:`HELD` on average and all cores have work."""
    return max(vectors.sparkSession.sparkContext.defaultParallelism, -(-vectors.count() // HELD))


def absorb(edges: DataFrame, offered: DataFrame, k: int) -> DataFrame:
    """The best k of edges and offers; edges that stay are old, offers that enter are new."""
    old = edges.select("src", "dst", "dist", F.lit(False).alias("is_new"))
    fresh = offered.where("src is not null").select("src", "dst", "dist", F.lit(True).alias("is_new"))
    once = old.unionByName(fresh).groupBy("src", "dst").agg(F.min("dist").alias("dist"), F.min("is_new").alias("is_new"))
    order = Window.partitionBy("src").orderBy("dist", "dst")
    return once.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).drop("rank")


def once(edges: DataFrame, vectors: DataFrame, origin: DataFrame, k: int, scope: str = "cross", metric: str = "l2", cap: int | None = None) -> DataFrame:
    """One round: visit, offer, absorb."""
    return absorb(edges, offers(edges, vectors, origin, k, scope, metric, cap), k)


def run(
    edges: DataFrame, vectors: DataFrame, origin: DataFrame, k: int, max_rounds: int = 8, scope: str = "cross", repair: str = "every", metric: str = "l2",
    stop_fraction: float = 0.0, cap: int | None = None, log: Callable[[dict], None] | None = None, mode: str = "bsp", order: str = "id", settle: str = "exact",
) -> DataFrame:
    """Rounds until no more than ``stop_fraction`` of the edges is new. Each is written out and the one before deleted.

    ``bsp`` visits all vertices and then updates all, in joins. ``sweep`` visits and updates vertex by vertex, so that a
    vertex sees what the ones before it in ``order`` (``id`` or ``dfs``) changed; it is sequential, runs in one task, and
    refuses more than :data:`SWEEP_LIMIT` edges. ``repair`` runs in ``every`` round, after the ``last``, or is ``off``;
    ``settle`` is its mode, see :func:`repaired`.
    """
    if repair not in ("every", "last", "off"):
        raise ValueError(f"repair must be every, last or off, not {repair!r}")
    if mode not in ("bsp", "sweep") or order not in ("id", "dfs"):
        raise ValueError(f"mode must be bsp or sweep and order id or dfs, not {mode!r} and {order!r}")
    given = edges if "is_new" in edges.columns else edges.withColumn("is_new", F.lit(True))
    now = stage(given.select("src", "dst", "dist", "is_new"), "refine")
    if mode == "sweep":
        n = now.count()
        if n > SWEEP_LIMIT:
            raise ValueError(f"sweeps run in one task: {n} edges are more than {SWEEP_LIMIT}; refine by rounds (bsp)")
        swept = stage(_swept(now, vectors, origin, k, max_rounds, scope, metric, stop_fraction, order, repair), "refine-sweep")
        if log:
            facts = swept.where("src is null").orderBy("round").collect()  # a row a round
            for r in facts:
                log({"round": r["round"], "pairs": r["pairs"], "accepted": r["accepted"]})
        drop(now)
        return swept.where("src is not null").select("src", "dst", "dist", "is_new")
    groups = group_count(vectors)
    for turn in range(1, max_rounds + 1):
        offered = stage(offers(now, vectors, origin, k, scope, metric, cap, groups=groups), "refine-offers")
        new = stage(absorb(now, offered, k), "refine")
        counted = new.select(F.col("is_new").cast("long").alias("accepted"), F.lit(1).alias("n"), F.lit(0).cast("long").alias("tried"))
        counted = counted.unionByName(offered.where("src is null").select(F.lit(0).cast("long").alias("accepted"), F.lit(0).alias("n"), "tried"))
        facts = counted.agg(*[F.sum(c).alias(c) for c in ("accepted", "n", "tried")]).first()
        if log:
            log({"round": turn, "pairs": facts["tried"] or 0, "accepted": facts["accepted"] or 0})
        drop(offered)
        drop(now)
        now = _kept_or_repaired(new, vectors, settle) if repair == "every" else new
        if (facts["accepted"] or 0) <= stop_fraction * (facts["n"] or 0):
            break
    return _kept_or_repaired(now, vectors, settle) if repair == "last" else now


def _kept_or_repaired(edges: DataFrame, vectors: DataFrame, settle: str) -> DataFrame:
    """Staged edges as they are where nobody is an orphan, else repaired and staged anew; in-edges are counted once."""
    degree = stage(indegrees(edges, vectors), "repair-degree")
    if degree.where("indeg = 0").isEmpty():
        drop(degree)
        return edges
    fixed = stage(repaired(edges, vectors, settle, degree=degree), "refine")
    drop(edges)
    drop(degree)
    return fixed


# --- visit and update in one pass ---


def walk(lists: list[list[list]]) -> list[int]:
    """Positions in depth-first order, nearest neighbours first, from the lowest position on."""
    seen, out = set(), []
    for root in range(len(lists)):
        todo = [root]
        while todo:
            v = todo.pop()
            if v in seen:
                continue
            seen.add(v)
            out.append(v)
            todo += [e[1] for e in reversed(lists[v]) if e[1] not in seen]
    return out


def sweep(x: np.ndarray, part: np.ndarray, lists: list[list[list]], k: int, rounds: int, scope: str, metric: str, stop_fraction: float, order: str, repair: str = "off") -> list[tuple[int, int]]:
    """Refine ``lists`` (sorted ``[dist, position, new ahead, new behind]``) in place; ``(pairs, accepted)`` of each round.

    An edge is new to its source and to its target apart, since either is visited at its own time. ``repair``: after
    ``every`` sweep, whose successors see it, after the ``last``, or ``off``.
    """
    behind: list[set[int]] = [set() for _ in lists]
    for v, row in enumerate(lists):
        for e in row:
            behind[e[1]].add(v)
    has = [{e[1] for e in row} for row in lists]

    def offer(v: int, u: int, d: float) -> int:
        row = lists[v]
        if u in has[v] or (len(row) >= k and (d, u) >= (row[-1][0], row[-1][1])):
            return 0
        row.append([d, u, True, True])
        row.sort(key=lambda e: (e[0], e[1]))
        has[v].add(u)
        behind[u].add(v)
        if len(row) > k:
            gone = row.pop()[1]
            has[v].discard(gone)
            behind[gone].discard(v)
        return 1

    log = []
    for _ in range(rounds):
        pairs = accepted = 0
        for p in walk(lists) if order == "dfs" else range(len(lists)):
            fresh: dict[int, bool] = {}
            for e in lists[p]:
                fresh[e[1]] = e[2]
                e[2] = False
            for s in behind[p]:
                e = next(e for e in lists[s] if e[1] == p)
                fresh[s] = fresh.get(s, False) or e[3]
                e[3] = False
            ids = sorted(fresh)
            found = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if (fresh[a] or fresh[b]) and (scope == "all" or part[a] != part[b]) and not (b in has[a] and a in has[b])]
            if not found:
                continue
            a, b = np.array(found).T
            pairs += len(found)
            for (v, u), d in zip(found, distance.rows(metric, x[a], x[b]).tolist(), strict=True):
                accepted += offer(v, u, d) + offer(u, v, d)
        log.append((pairs, accepted))
        if repair == "every":
            _mend_lists(lists, behind, has)
        if accepted <= stop_fraction * sum(map(len, lists)):
            break
    if repair == "last":
        _mend_lists(lists, behind, has)
    return log


def _mend_lists(lists: list[list[list]], behind: list[set[int]], has: list[set[int]]) -> None:
    """:func:`mend` on the lists of a sweep, in place."""
    src = [v for v, row in enumerate(lists) for _ in row]
    flat = [e for row in lists for e in row]
    lost = np.array([v for v, s in enumerate(behind) if not s], np.int64)
    if not len(lost) or not flat:
        return
    moves = mend(np.array(src), np.array([e[1] for e in flat]), np.array([e[0] for e in flat]), lost, {v: len(s) for v, s in enumerate(behind)})
    for v, gone, come, d in moves:
        lists[v] = sorted([e for e in lists[v] if e[1] != gone] + [[d, come, True, True]], key=lambda e: (e[0], e[1]))
        has[v].discard(gone)
        has[v].add(come)
        behind[gone].discard(v)
        behind[come].add(v)


def _swept(edges: DataFrame, vectors: DataFrame, origin: DataFrame, k: int, rounds: int, scope: str, metric: str, stop_fraction: float, order: str, repair: str) -> DataFrame:
    """Edges after sweeps, and a row without a source for each round's counts."""
    lists = edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst", "is_new"))).alias("to"))
    rows = vectors.select("vec_id", "x").join(origin.select("vec_id", "part"), "vec_id").join(lists, F.col("vec_id") == F.col("src"), "left").select("vec_id", "x", "part", "to")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("vec_id")
        ids = t.column("vec_id").to_pylist()
        at = {v: i for i, v in enumerate(ids)}
        near = [[[e["dist"], at[e["dst"]], e["is_new"], e["is_new"]] for e in to or []] for to in t.column("to").to_pylist()]
        log = sweep(distance.matrix(t.column("x")), t.column("part").to_numpy(), near, k, rounds, scope, metric, stop_fraction, order, repair)
        out = [(ids[v], ids[e[1]], e[0], e[2] or e[3], None, None, None) for v, row in enumerate(near) for e in row]
        out += [(None, None, None, None, i + 1, n, m) for i, (n, m) in enumerate(log)]
        kinds = (pa.int64(), pa.int64(), pa.float64(), pa.bool_(), pa.int32(), pa.int64(), pa.int64())
        return pa.table({n: pa.array(c, kind) for n, c, kind in zip(("src", "dst", "dist", "is_new", "round", "pairs", "accepted"), zip(*out, strict=True), kinds, strict=True)})

    return rows.groupBy(F.lit("all")).applyInArrow(run, "src long, dst long, dist double, is_new boolean, round int, pairs long, accepted long")


# --- vertices without an in-edge ---


def indegrees(edges: DataFrame, vectors: DataFrame) -> DataFrame:
    """``(id, indeg)`` of every vertex, zeros too."""
    counts = edges.groupBy("dst").agg(F.count("*").alias("n"))
    return vectors.select(F.col("vec_id").alias("id")).join(counts, F.col("id") == F.col("dst"), "left").select("id", F.coalesce("n", F.lit(0)).alias("indeg"))


def orphans(edges: DataFrame, vectors: DataFrame) -> DataFrame:
    return vectors.select(F.col("vec_id").alias("id")).join(edges, F.col("id") == F.col("dst"), "left_anti")


def mend(src: np.ndarray, dst: np.ndarray, dist: np.ndarray, lost: np.ndarray, indeg: dict[int, int]) -> list[tuple[int, int, int, float]]:
    """The moves of :func:`settled` where lists are known in full."""
    own = np.isin(src, lost)
    return settled((src[own], dst[own], dist[own]), (src, dst, dist), indeg)[0]


def settled(near: tuple, far: tuple, indeg: dict[int, int], cut: frozenset = frozenset()) -> tuple[list[tuple[int, int, int, float]], bool]:
    """In ascending order each orphan takes the place of a far neighbour, with in-edges to spare, of its nearest neighbour that has one.

    ``near`` are the edges ``(src, dst, dist)`` of the orphans, ``far`` those whose targets may go. ``cut`` has ``(source, is near)`` of
    lists that are longer than given, where the nearest or the farthest were. Returns ``(source, who goes, who comes, distance)``,
    and whether a cut list ran out.
    """
    near, far = (tuple(c[order] for c in t) for t, order in ((t, np.lexsort((t[1], t[2], t[0]))) for t in (near, far)))
    at = [dict(zip(ids.tolist(), zip(lo.tolist(), (lo + n).tolist(), strict=True), strict=True)) for ids, lo, n in (np.unique(t[0], return_index=True, return_counts=True) for t in (near, far))]
    # What may still go of a list, farthest last: who has no in-edge to spare never has one again. Changes of lists of orphans.
    left: dict[int, list[int]] = {}
    gone: dict[int, set[int]] = {}
    come: dict[int, list[tuple[float, int]]] = {}
    out = []
    for orphan, (lo, hi) in at[0].items():
        mine = list(zip(near[2][lo:hi].tolist(), near[1][lo:hi].tolist(), strict=True))
        if orphan in come:
            end = mine[-1] if (orphan, True) in cut else (np.inf, 0)
            mine = sorted([e for e in mine if e[1] not in gone[orphan]] + [e for e in come[orphan] if e < end])
        for w, v in mine:
            if v not in left:
                left[v] = far[1][slice(*at[1].get(v, (0, 0)))].tolist()
            some = left[v]
            while some and indeg[some[-1]] <= 1:
                some.pop()
            if some:
                victim = some.pop()
                out.append((v, victim, orphan, w))
                indeg[victim] -= 1
                if v in at[0]:
                    gone.setdefault(v, set()).add(victim)
                    come.setdefault(v, []).append((w, orphan))
                break
            if (v, False) in cut:
                return out, True
        else:
            if (orphan, True) in cut:
                return out, True
    return out, False


#: Nearest neighbours of an orphan, and targets of one of these besides one for each orphan, that exact repair looks at first.
NEAR, SPARE = 4, 4


def repaired(edges: DataFrame, vectors: DataFrame, mode: str = "exact", limit: int = REPAIR_LIMIT, degree: DataFrame | None = None) -> DataFrame:
    """``edges`` with in-edges for orphans; out-degrees stay. ``exact`` takes the orphans one by one, as much of their surroundings as they
    need in one task, and refuses more than ``limit`` edges there; ``rounds`` settles proposals in parallel rounds. ``degree``: the
    :func:`indegrees` where they are known."""
    if mode not in ("exact", "rounds"):
        raise ValueError(f"mode must be exact or rounds, not {mode!r}")
    if mode == "rounds":
        return _by_rounds(edges, vectors)
    degree = indegrees(edges, vectors) if degree is None else degree
    near, spare = NEAR, SPARE
    while True:
        around = stage(_around(edges, degree, near, spare), "repair-around")
        n = around.count()
        if n > limit:
            raise ValueError(f"exact repair runs in one task: {n} edges around the orphans are more than {limit}; settle by rounds")
        if not n:
            drop(around)
            return edges
        moves = stage(around.groupBy(F.lit("all")).applyInArrow(_settle, "src long, gone long, dst long, dist double"), "repair")
        drop(around)
        if moves.where("src is null").isEmpty():
            return _moved(edges, moves)
        # Few neighbours had an in-edge to spare: more of each list.
        drop(moves)
        near, spare = 4 * near, 4 * spare


def _around(edges: DataFrame, degree: DataFrame, near: int, spare: int) -> DataFrame:
    """``(src, dst, dist, indeg, lost, cut)``: the ``near`` nearest edges of the orphans (``lost``), and of who they lead to the farthest edges
    whose targets have in-edges to spare, one for each orphan that asks and ``spare`` more; ``cut`` where a list has more of them."""
    lost = degree.where("indeg = 0").select("id")
    by_src = Window.partitionBy("src")
    own = edges.join(lost, F.col("src") == F.col("id"), "left_semi").select("src", "dst", "dist").withColumns({"r": F.row_number().over(by_src.orderBy("dist", "dst")), "n": F.count("*").over(by_src)}).where(F.col("r") <= near)
    own = own.select("src", "dst", "dist", F.lit(0).cast("long").alias("indeg"), F.lit(True).alias("lost"), (F.col("n") > near).alias("cut"))
    # An orphan's list may come to hold another orphan, so these are asked as well.
    asked = own.select(F.col("dst").alias("v"), F.lit(1).alias("p")).unionByName(lost.select(F.col("id").alias("v"), F.lit(0).alias("p"))).groupBy("v").agg(F.sum("p").alias("p"))
    there = edges.select("src", "dst", "dist").join(asked, F.col("src") == F.col("v")).join(degree.where("indeg > 1"), F.col("dst") == F.col("id"))
    most = F.col("p") + spare
    there = there.withColumns({"r": F.row_number().over(by_src.orderBy(F.desc("dist"), F.desc("dst"))), "n": F.count("*").over(by_src)}).where(F.col("r") <= most)
    return own.unionByName(there.select("src", "dst", "dist", "indeg", F.lit(False).alias("lost"), (F.col("n") > most).alias("cut")))


def _settle(t: pa.Table) -> pa.Table:
    """The moves of :func:`settled`; a row without a source where a cut list ran out."""
    src, dst, dist, indeg = (t.column(c).to_numpy() for c in ("src", "dst", "dist", "indeg"))
    lost, cut = (t.column(c).to_numpy(zero_copy_only=False).astype(bool) for c in ("lost", "cut"))
    cuts = frozenset(zip(src[cut].tolist(), lost[cut].tolist(), strict=True))
    moves, short = settled(*((src[some], dst[some], dist[some]) for some in (lost, ~lost)), dict(zip(dst[~lost].tolist(), indeg[~lost].tolist(), strict=True)), cuts)
    columns = list(zip(*(moves if not short else [(None,) * 4]), strict=True)) or [[]] * 4
    return pa.table({n: pa.array(c, k) for n, c, k in zip(("src", "gone", "dst", "dist"), columns, (pa.int64(), pa.int64(), pa.int64(), pa.float64()), strict=True)})


def _moved(edges: DataFrame, moves: DataFrame) -> DataFrame:
    kept = edges.join(moves.select(F.col("src").alias("s"), F.col("gone")), (F.col("src") == F.col("s")) & (F.col("dst") == F.col("gone")), "left_anti")
    come = moves.select("src", "dst", "dist", *([F.lit(True).alias("is_new")] if "is_new" in edges.columns else []))
    names = come.columns
    return kept.select(*names).unionByName(come)


def _by_rounds(edges: DataFrame, vectors: DataFrame) -> DataFrame:
    """Each orphan proposes to its nearest neighbour that has a victim; one proposal a neighbour wins, and a victim loses
    fewer in-edges a round than it has. Edges that came in a round before are no victims. Every move settles an orphan and
    makes none, so the rounds end."""
    now, come = edges, None
    while True:
        degree = indegrees(now, vectors)
        lost = degree.where("indeg = 0").select(F.col("id").alias("orphan"))
        own = now.join(lost, F.col("src") == F.col("orphan")).select("orphan", F.col("dst").alias("v"), F.col("dist").alias("w"))
        old = now if come is None else now.join(come, (F.col("src") == F.col("cs")) & (F.col("dst") == F.col("cd")), "left_anti")
        spare = old.join(degree.where("indeg > 1"), F.col("dst") == F.col("id")).select(F.col("src").alias("v"), F.col("dst").alias("victim"), F.col("dist").alias("far"), "indeg")
        last = spare.groupBy("v").agg(F.max(F.struct("far", "victim", "indeg")).alias("m")).select("v", "m.victim", "m.indeg")
        first = Window.partitionBy("orphan").orderBy("w", "v")
        asks = own.join(last, "v").withColumn("r", F.row_number().over(first)).where("r = 1")
        wins = asks.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("w", "orphan"))).where("r = 1")
        fair = wins.withColumn("r", F.row_number().over(Window.partitionBy("victim").orderBy("w", "orphan"))).where("r < indeg")
        moves = stage(fair.select(F.col("v").alias("src"), F.col("victim").alias("gone"), F.col("orphan").alias("dst"), F.col("w").alias("dist")), "repair")
        if moves.isEmpty():
            return now
        now = stage(_moved(now, moves), "repair")
        here = moves.select(F.col("src").alias("cs"), F.col("dst").alias("cd"))
        come = here if come is None else come.unionByName(here)
