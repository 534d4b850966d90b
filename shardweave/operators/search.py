"""Beam search on proximity graphs.

``resident``: a graph shard is held whole by several tasks that share its queries. ``frontier``: each round joins the queries'
best open vertices to the edge table, so a graph may be larger than any task; one shuffle a join and one small driver check
a round. Both expand the same vertices in order of distance and id, and so find the same results with the same number of
distances.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import exact
from shardweave.staging import drop, stage

#: Pairs of one matrix product where a pool holds a whole shard.
EXHAUST = 1 << 22
#: Places of the table of queries and vertices in which beams in step note what they have seen.
SEEN = 1 << 25
#: Most beams that run in step.
WAVE = 512
RESULT = "q_id long, index_id int, rank int, vec_id long, dist double, ndc long, hops int"


class Shard:
    """One graph in memory: ids in order, vectors, and neighbours as rows of positions with their distances."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, src: np.ndarray, dst: np.ndarray, metric: str, far: np.ndarray | None = None):
        order = np.argsort(ids, kind="stable")
        self.ids, self.x, self.metric = ids[order], x[order], metric
        a, b = np.searchsorted(self.ids, src), np.searchsorted(self.ids, dst)
        good = (a < len(ids)) & (b < len(ids))
        a, b, src, dst = a[good], b[good], src[good], dst[good]
        far = None if far is None else far[good]
        good = (self.ids[a] == src) & (self.ids[b] == dst)
        a, b = a[good], b[good]
        _, by = np.unique(a * len(ids) + b, return_index=True)  # a list may name a vertex twice
        self.to, self.starts = b[by], np.searchsorted(a[by], np.arange(len(ids) + 1))
        self.far = None if far is None else far[good][by]

    def neighbours(self, at: int) -> np.ndarray:
        return self.to[self.starts[at] : self.starts[at + 1]]

    def links(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The neighbours of many positions, as (row of the position, neighbour)."""
        sizes = self.starts[at + 1] - self.starts[at]
        # Places of their edges: each list's first place, and so on to its last.
        places = np.arange(sizes.sum()) + np.repeat(self.starts[at] - (np.cumsum(sizes) - sizes), sizes)
        return np.repeat(np.arange(len(at)), sizes), self.to[places]

    def lengths(self, at: int) -> np.ndarray:
        return self.far[self.starts[at] : self.starts[at + 1]]

    def beam(self, q: np.ndarray, entry: int, size: int, width: int = 1, tri: bool = False) -> tuple[list[tuple[float, int]], int, int]:
        """The pool of the best ``size`` vertices found from ``entry``, distances evaluated, vertices expanded."""
        return beam(self.x, self.neighbours, q, [entry], size, self.metric, width=width, lengths=self.lengths if tri else None)

    def reached(self, entry: int) -> np.ndarray:
        """The positions of all vertices on paths from ``entry``, itself included."""
        seen = np.zeros(len(self.ids), bool)
        seen[entry] = True
        front = np.array([entry])
        while len(front):
            front = np.unique(self.links(front)[1])
            front = front[~seen[front]]
            seen[front] = True
        return np.flatnonzero(seen)

    def exhausted(self, q_id: np.ndarray, q: np.ndarray, entry: np.ndarray, k: int, target: int, shape: list) -> pa.Table:
        """What beams with a pool for the whole shard find: the ``k`` nearest reached vertices; each of these is measured and expanded."""
        out = []
        for start in np.unique(entry):
            at = self.reached(int(start))
            asked = np.flatnonzero(entry == start)
            step = max(1, EXHAUST // len(at))
            for lo in range(0, len(asked), step):
                mine = asked[lo : lo + step]
                r, v, d = exact.nearest(self.metric, q[mine], q_id[mine], self.x[at], self.ids[at], k)
                n = len(r)
                out.append((q_id[mine][r], np.full(n, target), np.arange(n) - np.searchsorted(r, r) + 1, v, d, np.full(n, len(at)), np.full(n, len(at))))
        columns = [np.concatenate(c) for c in zip(*out, strict=True)]
        return pa.table({name: pa.array(c, t) for (name, t), c in zip(shape, columns, strict=True)})


def beam(
    x: np.ndarray, neighbours, q: np.ndarray, entries: list[int], size: int, metric: str, visited: list | None = None, width: int = 1, lengths=None
) -> tuple[list[tuple[float, int]], int, int]:
    """Best-first search with a pool of ``size``; stops when every pooled vertex is expanded. ``visited`` collects those.

    ``width`` vertices are expanded at a time. With the ``lengths`` of the edges a neighbour is passed over without a distance
    where the triangle inequality keeps it out of a full pool; the pool stays the same.
    """
    if width == 1 and lengths is None:
        return _one_by_one(x, neighbours, q, entries, size, metric, visited)
    first = distance.rows(metric, q[None, :], x[entries])
    pool = sorted(zip(first.tolist(), entries, strict=True))[:size]
    seen, done = set(entries), set()
    ndc, hops = len(entries), 0
    while True:
        opened = [p for p in pool if p[1] not in done][:width]
        if not opened:
            return pool, ndc, hops
        worst = pool[-1] if len(pool) >= size else None
        new = []
        for p in opened:
            done.add(p[1])
            hops += 1
            if visited is not None:
                visited.append(p)
            near = neighbours(p[1])
            if lengths is not None and worst is not None and len(near):
                out = np.abs(np.asarray(lengths(p[1])) - p[0]) > worst[0] * (1 + 1e-12)
                seen.update(np.asarray(near)[out].tolist())
            for v in near:
                if v not in seen:
                    seen.add(v)
                    new.append(v)
        if not new:
            continue
        ndc += len(new)
        found = distance.rows(metric, q[None, :], x[new]).tolist()
        fresh = [p for p in zip(found, new, strict=True) if worst is None or p < worst]
        if fresh:
            pool = sorted(pool + fresh)[:size]


def _one_by_one(x: np.ndarray, neighbours, q: np.ndarray, entries: list[int], size: int, metric: str, visited: list | None) -> tuple[list[tuple[float, int]], int, int]:
    """:func:`beam` a vertex at a time: the pool stays in order, and ``at`` is the first place in it that may be open."""
    far = distance.to_row(metric, q)
    pool = sorted(zip(far(x[entries]).tolist(), entries, strict=True))[:size]
    seen, done = set(entries), set()
    ndc, hops, at = len(entries), 0, 0
    note = seen.add
    while at < len(pool):
        p = pool[at]
        at += 1
        if p[1] in done:
            continue
        done.add(p[1])
        hops += 1
        if visited is not None:
            visited.append(p)
        near = neighbours(p[1])
        if isinstance(near, np.ndarray):
            near = near.tolist()
        new = [v for v in near if not (v in seen or note(v))]
        if not new:
            continue
        ndc += len(new)
        found = far(x[new])
        if len(pool) >= size:
            few = np.flatnonzero(found <= pool[-1][0]).tolist()
            if not few:
                continue
            fresh = [p for p in zip(found[few].tolist(), [new[i] for i in few], strict=True) if p < pool[-1]]
        else:
            fresh = list(zip(found.tolist(), new, strict=True))
        for p in fresh:
            place = bisect_left(pool, p)
            pool.insert(place, p)
            if place < at:
                at = place
        del pool[size:]
    return pool, ndc, hops


def beams(
    x: np.ndarray, links: Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]], q: np.ndarray, starts: np.ndarray, size: int, metric: str, visits: bool = False, width: int = 1, single: np.ndarray | None = None
) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, tuple[np.ndarray, np.ndarray] | None]:
    """:func:`beam` for many queries in step, each with a row of entries in ``starts`` (-1: none), with the same results.

    ``links`` gives the neighbours of positions as (row, neighbour), rows in order; neither it nor a row of ``starts`` names a
    vertex twice. Result: distances and positions of the pools, ordered and filled up with infinity and -1, distances evaluated
    and vertices expanded of each query; with ``visits`` also the pairs (query, expanded vertex). ``width``: see :func:`beam`.
    With ``single``, ``x`` in single precision, rounded vectors (l2 only) tell what is too far for a pool, and only the rest is measured in full.
    """
    near = nearby(single, q) if single is not None and metric == "l2" else None
    n, end = len(q), len(x)
    # Positions stand doubled, and one more where nothing is left to expand.
    far, at = np.full((n, size), np.inf), np.full((n, size), 2 * end + 1, np.int64)
    ndc, hops, seen_by = np.zeros(n, np.int64), np.zeros(n, np.int64), []
    step = min(WAVE, max(1, SEEN // max(1, end)))
    table = np.empty(min(step, n) * end, bool)
    for lo in range(0, n, step):
        m = min(step, n - lo)
        table[:] = False
        pool, ids = far[lo : lo + m], at[lo : lo + m]
        r, c = np.nonzero(starts[lo : lo + m] >= 0)
        v = starts[lo : lo + m][r, c]
        place = r * end + v
        live, asked = np.arange(m), q[lo : lo + m]
        while True:
            table[place] = True
            ndc[lo : lo + m] += np.bincount(r, minlength=m)
            last = pool[:, -1].take(r)
            if near is not None:
                good = near(v, lo + r, last)
                r, v, last = r.take(good), v.take(good), last.take(good)
            d = measure(metric, x.take(v, 0), asked.take(r, 0))
            good = np.flatnonzero(d <= last)
            r, v, d, last = r.take(good), v.take(good), d.take(good), last.take(good)
            tied = d == last
            if tied.any():
                good = ~tied | (2 * v < ids[r, -1])
                r, v, d = r[good], v[good], d[good]
            _into(pool, ids, r, 2 * v, d, 2 * end + 1)
            opened = (ids[live] if len(live) < m else ids) & 1 == 0
            if width == 1:
                first = opened.argmax(axis=1)
                some = opened[np.arange(len(live)), first]
                mine, first = live[some], first[some]
                live = mine
            else:
                opened &= opened.cumsum(axis=1, dtype=np.int32) <= width
                some, first = np.nonzero(opened)
                mine = live[some]
                live = live[opened.any(axis=1)]
            if not len(live):
                break
            here = ids[mine, first]
            ids[mine, first] = here + 1
            here >>= 1
            hops[lo : lo + m] += np.bincount(mine, minlength=m)
            if visits:
                seen_by.append((lo + mine, here))
            r, v = links(here)
            place = mine.take(r) * end + v
            place = place[~table.take(place)]
            if width > 1 and len(place):
                place.sort()
                once = np.ones(len(place), bool)
                once[1:] = place[1:] != place[:-1]
                place = place[once]
            r = place // end
            v = place - r * end
    at >>= 1
    at[at == end] = -1
    return far, at, ndc, hops, tuple(np.concatenate(z) for z in zip(*seen_by, strict=True)) if seen_by else None


def nearby(x: np.ndarray, q: np.ndarray) -> Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray] | None:
    """A function of positions in ``x`` and ``q`` and bounds: which pairs may lie within them, by vectors in single precision; none
    where these are too large for it."""
    with np.errstate(over="ignore"):
        q = q.astype(np.float32)
        norm = max((np.einsum("rd,rd->r", z, z).max(initial=0) for z in (x, q)))
    if not norm < np.finfo(np.float32).max / 16:
        return None
    # What rounding and adding up may be off, of vectors as long as the longest.
    off = 16 * (x.shape[1] + 8) * (np.finfo(np.float32).eps * float(norm) + float(np.finfo(np.float32).tiny))

    def near(v: np.ndarray, r: np.ndarray, last: np.ndarray) -> np.ndarray:
        a = x.take(v, 0)
        a -= q.take(r, 0)
        with np.errstate(over="ignore"):
            return np.flatnonzero(np.einsum("rd,rd->r", a, a) <= last * last * (1 + 1e-12) + off)

    return near


def measure(metric: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """:func:`distance.rows` of rows that may be overwritten."""
    if metric not in ("l2", "l2sq"):
        return distance.rows(metric, b, a)
    a -= b
    a *= a
    d = np.add.reduce(a, 1)
    return np.sqrt(d, d) if metric == "l2" else d


def in_order(d: np.ndarray, v: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The first ``size`` of each row in order of distance and position."""
    order = np.argsort(d, axis=1)
    by = np.arange(len(d))[:, None] * d.shape[1]
    order += by
    d_ = d.take(order)
    same = d_[:, 1:] == d_[:, :-1]
    if same.any():
        same &= d_[:, 1:] < np.inf
        tied = np.flatnonzero(same.any(axis=1))
        if len(tied):
            order[tied] = np.lexsort((v[tied], d[tied]), axis=-1) + by[tied]
    return d_[:, :size], v.take(order[:, :size])


def _into(pool: np.ndarray, ids: np.ndarray, r: np.ndarray, v: np.ndarray, d: np.ndarray, none: int) -> None:
    """Put candidates, rows in order, into their pools; pools stay in order of distance and position, ``none`` in their free places."""
    if not len(r):
        return
    new = np.ones(len(r), bool)
    new[1:] = r[1:] != r[:-1]
    begins = np.flatnonzero(new)
    rows, to = r[begins], np.cumsum(new) - 1
    place = np.arange(len(r)) - begins[to]
    size, width = pool.shape[1], int(place.max()) + 1
    all_d, all_v = np.empty((len(rows), size + width)), np.empty((len(rows), size + width), np.int64)
    all_d[:, :size], all_v[:, :size] = pool.take(rows, 0), ids.take(rows, 0)
    # Places without a candidate look like free ones of the pool, since a sort may swap the two.
    all_d[:, size:], all_v[:, size:] = np.inf, none
    flat = to * (size + width) + size + place
    all_d.ravel()[flat], all_v.ravel()[flat] = d, v
    pool[rows], ids[rows] = in_order(all_d, all_v, size)


def resident(
    edges: DataFrame, vectors: DataFrame, queries: DataFrame, entries: DataFrame, pool: int, k: int, metric: str = "l2", spread: int | None = None, width: int = 1, tri: bool = False
) -> DataFrame:
    """Search the shard ``target`` of every query. ``vectors`` has ``part``, ``edges`` run inside parts, entries ``(index_id, ep)``.

    Result ``(q_id, index_id, rank, vec_id, dist, ndc, hops)``; without ``part`` all is one shard, 0. Queries with a column
    ``ep`` start there and not at their shard's entry. A pool that holds a whole shard finds all that its entry reaches, in
    order, so those vertices are listed once an entry and searched exactly. A shard is sent to ``spread`` tasks and its queries are dealt out to
    them, by default so many that all cores have work; a graph that outgrows a task is for :func:`frontier`. ``width`` and
    ``tri`` (l2 only): see :func:`beam`.
    """
    if k > pool:
        raise ValueError(f"the pool ({pool}) must not be smaller than k ({k})")
    distance.known(metric)
    if tri and metric != "l2":
        raise ValueError("the triangle inequality prunes l2 only")
    if spread is None:
        spread = max(1, -(-edges.sparkSession.sparkContext.defaultParallelism // max(1, entries.count())))
    v = vectors if "part" in vectors.columns else vectors.withColumn("part", F.lit(0))
    ask = queries if "target" in queries.columns else queries.withColumn("target", F.lit(0))
    far = F.col("dist") if tri else F.lit(0.0)
    lists = edges.groupBy("src").agg(F.collect_list(F.struct("dst", far.alias("dist"))).alias("to"))
    rows = v.join(lists, v["vec_id"] == lists["src"], "left").join(F.broadcast(entries.select("index_id", "ep")), F.col("part") == F.col("index_id"))
    to = F.coalesce("to", F.array().cast("array<struct<dst:bigint,dist:double>>"))
    lengths = [F.transform(to, lambda e: e.dist).alias("far")] if tri else []
    shard = rows.select(F.col("part").cast("int").alias("target"), F.explode(F.sequence(F.lit(0), F.lit(spread - 1))).alias("salt"), "vec_id", "x", F.transform(to, lambda e: e.dst).alias("to"), "ep", *lengths)
    own_entry = F.col("ep") if "ep" in ask.columns else F.lit(None)
    salt = F.pmod(F.xxhash64("vec_id"), F.lit(spread)).cast("int").alias("salt")
    ask = ask.select(F.col("target").cast("int").alias("target"), salt, F.col("vec_id").alias("q_id"), F.col("x").alias("qx"), own_entry.cast("long").alias("q_ep"))

    def run(graph: pa.Table, some: pa.Table) -> pa.Table:
        names = ["q_id", "index_id", "rank", "vec_id", "dist", "ndc", "hops"]
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int32())
        if not graph.num_rows or not some.num_rows:
            return pa.table({n: pa.array([], t) for n, t in zip(names, kinds, strict=True)})
        ids = graph.column("vec_id").to_numpy()
        lists = graph.column("to").combine_chunks()
        sizes = np.diff(lists.offsets.to_numpy())
        far = graph.column("far").combine_chunks().flatten().to_numpy() if tri else None
        own = Shard(ids, distance.matrix(graph.column("x")), np.repeat(ids, sizes), lists.flatten().to_numpy(), metric, far)
        entry = int(np.searchsorted(own.ids, graph.column("ep")[0].as_py()))
        target = graph.column("target")[0].as_py()
        if pool >= len(own.ids):
            starts = some.column("q_ep").fill_null(int(own.ids[entry])).to_numpy()
            return own.exhausted(some.column("q_id").to_numpy(), distance.matrix(some.column("qx")), np.searchsorted(own.ids, starts), k, target, list(zip(names, kinds, strict=True)))
        if not tri:
            q_id, starts = some.column("q_id").to_numpy(), some.column("q_ep").fill_null(int(own.ids[entry])).to_numpy()
            far, at, ndc, hops, _ = beams(own.x, own.links, distance.matrix(some.column("qx")), np.searchsorted(own.ids, starts)[:, None], pool, metric, width=width)
            r, c = np.nonzero(at[:, :k] >= 0)
            columns = [q_id[r], np.full(len(r), target), c + 1, own.ids[at[r, c]], far[r, c], ndc[r], hops[r]]
            return pa.table({n: pa.array(c, t) for n, c, t in zip(names, columns, kinds, strict=True)})
        out = []
        for q, x, start in zip(some.column("q_id").to_pylist(), distance.matrix(some.column("qx")), some.column("q_ep").to_pylist(), strict=True):
            found, ndc, hops = own.beam(x, entry if start is None else int(np.searchsorted(own.ids, start)), pool, width, tri)
            out += [(q, target, r + 1, int(own.ids[v]), d, ndc, hops) for r, (d, v) in enumerate(found[:k])]
        columns = list(zip(*out, strict=True)) or [[]] * 7
        return pa.table({n: pa.array(c, t) for n, c, t in zip(names, columns, kinds, strict=True)})

    return shard.groupBy("target", "salt").cogroup(ask.groupBy("target", "salt")).applyInArrow(run, RESULT)


def frontier(
    edges: DataFrame, vectors: DataFrame, queries: DataFrame, entries: DataFrame, pool: int, k: int, metric: str = "l2", max_rounds: int = 2000, width: int = 1
) -> DataFrame:
    """The same search as joins, so a graph may be larger than any task: a round joins all open vertices to their edges.

    ``entries`` has a row an index, ``(ep)`` or ``(index_id, ep)``; queries with ``target`` ask in that index, others in index 0.
    Every round is staged, the one before deleted.
    """
    if k > pool:
        raise ValueError(f"the pool ({pool}) must not be smaller than k ({k})")
    distance.known(metric)
    at_index = entries if "index_id" in entries.columns else entries.withColumn("index_id", F.lit(0))
    ask = queries if "target" in queries.columns else queries.withColumn("target", F.lit(0))
    packed = stage(edges.groupBy("src").agg(F.collect_list("dst").alias("to")), "adjacency")
    xs = vectors.select("vec_id", F.col("x").alias("y"))
    starts = at_index.select(F.col("index_id").cast("int").alias("target"), "ep").join(xs, F.col("ep") == F.col("vec_id")).select("target", "ep", "y")  # a row an index
    asked = ask.select(F.col("target").cast("int").alias("target"), F.col("vec_id").alias("q_id"), "x")
    first = distance.measured(asked.join(F.broadcast(starts), "target").select("q_id", "target", "ep", "x", "y"), "x", "y", metric=metric)
    item = F.struct(F.col("dist"), F.col("ep").alias("id"), F.lit(False).alias("done"))
    state = stage(first.select("q_id", "target", F.array(item).alias("pool"), F.array("ep").alias("seen"), F.lit(1).cast("long").alias("ndc"), F.lit(0).alias("hops")), "beam")
    asked = stage(asked, "beam-asked")
    for _ in range(max_rounds):
        opened = state.withColumn("at", F.transform(F.slice(F.filter("pool", lambda p: ~p.done), 1, width), lambda p: p.id))
        active = opened.where(F.size("at") > 0)
        if active.isEmpty():
            break
        met = active.select("q_id", "target", F.explode("at").alias("at"), "seen").join(packed, F.col("at") == F.col("src"))
        new = met.select("q_id", "target", F.explode(F.array_except("to", "seen")).alias("vec_id"))
        new = new.distinct() if width > 1 else new
        found = distance.measured(new.join(xs, "vec_id").join(asked, ["q_id", "target"]).select("q_id", "target", "vec_id", "x", "y"), "x", "y", metric=metric)
        gained = found.groupBy("q_id", "target").agg(F.collect_list(F.struct("dist", F.col("vec_id").alias("id"), F.lit(False).alias("done"))).alias("fresh"))
        both = opened.join(gained, ["q_id", "target"], "left")
        fresh = F.coalesce("fresh", F.array().cast("array<struct<dist:double,id:bigint,done:boolean>>"))
        marked = F.transform("pool", lambda p: F.struct(p.dist.alias("dist"), p.id.alias("id"), (p.done | F.array_contains("at", p.id)).alias("done")))
        nxt = both.select(
            "q_id", "target", F.slice(F.array_sort(F.concat(marked, fresh)), 1, pool).alias("pool"), F.concat("seen", F.transform(fresh, lambda p: p.id)).alias("seen"),
            (F.col("ndc") + F.size(fresh)).alias("ndc"), (F.col("hops") + F.size("at")).alias("hops"),
        )
        new_state = stage(nxt, "beam")
        drop(state)
        state = new_state
    drop(packed)
    drop(asked)
    out = state.select("q_id", "target", F.posexplode(F.slice("pool", 1, k)).alias("rank", "p"), "ndc", "hops")
    return out.select("q_id", F.col("target").alias("index_id"), (F.col("rank") + 1).alias("rank"), F.col("p.id").alias("vec_id"), F.col("p.dist").alias("dist"), "ndc", "hops")


def medoids(vectors: DataFrame, metric: str = "l2") -> DataFrame:
    """``(index_id, ep, ep_x)``: the vector nearest to each part's centroid, the lowest id on ties."""
    v = vectors if "part" in vectors.columns else vectors.withColumn("part", F.lit(0))
    centre = centroids(v)
    met = v.join(F.broadcast(centre), v["part"] == centre["index_id"])
    near = distance.measured(met.select("index_id", "vec_id", F.col("x").alias("ep_x"), "x", "centre"), "x", "centre", metric=metric)
    top = near.groupBy("index_id").agg(F.min(F.struct("dist", "vec_id", "ep_x")).alias("m"))
    return top.select("index_id", F.col("m.vec_id").alias("ep"), F.col("m.ep_x").alias("ep_x"))


def centroids(vectors: DataFrame) -> DataFrame:
    """``(index_id, centre)``: the mean vector of each part, by component."""
    flat = vectors.select(F.col("part").cast("int").alias("index_id"), F.posexplode("x").alias("pos", "c"))
    mean = flat.groupBy("index_id", "pos").agg(F.avg(F.col("c").cast("double")).alias("avg"))
    packed = mean.groupBy("index_id").agg(F.array_sort(F.collect_list(F.struct("pos", "avg"))).alias("s"))
    return packed.select("index_id", F.transform("s", lambda p: p.avg).alias("centre"))


def lowest(vectors: DataFrame) -> DataFrame:
    """Entries by the lowest id of each part."""
    v = vectors if "part" in vectors.columns else vectors.withColumn("part", F.lit(0))
    return v.groupBy(F.col("part").cast("int").alias("index_id")).agg(F.min(F.struct("vec_id", "x")).alias("m")).select("index_id", F.col("m.vec_id").alias("ep"), F.col("m.x").alias("ep_x"))


def scatter_gather(edges: DataFrame, vectors: DataFrame, queries: DataFrame, entries: DataFrame, pool: int, k: int, metric: str = "l2") -> DataFrame:
    """Every query on every index, the best k of all; ``ndc`` adds up over the indexes."""
    each = queries.select("vec_id", "x").join(F.broadcast(entries.select(F.col("index_id").alias("target"))), F.lit(True))
    found = resident(edges, vectors, each, entries, pool, k, metric)
    order = Window.partitionBy("q_id").orderBy("dist", "vec_id")
    cost = found.where("rank = 1").groupBy("q_id").agg(F.sum("ndc").alias("ndc"), F.sum("hops").cast("int").alias("hops"))
    top = found.drop("ndc", "hops", "rank").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return top.join(cost, "q_id").select("q_id", "index_id", "rank", "vec_id", "dist", "ndc", "hops")
