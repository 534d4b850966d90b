"""Index builders: one shard a task, with NumPy kernels. Each gives ``(index_id, layer, src, dst, dist)``.

A builder acquires candidates and selects neighbours. Kernels work on positions inside the shard, in order of id.
"""

from __future__ import annotations

import math
from bisect import insort
from collections.abc import Callable, Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardweave.functions import distance
from shardweave.operators import exact, refine, thin
from shardweave.operators.search import beam, beams, in_order, measure, nearby

#: Lists up to this length are pruned with all distances inside them at once, pairs measured at a time by local joins.
SHORT, PAIRS = 40, 1 << 14
#: So many times as many pairs may be offered at a time before those that meet twice are told apart.
OFFERS = 1 << 7
EDGES = "index_id int, layer int, src long, dst long, dist double, ndc long"


class Net:
    """A growing graph: vectors, neighbour lists, distances counted."""

    def __init__(self, x: np.ndarray, metric: str = "l2"):
        self.x, self.metric, self.to, self.ndc = x, metric, {}, 0
        self._single: np.ndarray | None = None

    @property
    def single(self) -> np.ndarray:
        """The vectors in single precision, for what need not be exact."""
        if self._single is None:
            with np.errstate(over="ignore"):
                self._single = self.x.astype(np.float32)
        return self._single

    def dist(self, a: int, others: list[int]) -> np.ndarray:
        self.ndc += len(others)
        return distance.to_row(self.metric, self.x[a])(self.x[others])

    def search(self, q: int, entries: list[int], size: int, visited: list | None = None) -> list[tuple[float, int]]:
        to = self.to
        pool, ndc, _ = beam(self.x, lambda v: to.get(v, ()), self.x[q], entries, size, self.metric, visited)
        self.ndc += ndc
        return pool

    def prune(self, near: list[tuple[float, int]], cap: int, rule: str = "kept", alpha: float = 1.0, tau: float = 0.0) -> list[int]:
        """Neighbours of a sorted candidate list that a rule keeps."""
        near = list(dict.fromkeys(near))
        if len(near) <= 1:
            return [v for _, v in near]
        ids, far = [v for _, v in near], np.array([w for w, _ in near])
        x = self.x[ids]
        kept: list[int] = []
        # A scan compares with the kept ones until one hides the candidate; only those distances count.
        if len(ids) <= SHORT:
            hides = thin.occluded(far, distance.rows(self.metric, x[:, None, :], x[None, :, :]), rule, alpha, tau).tolist()
            for v in range(len(ids)):
                if len(kept) >= cap:
                    break
                by = next((j for j, w in enumerate(kept) if hides[w][v]), -1)
                self.ndc += len(kept) if by < 0 else by + 1
                if by < 0:
                    kept.append(v)
            return [ids[v] for v in kept]
        # Of a long list only the kept ones' rows are measured, when they are kept.
        by = np.full(len(ids), -1)
        for v in range(len(ids)):
            if len(kept) >= cap:
                break
            if by[v] >= 0:
                self.ndc += int(by[v]) + 1
                continue
            self.ndc += len(kept)
            hides = thin.occluded(far[v:], distance.to_row(self.metric, x[v])(x[v:].copy())[None, :], rule, alpha, tau, far[v : v + 1])[0]
            later = by[v:]
            later[hides & (later < 0)] = len(kept)
            kept.append(v)
        return [ids[v] for v in kept]

    def sorted(self, a: int, others) -> list[tuple[float, int]]:
        others = [o for o in dict.fromkeys(others) if o != a]
        return sorted(zip(self.dist(a, others).tolist(), others, strict=True)) if others else []


def mixed(n: int, seed: int) -> np.ndarray:
    """A fixed permutation of n positions."""
    return np.random.default_rng(seed).permutation(n)


def medoid(x: np.ndarray) -> int:
    return int(((x - x.mean(axis=0)) ** 2).sum(axis=1).argmin()) if len(x) else 0


def _random(net: Net, degree: int, seed: int = 1) -> dict[int, list[int]]:
    n = len(net.x)
    rng = np.random.default_rng(seed)
    return {v: [int(u) for u in rng.choice(n, min(n, degree + 1), replace=False) if u != v][:degree] for v in range(n)}


def insert_flat(net: Net, v: int, m: int, ef: int, entry: int = 0) -> None:
    """Link a vertex both ways to the m best that a search finds; no pruning, reverse degrees grow freely."""
    if net.to:
        for _, u in net.search(v, [entry], max(ef, m))[:m]:
            net.to.setdefault(v, []).append(u)
            net.to[u].append(v)
    net.to.setdefault(v, [])


def nsw(net: Net, m: int = 16, ef: int = 200, **_) -> dict[int, dict[int, list[int]]]:
    for v in range(len(net.x)):
        insert_flat(net, v, m, ef)
    return {0: net.to}


class Layered:
    """A layered graph under insertion; ``wide``: the lowest layer holds twice as many edges a vertex."""

    def __init__(self, net: Net, m: int, ef: int, seed: int, wide: bool = True):
        self.net, self.m, self.ef, self.wide = net, m, ef, wide
        self.levels = np.floor(-np.log(np.random.default_rng(seed).uniform(1e-12, 1, len(net.x))) / math.log(m)).astype(int)
        self.layers: dict[int, dict[int, list[int]]] = {0: {}}
        self.lists: list[Lists] = []
        self.entry, self.top, self.size = -1, -1, 0

    def grow(self, order: list[int] | np.ndarray, ef: int | None = None) -> None:
        """Insert vertices in turn: one by one into a small graph, then batches of a fiftieth of the graph as it is by then, which
        don't see each other's edges. A vertex above all layers goes alone."""
        order, at = np.asarray(order, np.int64), 0
        while at < len(order):
            step = min(BATCH, 2 * (self.size // SHARE))
            if step < 2 * LEAST and not self.lists:
                self.insert(int(order[at]), ef)
                at += 1
                continue
            some = order[at : at + max(1, step)]
            above = np.flatnonzero(self.levels[some] > self.top)
            some = some[: max(1, int(above[0]))] if len(above) else some
            self.insert_many(some, ef)
            at += len(some)

    def insert_many(self, some: np.ndarray, ef: int | None = None) -> None:
        """:meth:`insert` of several vertices on the graph as it stands; of several only if none is above all layers."""
        net, levels = self.net, self.levels[some]
        if not self.lists:
            self.lists = [self._layer(at) for at in range(self.top + 1)]
            for at, to in self.layers.items():
                for v, us in to.items():
                    self.lists[at].to[v, : len(us)] = us
        starts = np.full((len(some), 1), self.entry)
        for layer in range(self.top, -1, -1):
            here, links = self.lists[layer], levels >= layer
            after = np.full((len(some), (ef or self.ef) if links.any() else 1), -1, np.int64)
            for mine, size in ((np.flatnonzero(~links), 1), (np.flatnonzero(links), ef or self.ef)):
                if not len(mine):
                    continue
                far, ids, ndc, _, _ = beams(net.x, here.links, net.x[some[mine]], starts[mine], size, net.metric, width=min(WIDTH, size), single=net.single)
                net.ndc += int(ndc.sum())
                after[mine, :size] = ids
                if size > 1 or links[mine[0]]:
                    here.to[some[mine]] = here.rows(*np.nonzero(prune_many(net, ids, far, self.m)), ids, len(mine))
                    here.tell(some[mine], "kept", 1.0)
            starts = after
        self.size += len(some)
        if levels[0] > self.top:
            self.entry, self.top = int(some[0]), int(levels[0])
            self.lists += [self._layer(at) for at in range(len(self.lists), self.top + 1)]

    def _layer(self, at: int) -> Lists:
        return Lists(self.net, self.m * (2 if at == 0 and self.wide else 1))

    def built(self) -> dict[int, dict[int, list[int]]]:
        """The neighbours by layer."""
        if not self.lists:
            return self.layers
        return {at: {v: row[row >= 0].tolist() for v, row in enumerate(here.to) if self.levels[v] >= at} for at, here in enumerate(self.lists)}

    def insert(self, v: int, ef: int | None = None) -> None:
        net, level = self.net, int(self.levels[v])
        self.size += 1
        for at in range(level + 1):
            self.layers.setdefault(at, {})[v] = []
        if self.entry < 0:
            self.entry, self.top = v, level
            return
        at = [self.entry]
        for layer in range(self.top, level, -1):
            net.to = self.layers[layer]
            at = [net.search(v, at, 1)[0][1]]
        for layer in range(min(self.top, level), -1, -1):
            net.to = self.layers[layer]
            found = [p for p in net.search(v, at, ef or self.ef) if p[1] != v]
            cap = self.m * (2 if layer == 0 and self.wide else 1)
            net.to[v] = net.prune(found, self.m)
            for u in net.to[v]:
                net.to[u].append(v)
                if len(net.to[u]) > cap:
                    net.to[u] = net.prune(net.sorted(u, net.to[u]), cap)
            at = [p[1] for p in found] or at
        if level > self.top:
            self.entry, self.top = v, level


def hnsw(net: Net, m: int = 16, ef: int = 200, seed: int = 1, **_) -> dict[int, dict[int, list[int]]]:
    graph = Layered(net, m, ef, seed)
    graph.grow(np.arange(len(net.x)))
    return graph.built()


def refit(net: Net, v: int, entry: int, degree: int, size: int, alpha: float) -> None:
    """Search a vertex, prune what was visited with its own list, and hand it to its neighbours, who prune on overflow."""
    visited: list[tuple[float, int]] = []
    net.search(v, [entry], size, visited)
    near = net.sorted(v, [u for _, u in visited] + net.to.get(v, []))
    net.to[v] = net.prune(near, degree, "alpha", alpha)
    for u in net.to[v]:
        own = net.to.setdefault(u, [])
        if v not in own:
            own.append(v)
            if len(own) > degree:
                net.to[u] = net.prune(net.sorted(u, own), degree, "alpha", alpha)


#: Numbers in the vectors of a block of lists that are pruned at a time.
BLOCK = 1 << 21
#: Lists longer than so many times what is kept of them have only the kept ones' products made.
LONG = 8


def prune_many(net: Net, ids: np.ndarray, far: np.ndarray, cap: int, rule: str = "kept", alpha: float = 1.0, tau: float = 0.0) -> np.ndarray:
    """:meth:`Net.prune` of many lists, rows of positions (-1: none) in order of distance: which are kept."""
    kept = np.zeros(ids.shape, bool)
    step = max(1, BLOCK // max(1, ids.shape[1] * net.x.shape[1]))
    for lo in range(0, len(ids), step):
        some = slice(lo, lo + step)
        kept[some] = _scan(net, ids[some], far[some], cap, rule, alpha, tau)
    return kept


def _scan(net: Net, ids: np.ndarray, far: np.ndarray, cap: int, rule: str, alpha: float, tau: float) -> np.ndarray:
    kept, by, n_kept = np.zeros(ids.shape, bool), np.full(ids.shape, -1, np.int32), np.zeros(len(ids), np.int32)
    real = ids >= 0
    rough = _rough(net, ids, far, cap, rule, alpha, tau) if net.metric == "l2" else None
    for v in range(ids.shape[1]):
        asked = real[:, v] & (n_kept < cap)
        net.ndc += int(np.where(by[:, v] >= 0, by[:, v] + 1, n_kept)[asked].sum())
        new = np.flatnonzero(asked & (by[:, v] < 0))
        if not len(new):
            continue
        kept[new, v] = True
        # Only what nothing hides yet is compared with the row just kept.
        left = (by[new, v + 1 :] < 0) & real[new, v + 1 :]
        if rough is not None:
            sure, may = rough(new, v)
            may &= left
            r, c = np.nonzero(may & ~sure)
            sure &= may
            r, c = new[r], v + 1 + c
        else:
            r, c = np.nonzero(left)
            r, c = new[r], v + 1 + c
        d = distance.rows(net.metric, net.x[ids[r, v]], net.x[ids[r, c]])
        hides = thin.occluded(far[r, c][:, None], d[:, None, None], rule, alpha, tau, far[r, v][:, None])[:, 0, 0]
        by[r[hides], c[hides]] = n_kept[r[hides]]
        if rough is not None:
            r, c = np.nonzero(sure)
            by[new[r], v + 1 + c] = n_kept[new[r]]
        n_kept[new] += 1
    return kept


def _rough(net: Net, ids: np.ndarray, far: np.ndarray, cap: int, rule: str, alpha: float, tau: float) -> Callable[[np.ndarray, int], tuple[np.ndarray, np.ndarray]]:
    """A function of lists and a place that says which later places this one hides for sure, and which it may hide: squares from
    inner products of rounded vectors, and how far those may be off."""
    x = net.single.take(ids, 0, mode="wrap")
    norm = np.einsum("rcd,rcd->rc", x, x)
    if not np.isfinite(norm).all():
        x = net.x.take(ids, 0, mode="wrap")
        norm = np.einsum("rcd,rcd->rc", x, x)
    eps, least = np.finfo(x.dtype).eps, np.finfo(x.dtype).tiny
    bound = {"alpha": far / alpha, "tau": far - 3 * tau}.get(rule, far)
    most = np.where((ids >= 0) & (bound >= 0), bound * bound, -np.inf)
    off = 16 * (x.shape[2] + 8) * (eps * norm.max(axis=1, initial=0)[:, None].astype(float) + least) + max(1e-12, 8 * eps) * np.where(np.isinf(most), 0, most)
    under, over = (most - off).astype(x.dtype), (most + off).astype(x.dtype)

    # Few rows of a long list are kept.
    every = x @ x.transpose(0, 2, 1) if ids.shape[1] <= LONG * cap else None

    def near(some: np.ndarray, v: int) -> tuple[np.ndarray, np.ndarray]:
        square = every[some, v, v + 1 :] if every is not None else np.einsum("rcd,rd->rc", x[some, v + 1 :], x[some, v])
        square *= -2
        square += norm[some, v + 1 :]
        square += norm[some, v][:, None]
        sure, may = square < under[some, v + 1 :], square <= over[some, v + 1 :]
        if rule in ("tau", "lune"):
            closer = far[some, v][:, None] < far[some, v + 1 :]
            sure &= closer
            may &= closer
        return sure, may

    return near


class Lists:
    """Neighbour lists of bounded length as one array, changed many at a time."""

    def __init__(self, net: Net, width: int):
        self.net, self.to = net, np.full((len(net.x), width), -1, np.int64)

    def links(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        near = self.to[at]
        r, c = np.nonzero(near >= 0)
        return r, near[r, c]

    def pruned(self, r: np.ndarray, v: np.ndarray, own: np.ndarray, rule: str, alpha: float) -> np.ndarray:
        """Rows of neighbours that a rule keeps of the candidates ``v`` of rows ``r``, whose vertices are ``own``."""
        far, ids = self.ranked(r, v, own)
        return self.rows(*np.nonzero(prune_many(self.net, ids, far, self.to.shape[1], rule, alpha)), ids, len(own))

    def ranked(self, r: np.ndarray, v: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """:meth:`Net.sorted` of the candidates ``v`` of rows ``r``, whose vertices are ``own``: distances and positions, rows filled up
        with infinity and -1."""
        n = len(self.net.x)
        code = np.sort(r * n + v)
        once = np.ones(len(code), bool)
        once[1:] = code[1:] != code[:-1]
        r, v = np.divmod(code[once], n)
        other = v != own[r]
        r, v = r[other], v[other]
        self.net.ndc += len(r)
        d = measure(self.net.metric, self.net.x.take(own.take(r), 0), self.net.x.take(v, 0))
        at = np.arange(len(r)) - np.searchsorted(r, np.arange(len(own))).take(r)
        ids, far = np.full((len(own), at.max(initial=-1) + 1), -1, np.int64), np.full((len(own), at.max(initial=-1) + 1), np.inf)
        ids[r, at], far[r, at] = v, d
        return in_order(far, ids, ids.shape[1])

    def rows(self, r: np.ndarray, c: np.ndarray, ids: np.ndarray, n: int) -> np.ndarray:
        out = np.full((n, self.to.shape[1]), -1, np.int64)
        out[r, np.arange(len(r)) - np.searchsorted(r, r)] = ids[r, c]
        return out

    def refit(self, some: np.ndarray, entry: int, size: int, alpha: float) -> None:
        """:func:`refit` of several vertices on the graph as it stands; then their neighbours take them and prune on overflow."""
        found = beams(self.net.x, self.links, self.net.x[some], np.full((len(some), 1), entry), size, self.net.metric, True, 1 if len(some) == 1 else WIDTH, self.net.single)
        self.net.ndc += int(found[2].sum())
        r, v = self.links(some)
        self.to[some] = self.pruned(np.concatenate((found[4][0], r)), np.concatenate((found[4][1], v)), some, "alpha", alpha)
        self.tell(some, "alpha", alpha)

    def tell(self, some: np.ndarray, rule: str, alpha: float) -> None:
        """The neighbours of vertices take them into their own lists and prune on overflow."""
        r, u = self.links(some)
        v = some[r]
        new = (self.to[u] != v[:, None]).all(axis=1)
        order = np.lexsort((v[new], u[new]))
        u, v = u[new][order], v[new][order]
        at, begins, counts = np.unique(u, return_index=True, return_counts=True)
        held = (self.to[at] >= 0).sum(axis=1)
        full = held + counts > self.to.shape[1]
        row = np.repeat(np.arange(len(at)), counts)
        place = held[row] + np.arange(len(u)) - np.repeat(begins, counts)
        fits = ~full[row]
        self.to[u[fits], place[fits]] = v[fits]
        own = at[full]
        if len(own):
            which = np.cumsum(full) - 1
            r, w = self.links(own)
            self.to[own] = self.pruned(np.concatenate((r, which[row[~fits]])), np.concatenate((w, v[~fits])), own, rule, alpha)


#: Batches of a builder hold one of so many vertices; bounds of a batch, below the first of which vertices go one at a time.
SHARE, LEAST, BATCH = 100, 16, 512
#: Vertices that a search of a batch expands at a time.
WIDTH = 4


def vamana(net: Net, degree: int = 16, size: int = 50, alpha: float = 1.2, seed: int = 1, **_) -> dict[int, dict[int, list[int]]]:
    """Two passes of :func:`refit` over a random graph, in batches of a hundredth of the vertices, which don't see each other's new edges;
    small graphs one by one."""
    step = min(BATCH, len(net.x) // SHARE)
    if step < LEAST:
        net.to = _random(net, degree, seed)
        entry = medoid(net.x)
        for a in (1.0, alpha):
            for v in mixed(len(net.x), seed).tolist():
                refit(net, v, entry, degree, size, a)
        return {0: net.to}
    lists = Lists(net, degree)
    for v, us in _random(net, degree, seed).items():
        lists.to[v, : len(us)] = us
    entry = medoid(net.x)
    for a in (1.0, alpha):
        order = mixed(len(net.x), seed)
        for at in range(0, len(order), step):
            lists.refit(order[at : at + step], entry, size, a)
    net.to = {v: row[row >= 0].tolist() for v, row in enumerate(lists.to)}
    return {0: net.to}


def nn_descent(net: Net, k: int = 16, rounds: int = 12, sample: float = 1.0, stop: float = 0.001, seed: int = 1, **_) -> dict[int, dict[int, list[int]]]:
    """Local joins of new with new and old members, forward and reverse, of all origins."""
    n = len(net.x)
    rng = np.random.default_rng(seed)
    lists = {v: net.sorted(v, us) for v, us in _random(net, k, seed).items()}
    size = len(lists[0]) if n else 0
    if not size:
        net.to = {v: [] for v in range(n)}
        return {0: net.to}
    far, to, fresh = np.array([[d for d, _ in own] for own in lists.values()]), np.array([[u for _, u in own] for own in lists.values()]), np.ones((n, size), bool)
    rows = np.repeat(np.arange(n), size).reshape(n, size)
    near = nearby(net.single, net.x) if net.metric == "l2" else None
    for _turn in range(rounds):
        picked = fresh & (rng.random(fresh.shape) <= sample)
        # What is new and not picked waits, on neither side.
        joins = picked | ~fresh
        pools = _both_ways(rows[joins], to[joins], picked[joins], n)
        fresh &= ~picked
        held, changed = np.sort((np.arange(n)[:, None] * n + to).ravel()), 0
        for offered in _offered(*pools, n):
            net.ndc += len(offered)
            changed += _take(net, offered, held, far, to, fresh, near)
        if changed <= stop * n * k:
            break
    net.to = dict(enumerate(to.tolist()))
    return {0: net.to}


def _both_ways(a: np.ndarray, b: np.ndarray, new: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct partners of each of n vertices in pairs, in order: ``(vertex, partner, is new)``, new if one of its pairs is."""
    code = np.concatenate((a * n + b, b * n + a))
    code += code
    code += ~np.concatenate((new, new))
    code.sort()
    once = np.ones(len(code), bool)
    once[1:] = code[1:] >> 1 != code[:-1] >> 1
    code = code[once]
    return *np.divmod(code >> 1, n), code & 1 == 0


def _offered(pivot: np.ndarray, member: np.ndarray, new: np.ndarray, n: int) -> Iterator[np.ndarray]:
    """The distinct pairs of a vertex's members of which one is new, as ``smaller * n + larger`` in order; so many smaller ends at a
    time as make a bounded number of pairs."""
    # Each meets those behind it in its pool.
    behind = np.searchsorted(pivot, pivot, "right") - np.arange(len(pivot)) - 1
    order = np.argsort(member, kind="stable")
    first = np.searchsorted(member[order], np.arange(n + 1))
    total = np.concatenate(([0], np.cumsum(behind[order])))[first]
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + OFFERS * PAIRS, "right")) - 1)
        some = order[first[lo] : first[hi]]
        lo = hi
        sizes = behind[some]
        ends = np.cumsum(sizes)
        if not len(ends) or not ends[-1]:
            continue
        one = np.repeat(some, sizes)
        other = np.arange(ends[-1]) - np.repeat(ends - sizes - some - 1, sizes)
        met = np.flatnonzero(new.take(one) | new.take(other))
        code = member.take(one.take(met))
        code *= n
        code += member.take(other.take(met))
        code.sort()
        once = np.ones(len(code), bool)
        once[1:] = code[1:] != code[:-1]
        if len(code):
            yield code[once]


def _take(net: Net, offered: np.ndarray, held: np.ndarray, far: np.ndarray, to: np.ndarray, fresh: np.ndarray, near: Callable | None) -> int:
    """Put offered pairs into the lists of both ends, each list's offers in order of id; how many went in, if only for a while.
    ``held`` are the pairs that the lists began with. Offers in order go in some blocks at a time, so few of them wait. ``near`` tells
    which pairs may lie within a bound; only these are measured in full."""
    n = len(to)
    good, waiting, changed = [], 0, 0
    for at in range(0, len(offered), PAIRS):
        a, b = np.divmod(offered[at : at + PAIRS], n)
        if near is not None:
            some = near(b, a, np.maximum(far[a, -1], far[b, -1]))
            a, b = a[some], b[some]
        d = distance.rows(net.metric, net.x[a], net.x[b])
        inside = held[np.minimum(np.searchsorted(held, a * n + b), len(held) - 1)] == a * n + b
        turned = held[np.minimum(np.searchsorted(held, b * n + a), len(held) - 1)] == b * n + a
        for s, t, known in ((a, b, inside), (b, a, turned)):
            # An offer behind the last of a list stays behind it.
            some = ~known & ((d < far[s, -1]) | ((d == far[s, -1]) & (t < to[s, -1])))
            good.append((s[some], t[some], d[some]))
            waiting += len(good[-1][0])
        if waiting >= 32 * PAIRS or at + PAIRS >= len(offered):
            changed += _put(good, far, to, fresh)
            good, waiting = [], 0
    return changed


def _put(good: list[tuple[np.ndarray, np.ndarray, np.ndarray]], far: np.ndarray, to: np.ndarray, fresh: np.ndarray) -> int:
    s, t, d = (np.concatenate(z) for z in zip(*good, strict=True))
    if not len(s):
        return 0
    order = np.lexsort((t, s))
    s, t, d = s[order], t[order], d[order]
    changed = 0
    begins = np.flatnonzero(np.diff(s, prepend=-1))
    for lo, hi in zip(begins.tolist(), [*begins[1:].tolist(), len(s)], strict=True):
        v = int(s[lo])
        own = list(zip(far[v].tolist(), to[v].tolist(), fresh[v].tolist(), strict=True))
        for offer in zip(d[lo:hi].tolist(), t[lo:hi].tolist(), repeat(True)):
            if offer < own[-1]:
                own.pop()
                insort(own, offer)
                changed += 1
        far[v], to[v], fresh[v] = zip(*own, strict=True)
    return changed


def nsg(net: Net, degree: int = 16, size: int = 50, k: int = 24, seed: int = 1, **_) -> dict[int, dict[int, list[int]]]:
    """Candidates are the visited of a search from the medoid on a neighbour graph; unreached vertices are attached."""
    nn_descent(net, k, seed=seed)
    base, entry, out = net.to, medoid(net.x), {}
    for v in range(len(net.x)):
        net.to = base
        visited: list[tuple[float, int]] = []
        net.search(v, [entry], size, visited)
        out[v] = net.prune(net.sorted(v, [u for _, u in visited] + base[v]), degree)
    net.to = {v: list(us) for v, us in out.items()}
    for v, us in out.items():
        for u in us:
            if v not in net.to[u]:
                net.to[u].append(v)
                if len(net.to[u]) > degree:
                    net.to[u] = net.prune(net.sorted(u, net.to[u]), degree)
    reached, front = {entry}, [entry]
    while len(reached) < len(net.x):
        while front:
            front = [u for v in front for u in net.to[v] if u not in reached and not reached.add(u)]
        left = next((v for v in range(len(net.x)) if v not in reached), None)
        if left is None:
            break
        near = net.search(left, [entry], size)[0][1]
        net.to[near].append(left)
        reached.add(left)
        front = [left]
    return {0: net.to}


#: Vertices whose candidates a builder holds at a time.
HELD = 4096


def tau_graph(net: Net, degree: int = 16, size: int = 50, h: int = 50, tau: float = 0.01, seed: int = 1, **_) -> dict[int, dict[int, list[int]]]:
    """From a neighbour graph: candidates by search, the tau rule, candidates within three tau stay, reverse edges."""
    n = len(net.x)
    nn_descent(net, min(degree, max(1, n - 1)), seed=seed)
    base, entry, out = Lists(net, degree), medoid(net.x), np.full((n, degree), -1, np.int64)
    for v, us in net.to.items():
        base.to[v, : len(us)] = us
    # No search sees what another one finds, so they run in step.
    for lo in range(0, n, HELD):
        some = np.arange(lo, min(lo + HELD, n))
        _, found, ndc, _, _ = beams(net.x, base.links, net.x[some], np.full((len(some), 1), entry), max(size, h), net.metric, single=net.single)
        net.ndc += int(ndc.sum())
        r, c = np.nonzero(found[:, :h] >= 0)
        s, u = base.links(some)
        far, ids = base.ranked(np.concatenate((r, s)), np.concatenate((found[r, c], u)), some)
        stays = prune_many(net, ids, far, degree, "tau", tau=tau) | ((ids >= 0) & (far <= 3 * tau))
        out[some] = base.rows(*np.nonzero(stays & (stays.cumsum(axis=1) <= degree)), ids, len(some))
    # A vertex is taken up by those it points to in order of position, while they have less than twice the degree.
    v, c = np.nonzero(out >= 0)
    u = out[v, c]
    new = ~np.isin(u * n + v, v * n + u)
    u, v = u[new], v[new]
    order = np.lexsort((v, u))
    u, v = u[order], v[order]
    begins = np.searchsorted(u, np.arange(n + 1))
    more = np.minimum(begins[1:] - begins[:-1], 2 * degree - (out >= 0).sum(axis=1)).tolist()
    net.to = {at: row[row >= 0].tolist() + v[lo : lo + m].tolist() for at, (row, lo, m) in enumerate(zip(out, begins.tolist(), more))}
    return {0: net.to}


KERNELS: dict[str, Callable[..., dict[int, dict[int, list[int]]]]] = {
    "nsw": nsw, "hnsw": hnsw, "vamana": vamana, "nn_descent": nn_descent, "nsg": nsg, "tau_graph": tau_graph,
    "random": lambda net, degree=16, seed=1, **_: {0: _random(net, degree, seed)},
}


def packed(net: Net, ids: np.ndarray, layers: dict[int, dict[int, list[int]]], index: int) -> pa.Table:
    """A kernel's graph as edge rows; the distances evaluated stand on the first row."""
    src, dst, at = [], [], []
    for layer, to in layers.items():
        for v, us in to.items():
            us = [u for u in dict.fromkeys(us) if u != v]
            src += [v] * len(us)
            dst += us
            at += [layer] * len(us)
    a, b = np.array(src, int), np.array(dst, int)
    d = distance.rows(net.metric, net.x[a], net.x[b]) if len(a) else np.zeros(0)
    cost = np.zeros(len(a), np.int64)
    if len(a):
        cost[0] = net.ndc
    return pa.table({
        "index_id": pa.array(np.full(len(a), index, np.int32)), "layer": pa.array(np.array(at, np.int32)), "src": pa.array(ids[a].astype(np.int64) if len(a) else np.zeros(0, np.int64)),
        "dst": pa.array(ids[b].astype(np.int64) if len(b) else np.zeros(0, np.int64)), "dist": pa.array(d), "ndc": pa.array(cost),
    })


def shard_arrays(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    ids = t.column("vec_id").to_numpy()
    order = np.argsort(ids, kind="stable")
    return ids[order], distance.matrix(t.column("x"))[order]


def build(vectors: DataFrame, kind: str, metric: str = "l2", **how) -> DataFrame:
    """An index of each part by a named kernel; ``exact`` is the exact neighbour graph (``k``) in DataFrame form."""
    v = vectors if "part" in vectors.columns else vectors.withColumn("part", F.lit(0))
    if kind == "exact":
        near = exact.graph(v, how.get("k", 16), metric, scope="same").join(v.select(F.col("vec_id").alias("src"), "part"), "src")
        return near.select(F.col("part").cast("int").alias("index_id"), F.lit(0).alias("layer"), "src", "dst", "dist", F.lit(0).cast("long").alias("ndc"))
    if kind not in KERNELS:
        raise ValueError(f"no builder {kind!r}; there are {sorted([*KERNELS, 'exact'])}")
    kernel = KERNELS[kind]

    def run(t: pa.Table) -> pa.Table:
        out, part = [], t.column("part").to_numpy()
        for p in np.unique(part).tolist():
            ids, x = shard_arrays(t.filter(pa.array(part == p)))
            net = Net(x, metric)
            out.append(packed(net, ids, kernel(net, **how), p))
        return pa.concat_tables(out)

    # Parts meet in a task only where there are more of them than tasks.
    labels = refine.even_labels(v.sparkSession, int(v.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    task = F.array(*map(F.lit, labels))[F.pmod(F.col("part"), F.lit(len(labels)))].alias("task")
    return v.select(F.col("part").cast("int").alias("part"), "vec_id", "x").select("part", "vec_id", "x", task).groupBy("task").applyInArrow(run, EDGES)
