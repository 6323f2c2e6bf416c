"""Graph builders for one shard, over places 0 .. n-1 in order of id.

Every builder is deterministic: orders and random choices come from hashes of
places, and ties go to the smaller place.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import cached_property

import numpy as np

from annspark.functions.balls import FEW_COMPONENTS, Balls, Near
from annspark.functions.beam import beam_search, padded
from annspark.functions.metric import Metric
from annspark.functions.rules import Rule, ScaledBall, ScaledShiftedBall, ShiftedBall, UnitBall
from annspark.functions.select import Selection, adaptive_many, adaptive_select, fixed_select, select_many, select_neighbors


@dataclass(frozen=True)
class Params:
    """Construction parameters: K-NN degree, degree cap, queue width, candidates, alpha range, tau; and the insertion baselines' own.

    ``start`` is the place from which the entry is searched, a hashed one if
    none; ``backward`` (lazy, eager, none) takes the place of a method's own way.
    """

    K: int = 40
    M: int = 32
    L: int = 40
    C: int = 200
    alpha0: float = 0.9
    alpha_step: float = 0.05
    alpha_max: float = 1.6
    alpha: float = 1.1
    tau: float = 0.0
    include_knn: bool = True
    backward_cap: int | None = None
    seed: int = 1
    reuse: bool = True
    hnsw_m: int = 32
    hnsw_ef: int = 500
    vamana_m: int = 70
    vamana_l: int = 75
    vamana_alpha: float = 1.2
    start: int | None = None
    backward: str | None = None


# The published settings, by degree cap. The baselines' own are the defaults above.
PRESETS = {
    "degree_50": Params(K=200, M=50, L=40, C=500),
    "degree_70": Params(K=200, M=70, L=60, C=500),
    "degree_100": Params(K=200, M=100, L=100, C=500),
    "degree_80_large": Params(K=200, M=80, L=100, C=500, alpha0=1.0),
}
#: Points up to which a shard's K-NN graph is exact; beyond, it is refined from projections.
EXACT_POINTS = 20_000
#: Points that an insertion baseline searches for together, at most a part of those already in.
BATCH, BATCH_SHARE = 256, 8


@dataclass
class Graph:
    """Out-neighbours by vertex with distances, and what the build did."""

    neighbors: list[list[int]]
    dists: list[list[float]]
    entry: int
    log: list[Selection] = field(default_factory=list)
    selections: int = 0
    repairs: list[tuple[int, int]] = field(default_factory=list)
    #: Upper layers of the layered baseline, lowest first: vertex -> neighbours.
    layers: list[dict[int, list[int]]] = field(default_factory=list)

    def adjacency(self) -> np.ndarray:
        return padded(self.neighbors)


def replace_knn(p: Params) -> Params:
    """The same parameters with candidates from the search alone."""
    return replace(p, include_knn=False)


def mix(i: np.ndarray | int, seed: int) -> np.ndarray:
    """A well-mixed unsigned 64-bit value for each integer."""
    z = np.asarray(i, np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x9E3779B97F4A7C15) & (2**64 - 1))
    with np.errstate(over="ignore"):
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


class FullRows:
    """The ordered filter of any point over all others, without distances to candidates that are surely dropped.

    The nearest candidates are filtered exactly, a few at a time; of the rest, a matrix product in single precision
    drops those whose least distance to the newly kept lies in the rule's ball by more than the product's error, and
    what is within that error is measured again. So kept sets are those of ``select_neighbors`` over all candidates.
    Where many others are too near to be dropped by anything, rows of few components are in balls, and those of a ball
    that is dropped as a whole are not looked at.
    """

    FIRST, MOST, BALLS, OPENED, DENSE = 16, 256, 8, 16, 64

    def __init__(self, x: np.ndarray, rule: Rule, metric: Metric = Metric()):
        self.x, self.rule, self.metric = x, rule, metric
        centred = x - x.mean(axis=0)
        scale = float(np.einsum("ij,ij->i", centred, centred).max(initial=0.0))
        #: Single precision holds neither very large nor very small squares; a scale near 1 does not matter to it.
        unit = math.sqrt(scale) if 0 < scale < np.inf else 1.0
        self.unit, self.low = unit, np.ascontiguousarray(centred / unit, np.float32)
        self.squares = np.einsum("ij,ij->i", self.low, self.low)
        self.slack = 16 * (x.shape[1] + 8) * 6e-8
        self.few = metric.name == "l2" and 0 < x.shape[1] <= FEW_COMPONENTS

    def _bounds(self, coarse: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distances that the true one lies between, of coarse squares."""
        c = coarse.astype(np.float64)
        ends = (np.sqrt(np.maximum(c - self.slack, 0)) * self.unit, np.sqrt(np.maximum(c, 0) + self.slack) * self.unit)
        return tuple(2 * np.arcsin(np.minimum(e / 2, 1)) for e in ends) if self.metric.name == "angular" else ends

    def _coarse(self, of: np.ndarray) -> np.ndarray:
        """Squares of the distances of all rows to each of ``of``."""
        out = (-2 * self.low[of]) @ self.low.T
        out += self.squares[of][:, None]
        out += self.squares
        return out

    def _least(self, rows: np.ndarray | slice, of: np.ndarray) -> np.ndarray:
        """The least square of each row's distances to ``of``."""
        out = (-2 * self.low[of]) @ self.low[rows].T
        out += self.squares[of][:, None]
        return out.min(axis=0) + self.squares[rows]

    def rows(self, own: np.ndarray, cap: int | None = None, block: int = 32) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(kept places, their distances) of each of ``own``, nearest first; with ``cap`` the first so many."""
        own = np.asarray(own, np.int64)
        for i in range(0, len(own), block):
            if self.metric.name == "l1":
                yield from (self._plain(p, cap) for p in own[i : i + block].tolist())
                continue
            part = own[i : i + block]
            for p, c in zip(part.tolist(), self._coarse(part)):
                yield self._by_balls(p, cap) if self.few and self._dense(c) else self._row(p, c, cap)

    def _plain(self, p: int, cap: int | None) -> tuple[np.ndarray, np.ndarray]:
        d = self.metric.rows(self.x, self.x[p])
        order = np.argsort(d, kind="stable")
        order = order[order != p]
        kept = select_neighbors(d[order], self.x[order], self.rule, cap, self.metric).kept
        return order[kept], d[order][kept]

    @cached_property
    def balls(self) -> Balls:
        return Balls(self.x)

    @cached_property
    def near(self) -> Near:
        return Near(self.x)

    @cached_property
    def centres(self) -> tuple[np.ndarray, np.ndarray]:
        return self.near.of(self.balls.centre)

    def _dense(self, c: np.ndarray) -> bool:
        """Whether more rows than a few heads would take are so near, by coarse squares, that even a copy would not drop them."""
        return np.count_nonzero(self.rule.drops(np.sqrt(np.maximum(c, 0)) * self.unit, 0.0)) + self.DENSE < len(c)

    def _useful(self, kept: np.ndarray, dist: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Which of ``kept`` can drop anything at distances between ``ends``: by the triangle inequality a near one drops nothing far.

        The rules are linear, so one that can do it between can do it at an end.
        """
        far = ends[:, None]
        return kept[self.rule.drops(far * (1 + 1e-9), np.maximum(far * (1 - 1e-9) - dist * (1 + 1e-9), 0)).any(axis=0)]

    def _dropped(self, places: np.ndarray, d: np.ndarray, kept: np.ndarray, dist: np.ndarray) -> np.ndarray:
        """Which of ``places`` at distances ``d`` any of ``kept`` drops."""
        drops, out = self.rule.drops, np.zeros(len(places), bool)
        if len(places) and len(kept):
            kept = self._useful(kept, dist, np.array([d.min(), d.max()]))
        if not len(places) or not len(kept):
            return out
        low, high = self.near.least(self.near.x[places], self.near.squares[places], kept)
        out = drops(d, high)
        unsure = np.flatnonzero(drops(d, low) & ~out)
        if len(unsure):
            for v in kept.tolist():
                out[unsure] |= drops(d[unsure], self.metric.rows(self.x[places[unsure]], self.x[v]))
        return out

    def _by_balls(self, p: int, cap: int | None) -> tuple[np.ndarray, np.ndarray]:
        x, metric, drops, balls = self.x, self.metric, self.rule.drops, self.balls
        away = metric.rows(balls.centre, x[p])
        low = np.maximum(away * (1 - 1e-9) - balls.radius, 0)
        left = np.argsort(low, kind="stable")
        ids, dist = np.empty(0, np.int64), np.empty(0)
        pool, pool_d, step = np.empty(0, np.int64), np.empty(0), self.BALLS
        # What even a copy would not drop is kept, whatever else is: such balls are opened together.
        take = max(step, len(left) - int(np.count_nonzero(drops(low, 0.0))))
        while (len(left) or len(pool)) and (cap is None or len(ids) < cap):
            places = balls.members(left[:take])
            places, left = places[places != p], left[take:]
            # All rows that are not in the pool yet are farther.
            reach = low[left[0]] if len(left) else np.inf
            d = metric.rows(x[places], x[p])
            stay = ~self._dropped(places, d, ids, dist)
            pool, pool_d = np.concatenate([pool, places[stay]]), np.concatenate([pool_d, d[stay]])
            ready = np.flatnonzero(pool_d < reach)
            near, d = pool[ready], pool_d[ready]
            order = np.lexsort((near, d))
            near, d = near[order], d[order]
            free = int(np.count_nonzero(~drops(d, 0.0)))
            new, new_d, near, d = near[:free], d[:free], near[free:], d[free:]
            stay = ~self._dropped(near, d, new, new_d)
            near, d = near[stay], d[stay]
            kept = select_neighbors(d, x[near], self.rule, None if cap is None else cap - len(ids), metric).kept
            new, new_d = np.concatenate([new, near[kept]]), np.concatenate([new_d, d[kept]])
            rest = pool_d >= reach
            pool, pool_d = pool[rest], pool_d[rest]
            stay = ~self._dropped(pool, pool_d, new, new_d)
            pool, pool_d = pool[stay], pool_d[stay]
            ids, dist = np.concatenate([ids, new]), np.concatenate([dist, new_d])
            if len(left) and len(new):
                end = away[left[-1]] + balls.radius.max()
                useful = self._useful(new, new_d, np.array([reach, max(reach, end)]))
                if len(useful):
                    least = self.near.least(self.centres[0][left], self.centres[1][left], useful)[1]
                    left = left[~drops(low[left] * (1 - 1e-9), least + balls.radius[left])]
            take = step = min(2 * step, self.OPENED)
        return ids[:cap], dist[:cap]

    def _row(self, p: int, c: np.ndarray, cap: int | None) -> tuple[np.ndarray, np.ndarray]:
        x, metric = self.x, self.metric
        live = np.delete(np.arange(len(c)), p)
        c = c[live]
        ids, dist, size, most = [], [], self.FIRST, 0
        while len(live) and (cap is None or most < cap):
            head = np.arange(len(live))
            if len(live) > 2 * size:
                # All within the size-th coarse distance, by true distances: a run of the order without gaps.
                reach = np.partition(c, size - 1)[size - 1]
                head = np.flatnonzero(c <= reach + 2 * self.slack)
            d = metric.rows(x[live[head]], x[p])
            if len(head) < len(live):
                inside = d <= self._bounds(np.array([reach]))[1][0]
                head, d = head[inside], d[inside]
            order = np.lexsort((live[head], d))
            near, d = live[head][order], d[order]
            kept = select_neighbors(d, x[near], self.rule, None if cap is None else cap - most, metric).kept
            new = near[kept]
            ids.append(new)
            dist.append(d[kept])
            most += len(new)
            rest = np.ones(len(live), bool)
            rest[head] = False
            # A matrix product over all rows is quicker than gathering most of them.
            least = self._least(slice(None), new)[live[rest]] if 2 * len(live) > len(self.low) else self._least(live[rest], new)
            live, c = live[rest], c[rest]
            (pu_low, pu_high), (uv_low, uv_high) = self._bounds(c), self._bounds(least)
            out = self.rule.drops(pu_low, uv_high)
            unsure = np.flatnonzero(self.rule.drops(pu_high, uv_low) & ~out)
            if len(unsure):
                d_pu = metric.rows(x[live[unsure]], x[p])
                for v in new.tolist():
                    out[unsure] |= self.rule.drops(d_pu, metric.rows(x[live[unsure]], x[v]))
            live, c = live[~out], c[~out]
            size = min(2 * size, self.MOST)
        return (np.concatenate(ids), np.concatenate(dist)) if ids else (np.empty(0, np.int64), np.empty(0))


def full_graph(x: np.ndarray, rule: Rule, metric: Metric = Metric(), own: np.ndarray | None = None) -> list[tuple[list[int], list[float]]]:
    """For each vertex in ``own`` the rule's kept set over all others, nearest first."""
    own = np.arange(len(x)) if own is None else own
    return [(ids.tolist(), d.tolist()) for ids, d in FullRows(x, rule, metric).rows(own)]


def exact_knn_graph(x: np.ndarray, k: int, metric: Metric = Metric()) -> tuple[np.ndarray, np.ndarray]:
    places = np.arange(len(x))
    return metric.nearest(x, x, places, min(k, max(1, len(x) - 1)), skip=places)


def _closest(x: np.ndarray, ids: np.ndarray, dist: np.ndarray, more: np.ndarray, k: int, metric: Metric, block: int = 1024) -> tuple[np.ndarray, np.ndarray, int]:
    """The k nearest different vertices of each row among ``ids`` with their distances and ``more``; and how many are new."""
    out_i, out_d, changed = np.full((len(x), k), -1, np.int64), np.full((len(x), k), np.inf), 0
    for i in range(0, len(x), block):
        rows = slice(i, min(i + block, len(x)))
        new = more[rows]
        d = metric.rows(x[np.maximum(new, 0)], x[rows][:, None, :])
        d[(new < 0) | (new == np.arange(len(x))[rows][:, None])] = np.inf
        all_i, all_d = np.concatenate([ids[rows], new], axis=1), np.concatenate([dist[rows], d], axis=1)
        order = np.lexsort((all_d, all_i), axis=1)
        all_i, all_d = np.take_along_axis(all_i, order, 1), np.take_along_axis(all_d, order, 1)
        all_d[:, 1:][all_i[:, 1:] == all_i[:, :-1]] = np.inf
        order = np.lexsort((all_i, all_d), axis=1)[:, :k]
        got_i, got_d = np.take_along_axis(all_i, order, 1), np.take_along_axis(all_d, order, 1)
        got_i[~np.isfinite(got_d)] = -1
        out_i[rows, : got_i.shape[1]], out_d[rows, : got_d.shape[1]] = got_i, got_d
        changed += int((got_i[:, :, None] != ids[rows][:, None, :]).all(axis=2).sum()) if k <= 64 else int((got_i != ids[rows]).sum())
    return out_i, out_d, changed


def descent_knn_graph(x: np.ndarray, k: int, metric: Metric = Metric(), rounds: int = 12, sample: int = 12, delta: float = 0.001, seed: int = 7) -> tuple[np.ndarray, np.ndarray]:
    """An approximate K-NN graph in arrays: neighbours along projections, then neighbours of forward and reverse neighbours."""
    n = len(x)
    k = min(k, max(1, n - 1))
    ids, dist = np.full((n, k), -1, np.int64), np.full((n, k), np.inf)
    rng = np.random.default_rng(seed)
    for _ in range(4):
        order = np.argsort(x @ rng.normal(size=x.shape[1]), kind="stable")
        place = np.empty(n, np.int64)
        place[order] = np.arange(n)
        shift = np.concatenate([np.arange(-(k // 2) - 1, 0), np.arange(1, k // 2 + 2)])
        near = place[:, None] + shift
        ids, dist, _ = _closest(x, ids, dist, np.where((near >= 0) & (near < n), order[np.clip(near, 0, n - 1)], -1), k, metric)
    for r in range(rounds):
        top = ids[:, :sample]
        src, dst = np.repeat(np.arange(n), top.shape[1]), top.ravel()
        src, dst = src[dst >= 0], dst[dst >= 0]
        order = np.lexsort((mix(src, seed + r), dst))
        src, dst = src[order], dst[order]
        at = np.arange(len(dst)) - np.searchsorted(dst, dst)
        back = np.full((n, sample), -1, np.int64)
        back[dst[at < sample], at[at < sample]] = src[at < sample]
        both = np.concatenate([top, back], axis=1)
        hop = np.where(both[:, :, None] >= 0, np.concatenate([top, back[:, : sample // 2]], axis=1)[np.maximum(both, 0)], -1).reshape(n, -1)
        ids, dist, changed = _closest(x, ids, dist, hop, k, metric, max(1, 4_000_000 // max(1, hop.shape[1] * x.shape[1])))
        if changed <= delta * n * k:
            break
    return ids, dist


def knn_graph(x: np.ndarray, k: int, metric: Metric = Metric()) -> tuple[np.ndarray, np.ndarray]:
    """The shard's K-NN graph: exact for a small shard, by descent for a large one."""
    return exact_knn_graph(x, k, metric) if len(x) <= EXACT_POINTS else descent_knn_graph(x, k, metric)


def find_entry(x: np.ndarray, adjacency: np.ndarray, width: int, metric: Metric, seed: int, start: int | None = None) -> int:
    """The vertex that a search for the centroid finds, from a hashed start if none is given."""
    start = int(np.argmin(mix(np.arange(len(x)), seed))) if start is None else start
    centre = x.mean(axis=0)
    found = beam_search(adjacency, x, centre[None, :], start, max(1, width), 1, metric)
    return int(found.ids[0, 0])


def exact_entry(x: np.ndarray, metric: Metric = Metric()) -> int:
    return int(np.argmin(metric.rows(x, x.mean(axis=0))))


def local_candidates(x, knn, knn_dist, entry, p: Params, metric: Metric, own: np.ndarray | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each vertex the C nearest of all that a search for it on the K-NN graph evaluates; with ``own`` for those alone, whose rows ``knn_dist`` has."""
    own = np.arange(len(x)) if own is None else own
    # Its own vertex is among a point's nearest, and left out.
    pools = beam_search(knn, x, x[own], entry, p.L, 1, metric, pools=True, most=p.C + 1).pools
    out = []
    for v, near_d, (ids, d) in zip(own.tolist(), knn_dist, pools):
        if p.include_knn:
            more = knn[v] >= 0
            ids, first = np.unique(np.concatenate([ids, knn[v][more]]), return_index=True)
            d = np.concatenate([d, near_d[more]])[first]
        ids, d = ids[ids != v], d[ids != v]
        order = np.lexsort((ids, d))[: p.C]
        out.append((ids[order].astype(np.int64), d[order]))
    return out


def make_rule(policy: str, p: Params) -> Rule:
    return {"unit": UnitBall(), "shifted": ShiftedBall(p.tau), "scaled": ScaledBall(p.alpha), "scaled_shifted": ScaledShiftedBall(p.alpha, p.tau), "fixed": ScaledShiftedBall(p.alpha, p.tau)}[policy]


def make_select(policy: str, p: Params, metric: Metric):
    """dist, vectors -> Selection, for a policy: adaptive, fixed, or a rule's name."""
    if policy == "adaptive":
        return lambda d, v: adaptive_select(d, v, p.M, p.alpha0, p.alpha_max, p.alpha_step, p.tau, p.reuse, metric)
    if policy == "fixed":
        return lambda d, v: fixed_select(d, v, p.M, p.alpha, p.tau, metric)
    return lambda d, v: select_neighbors(d, v, make_rule(policy, p), p.M, metric)


def make_select_many(policy: str, x: np.ndarray, p: Params, metric: Metric):
    """ids, distances of many vertices -> Selections, as make_select for each."""
    if policy == "adaptive":
        return lambda ids, d: adaptive_many(x, ids, d, p.M, p.alpha0, p.alpha_max, p.alpha_step, p.tau, p.reuse, metric)
    return lambda ids, d: select_many(x, ids, d, make_rule(policy, p), p.M, metric)


def add_backward_lazy(x, neighbors, dists, select, p: Params, log: list[Selection] | None = None, many=None) -> int:
    """Join reversed edges to forward ones, then prune each overfull vertex once. Returns the selections made."""
    n, size = len(neighbors), [len(row) for row in neighbors]
    src, dst = np.repeat(np.arange(n), size), np.fromiter((u for row in neighbors for u in row), np.int64, sum(size))
    d = np.fromiter((e for row in dists for e in row), float, len(dst))
    # A vertex's own edge goes before a reversed one.
    at = np.unique(np.concatenate([src * n + dst, dst * n + src]), return_index=True)[1]
    src, dst, d = np.concatenate([src, dst])[at], np.concatenate([dst, src])[at], np.concatenate([d, d])[at]
    order = np.lexsort((dst, d, src))
    dst, d, ends = dst[order], d[order], np.searchsorted(src[order], np.arange(n + 1))
    over = np.flatnonzero(np.diff(ends) > p.M).tolist()
    for v in range(n):
        neighbors[v], dists[v] = dst[ends[v] : ends[v + 1]].tolist(), d[ends[v] : ends[v + 1]].tolist()
    ids, near = ([a[ends[v] : ends[v + 1]][: p.backward_cap or None] for v in over] for a in (dst, d))
    chosen = many(ids, near) if many is not None else [select(e, x[i]) for i, e in zip(ids, near)]
    for v, i, e, got in zip(over, ids, near, chosen):
        neighbors[v], dists[v] = i[got.kept].tolist(), e[got.kept].tolist()
    if log is not None:
        log += chosen
    return len(over)


#: New edges of an overfull vertex that are put among its own one at a time, at most.
FEW = 8


def add_backward_eager(x, neighbors, dists, select, p: Params, rule: Rule | None = None, metric: Metric = Metric()) -> int:
    """Insert reversed edges one at a time and prune whenever a vertex overflows. Returns the selections made.

    With ``rule``, that of ``select`` by which the given edges were chosen, a pruned row is known to hold no edge that
    another drops, so only what was added since is measured.
    """
    calls, pruned = 0, [len(row) for row in neighbors]
    for v, (ns, ds) in enumerate(zip([list(n) for n in neighbors], [list(d) for d in dists])):
        for u, d in zip(ns, ds):
            if v in neighbors[u]:
                continue
            if len(neighbors[u]) < p.M:
                neighbors[u].append(v)
                dists[u].append(d)
                continue
            ids, dd = np.array([*neighbors[u], v]), np.array([*dists[u], d])
            if rule is not None and len(ids) - pruned[u] <= FEW:
                ids, dd = _put_among(x, ids[: pruned[u]], dd[: pruned[u]], ids[pruned[u] :], dd[pruned[u] :], rule, metric)
                ids, dd = ids[: p.M], dd[: p.M]
            else:
                order = np.lexsort((ids, dd))
                ids, dd = ids[order], dd[order]
                kept = select(dd, x[ids]).kept
                ids, dd = ids[kept], dd[kept]
            calls += 1
            neighbors[u], dists[u], pruned[u] = ids.tolist(), dd.tolist(), len(ids)
    return calls


def _put_among(x, ids: np.ndarray, dist: np.ndarray, new: np.ndarray, new_dist: np.ndarray, rule: Rule, metric: Metric) -> tuple[np.ndarray, np.ndarray]:
    """What the rule's filter keeps of a kept set, nearest first, and ``new`` ones: these go in nearest first, as the filter meets them."""
    for w, d in sorted(zip(new.tolist(), new_dist.tolist()), key=lambda e: (e[1], e[0])):
        at = int(np.count_nonzero((dist < d) | ((dist == d) & (ids < w))))
        between = metric.rows(x[ids], x[w])
        if rule.drops(d, between[:at]).any():
            continue
        stays = ~rule.drops(dist[at:], between[at:])
        ids, dist = np.concatenate([ids[:at], [w], ids[at:][stays]]), np.concatenate([dist[:at], [d], dist[at:][stays]])
    return ids, dist


def reached(neighbors: list[list[int]], entry: int, seen: np.ndarray | None = None) -> np.ndarray:
    """Which vertices a walk from ``entry`` reaches; with ``seen`` those are marked beside the ones it has."""
    seen = np.zeros(len(neighbors), bool) if seen is None else seen
    seen[entry] = True
    stack = [entry]
    while stack:
        near = np.asarray(neighbors[stack.pop()], np.int64)
        near = near[~seen[near]]
        seen[near] = True
        stack += near.tolist()
    return seen


def repair(x, neighbors, dists, entry: int, p: Params, metric: Metric) -> list[tuple[int, int]]:
    """Give each unreached part an edge from its nearest reached vertex with room (or the nearest); returns the new edges.

    A new edge only adds to what is reached, so the walk goes on from its end, and the next unreached place is not before this one.
    """
    added: list[tuple[int, int]] = []
    seen = reached(neighbors, entry)
    if seen.all():
        return added
    adjacency = padded(neighbors)
    for v in np.flatnonzero(~seen).tolist():
        if seen[v]:
            continue
        found = beam_search(adjacency, x, x[v : v + 1], entry, max(p.L, 10), None, metric)
        near = [(int(i), float(d)) for i, d in zip(found.ids[0], found.dist[0]) if i >= 0]
        u, d = next(((i, d) for i, d in near if len(neighbors[i]) < p.M), near[0])
        neighbors[u].append(v)
        dists[u].append(d)
        if len(neighbors[u]) > adjacency.shape[1]:
            adjacency = np.concatenate([adjacency, np.full((len(adjacency), 8), -1, np.int32)], axis=1)
        adjacency[u, len(neighbors[u]) - 1] = v
        added.append((u, v))
        reached(neighbors, v, seen)
    return added


def prepare_local(x: np.ndarray, p: Params, metric: Metric = Metric()) -> tuple[int, list[tuple[np.ndarray, np.ndarray]]]:
    """(entry, candidates): the phases that neither alpha nor tau touches, shared by sweeps over them."""
    knn, knn_dist = knn_graph(x, p.K, metric)
    entry = find_entry(x, knn, p.L, metric, p.seed, p.start)
    return entry, local_candidates(x, knn, knn_dist, entry, p, metric)


def build_local(x: np.ndarray, p: Params, policy: str = "adaptive", backward: str = "lazy", metric: Metric = Metric(), prepared=None) -> Graph:
    """Candidates by search on a K-NN graph, selection by ``policy``, backward edges, repair."""
    n = len(x)
    if n == 1:
        return Graph([[]], [[]], 0)
    entry, candidates = prepare_local(x, p, metric) if prepared is None else prepared
    select = make_select(policy, p, metric)
    many = make_select_many(policy, x, p, metric)
    log = many([ids for ids, _ in candidates], [d for _, d in candidates])
    g = Graph([ids[got.kept].tolist() for (ids, _), got in zip(candidates, log)], [d[got.kept].tolist() for (_, d), got in zip(candidates, log)], entry, log)
    finish_local(x, g, select, p, p.backward or backward, metric, many, None if policy == "adaptive" else make_rule(policy, p))
    return g


def finish_local(x: np.ndarray, g: Graph, select, p: Params, backward: str, metric: Metric, many=None, rule: Rule | None = None) -> None:
    """Add backward edges and the repair to a graph of forward edges."""
    g.selections = len(g.neighbors)
    if backward != "none":
        g.selections += add_backward_lazy(x, g.neighbors, g.dists, select, p, many=many) if backward == "lazy" else add_backward_eager(x, g.neighbors, g.dists, select, p, rule, metric)
        g.repairs = repair(x, g.neighbors, g.dists, g.entry, p, metric)


class Rows:
    """Out-neighbours in one array, -1 padded."""

    def __init__(self, n: int, width: int):
        self.a, self.degree = np.full((n, width), -1, np.int32), np.zeros(n, np.int64)

    def get(self, v: int) -> np.ndarray:
        return self.a[v, : self.degree[v]].astype(np.int64)

    def put(self, v: int, ids) -> None:
        self.a[v] = -1
        self.a[v, : len(ids)] = ids
        self.degree[v] = len(ids)

    def lists(self) -> list[list[int]]:
        return [self.a[v, :d].tolist() for v, d in enumerate(self.degree)]


def _prune(x, places: list[int], pools: list[np.ndarray], rule: Rule, cap: int, metric: Metric) -> list[np.ndarray]:
    """Of each of ``places`` what the rule keeps of its pool of other places."""
    size = np.array([len(ids) for ids in pools])
    if not size.sum():
        return pools
    row, ids = np.repeat(np.arange(len(size)), size), np.concatenate(pools)
    own = np.asarray(places)[row]
    d = np.concatenate([metric.rows(x[ids[i : i + 4096]], x[own[i : i + 4096]]) for i in range(0, len(ids), 4096)])
    order = np.lexsort((ids, d, row))
    ends = np.cumsum(size)[:-1]
    near, far = np.split(ids[order], ends), np.split(d[order], ends)
    return [i[got.kept] for i, got in zip(near, select_many(x, near, far, rule, cap, metric))]


def _link(rows: Rows, x, batch, pools: list[np.ndarray], rule: Rule, m: int, cap: int, metric: Metric) -> int:
    """Select at most ``m`` neighbours of each of ``batch`` from its pool and add reversed edges, pruning rows over ``cap`` once. Returns the selections made."""
    back: dict[int, list[int]] = {}
    for v, kept in zip(batch, _prune(x, batch, [pool[pool != v] for v, pool in zip(batch, pools)], rule, m, metric)):
        rows.put(v, kept)
        for u in kept.tolist():
            back.setdefault(u, []).append(v)
    over, full = [], []
    for u, new in back.items():
        own = rows.get(u)
        row = np.concatenate([own, np.array(sorted(set(new).difference(own.tolist())), np.int64)])
        if len(row) > cap:
            over.append(u)
            full.append(row)
        else:
            rows.put(u, row)
    for u, kept in zip(over, _prune(x, over, full, rule, cap, metric)):
        rows.put(u, kept)
    return len(batch) + len(over)


def build_layered(x: np.ndarray, m: int, width: int, rule: Rule = UnitBall(), metric: Metric = Metric(), seed: int = 1) -> Graph:
    """The layered small-world baseline: levels drawn geometrically from hashes, inserts in hash order.

    Points are searched for in batches of at most an eighth of those already in,
    and linked together; one that opens a layer goes alone.
    """
    n = len(x)
    u = (mix(np.arange(n), seed + 17) >> np.uint64(11)).astype(float) / 2**53
    level = np.floor(-np.log(np.maximum(u, 1e-18)) / math.log(max(2, m))).astype(int)
    order = np.argsort(mix(np.arange(n), seed), kind="stable")
    caps = lambda lay: 2 * m if lay == 0 else m
    entry, calls, done = int(order[0]), 0, 1
    layers = [Rows(n, caps(lay)) for lay in range(level[entry] + 1)]
    while done < n:
        top = len(layers) - 1
        batch = order[done : done + min(BATCH, max(1, done // BATCH_SHARE))]
        opens = np.flatnonzero(level[batch] > top)
        if len(opens):
            batch = batch[: max(1, opens[0])]
        starts = np.full(len(batch), entry)
        for lay in range(top, -1, -1):
            enters = level[batch] >= lay
            for group, queue in ((np.flatnonzero(~enters), 1), (np.flatnonzero(enters), width)):
                if not len(group):
                    continue
                got = beam_search(layers[lay].a, x, x[batch[group]], starts[group], queue, queue, metric)
                starts[group] = got.ids[:, 0]
                if queue > 1 or enters.any() and enters[group[0]]:
                    calls += _link(layers[lay], x, batch[group].tolist(), [row[row >= 0] for row in got.ids], rule, m, caps(lay), metric)
        for lay in range(top + 1, level[batch[0]] + 1):
            layers.append(Rows(n, caps(lay)))
            entry = int(batch[0])
        done += len(batch)
    neighbors = layers[0].lists()
    dists = [metric.rows(x[r], x[v]).tolist() if r else [] for v, r in enumerate(neighbors)]
    upper = [{int(v): layers[lay].get(v).tolist() for v in np.flatnonzero(level >= lay)} for lay in range(1, len(layers))]
    return Graph(neighbors, dists, entry, [], calls, [], upper)


def build_two_pass(x: np.ndarray, m: int, width: int, alpha: float, tau: float | None = None, metric: Metric = Metric(), seed: int = 1) -> Graph:
    """Random start, then two passes of search, selection and reverse edges, in batches; ``tau`` swaps in the scaled-shifted rule."""
    n = len(x)
    entry = exact_entry(x, metric)
    rows = Rows(n, m)
    for v in range(n):
        drawn = mix(np.arange(min(m, n - 1) * 2) + 1_000_003 * v, seed) % np.uint64(n)
        rows.put(v, [int(u) for u in dict.fromkeys(drawn.tolist()) if u != v][:m])
    calls, order = 0, np.argsort(mix(np.arange(n), seed + 5), kind="stable")
    step = max(1, min(BATCH, n // BATCH_SHARE))
    for a in (1.0, alpha):
        rule = ScaledBall(a) if tau is None else ScaledShiftedBall(a, tau)
        for i in range(0, n, step):
            batch = order[i : i + step]
            traces = beam_search(rows.a, x, x[batch], entry, width, 1, metric, traces=True).traces
            pools = [np.union1d([c for c, _ in t], rows.get(v)).astype(np.int64) for v, t in zip(batch, traces)]
            calls += _link(rows, x, batch.tolist(), pools, rule, m, m, metric)
    neighbors = rows.lists()
    dists = [metric.rows(x[r], x[v]).tolist() if r else [] for v, r in enumerate(neighbors)]
    return Graph(neighbors, dists, entry, [], calls)


@dataclass
class FlatGraph:
    """A graph ready for search: the entry and each layer's adjacency, the base first."""

    entry: int
    adjacencies: list[np.ndarray]


def flat(g: Graph) -> FlatGraph:
    n = len(g.neighbors)
    return FlatGraph(g.entry, [g.adjacency(), *(padded([layer.get(v, []) for v in range(n)]) for layer in g.layers)])


def search_layered(g: Graph | FlatGraph, x, queries, width: int, k: int, metric: Metric = Metric()):
    """Greedy descent through the upper layers, then a beam on the base layer; costs of all layers count."""
    g = flat(g) if isinstance(g, Graph) else g
    starts = np.full(len(queries), g.entry)
    ndc, hops, edges = np.zeros(len(queries), np.int64), np.zeros(len(queries), np.int64), np.zeros(len(queries), np.int64)
    for adjacency in reversed(g.adjacencies[1:]):
        got = beam_search(adjacency, x, queries, starts, 1, 1, metric)
        starts = got.ids[:, 0]
        ndc, hops, edges = ndc + got.ndc - 1, hops + got.hops, edges + got.edges
    got = beam_search(g.adjacencies[0], x, queries, starts, width, k, metric)
    got.ndc, got.hops, got.edges = got.ndc + ndc, got.hops + hops, got.edges + edges
    return got


METHODS = ("lcg_adaptive", "lcg_fixed", "lcg_adaptive_eager", "nsg", "shifted_local", "hnsw", "vamana", "hnsw_plus", "vamana_plus", "mrng", "shifted_full", "scaled_full", "fcg")


#: Methods whose vertices choose among all others, each for itself.
FULL = ("mrng", "shifted_full", "scaled_full", "fcg")


def full_rule(method: str, p: Params) -> Rule:
    """The rule of a full-candidate method."""
    return {"mrng": UnitBall(), "shifted_full": ShiftedBall(p.tau), "scaled_full": ScaledBall(p.alpha), "fcg": ScaledShiftedBall(p.alpha, p.tau)}[method]


#: Methods over the candidates of a search on the K-NN graph: policy and backward edges.
LOCAL = {"lcg_adaptive": ("adaptive", "lazy"), "lcg_adaptive_eager": ("adaptive", "eager"), "lcg_fixed": ("fixed", "lazy"), "nsg": ("unit", "eager"), "shifted_local": ("shifted", "eager")}


def prepared_by(method: str, p: Params) -> tuple | None:
    """What the phases of prepare_local depend on: settings of which this is equal may share them."""
    return (p.K, p.L, p.C, p.include_knn, p.seed, p.start) if method in LOCAL else None


def build(method: str, x: np.ndarray, p: Params, metric: Metric = Metric(), prepared=None) -> Graph:
    """Any method by name over prepared vectors; ``prepared`` is of prepare_local, for local methods."""
    if len(x) <= 1:
        return Graph([[] for _ in x], [[] for _ in x], 0)
    if method in LOCAL:
        return build_local(x, p, *LOCAL[method], metric, prepared)
    if method in ("hnsw", "hnsw_plus"):
        rule = UnitBall() if method == "hnsw" else ScaledShiftedBall(p.alpha, p.tau)
        return build_layered(x, p.hnsw_m, p.hnsw_ef, rule, metric, p.seed)
    if method in ("vamana", "vamana_plus"):
        alpha, tau = (p.vamana_alpha, None) if method == "vamana" else (max(p.alpha, 1.0), p.tau)
        return build_two_pass(x, p.vamana_m, p.vamana_l, alpha, tau, metric, p.seed)
    rows = full_graph(x, full_rule(method, p), metric)
    return Graph([r[0] for r in rows], [r[1] for r in rows], exact_entry(x, metric), [], len(x))
