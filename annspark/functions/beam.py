"""Beam search in one shard, many queries in lockstep.

State is arrays: for each query a sorted queue of at most L entries with their
distances and whether they were expanded, and a bitmap of vertices whose
distance was evaluated. Every round expands the nearest unexpanded entry of each
live query at once. A query ends when its whole queue is expanded.

Where many of few vertices are evaluated, one matrix product in single precision
has the distances of a batch to all of them; what it leaves possible to enter a
queue, and what is returned, is measured by direct differences, so results are
those of measuring every vertex.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from annspark.functions.metric import Metric

#: Bytes that the bitmaps and gathered vectors of one batch may take: few enough to stay in a core's cache.
BUDGET = 16_000_000
#: Vertices up to which products are used, for searches that may evaluate this part of them, and bytes of a batch then.
COARSE_POINTS, COARSE_SHARE, COARSE_BUDGET = 20_000, 32, 8_000_000


@dataclass
class Found:
    """Results by query: places of vertices (-1 where there are fewer), distances and costs."""

    ids: np.ndarray
    dist: np.ndarray
    ndc: np.ndarray
    hops: np.ndarray
    edges: np.ndarray
    pools: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)
    traces: list[list[tuple[int, float]]] = field(default_factory=list)


def beam_search(
    adjacency: np.ndarray, x: np.ndarray, queries: np.ndarray, entries: np.ndarray | int, width: int, k: int | None = None,
    metric: Metric = Metric(), pools: bool = False, traces: bool = False, most: int | None = None,
) -> Found:
    """Search ``adjacency`` (places, -1 padded) over prepared vectors ``x``.

    ndc counts distinct vertices evaluated, the entry included; hops counts
    expanded vertices; edges sums their out-degrees. ``pools`` returns every
    evaluated vertex with its distance (with ``most`` at least the so many nearest of them), ``traces`` the expanded ones in order.
    """
    n, degree = adjacency.shape if adjacency.ndim == 2 else (len(x), 0)
    k = width if k is None else k
    step = int(max(1, min(len(queries), BUDGET // max(1, n + 8 * max(1, degree) * x.shape[1]))))
    starts = np.broadcast_to(np.asarray(entries, np.int64), (len(queries),))
    near = Near.of(adjacency, x, metric) if len(queries) > 8 and COARSE_SHARE * degree * width >= n else None
    if near is None:
        parts = [_batch(adjacency, x, queries[i : i + step], starts[i : i + step], width, metric, pools, traces) for i in range(0, len(queries), step)]
    else:
        step = max(1, min(len(queries), COARSE_BUDGET // (4 * n)))
        parts = [_coarse_batch(near, x, queries[i : i + step], starts[i : i + step], width, metric, pools, traces, most) for i in range(0, len(queries), step)]
    if not parts:
        empty = np.empty(0, np.int64)
        return Found(np.empty((0, k), np.int64), np.empty((0, k)), empty, empty, empty)
    join = lambda f: np.concatenate([getattr(p, f) for p in parts])
    return Found(join("ids")[:, :k], join("dist")[:, :k], join("ndc"), join("hops"), join("edges"), sum((p.pools for p in parts), []), sum((p.traces for p in parts), []))


def _batch(adjacency, x, queries, starts, width, metric, pools, traces) -> Found:
    b, n = len(queries), len(x)
    ids = np.full((b, width), -1, np.int64)
    dist = np.full((b, width), np.inf)
    done = np.ones((b, width), bool)
    seen = np.zeros((b, n), bool)
    every = np.arange(b)
    ids[:, 0], dist[:, 0], done[:, 0] = starts, metric.rows(x[starts], queries), False
    seen[every, starts] = True
    ndc, hops, edges = np.ones(b, np.int64), np.zeros(b, np.int64), np.zeros(b, np.int64)
    log = [(every, starts.copy(), dist[:, 0].copy())] if pools else []
    steps: list[list[tuple[int, float]]] = [[] for _ in range(b)] if traces else []
    live = every
    while len(live):
        open_ = ~done[live]
        at = open_.argmax(axis=1)
        go = open_[np.arange(len(live)), at]
        live, at = live[go], at[go]
        if not len(live):
            break
        current = ids[live, at]
        done[live, at] = True
        hops[live] += 1
        if traces:
            for q, c, d in zip(live.tolist(), current.tolist(), dist[live, at].tolist()):
                steps[q].append((c, d))
        near = adjacency[current].astype(np.int64)
        there = near >= 0
        edges[live] += there.sum(axis=1)
        new = there & ~seen[live[:, None], np.where(there, near, 0)]
        r, c = np.nonzero(new)
        if not len(r):
            continue
        v = near[r, c]
        seen[live[r], v] = True
        ndc[live] += new.sum(axis=1)
        d = metric.rows(x[v], queries[live[r]])
        if pools:
            log.append((live[r], v, d))
        # Only what comes before a queue's last entry enters it.
        enters = d <= dist[live[r], -1]
        if not enters.all():
            r, c, v, d = r[enters], c[enters], v[enters], d[enters]
            if not len(r):
                continue
        _enter(ids, dist, done, live, r, v, d)
    out = Found(ids, dist, ndc, hops, edges, traces=steps)
    if pools:
        q = np.concatenate([p[0] for p in log])
        order = np.argsort(q, kind="stable")
        ends = np.cumsum(np.bincount(q, minlength=b))[:-1]
        out.pools = list(zip(np.split(np.concatenate([p[1] for p in log])[order], ends), np.split(np.concatenate([p[2] for p in log])[order], ends)))
    return out


def _enter(ids, dist, done, live, r, v, d) -> None:
    """Put vertices ``v`` at distances ``d`` into the queues of ``live[r]``; r is sorted."""
    width = ids.shape[1]
    # New entries of a row side by side, in few columns.
    first = np.concatenate([[True], r[1:] != r[:-1]])
    starts_at, rows, r = np.flatnonzero(first), live[r[first]], np.cumsum(first) - 1
    at = np.arange(len(r)) - starts_at[r]
    wide_d = np.full((len(rows), int(at.max()) + 1), np.inf)
    wide_i = np.full(wide_d.shape, -1, np.int64)
    wide_d[r, at], wide_i[r, at] = d, v
    all_d = np.concatenate([dist[rows], wide_d], axis=1)
    all_i = np.concatenate([ids[rows], wide_i], axis=1)
    # An entry's place and whether it was expanded travel in one number.
    packed = np.concatenate([2 * ids[rows] + done[rows], 2 * wide_i + (wide_i < 0)], axis=1)
    order, d = _order(all_d, all_i)
    dist[rows] = d[:, :width]
    packed = packed.ravel()[order[:, :width]]
    ids[rows], done[rows] = packed >> 1, (packed & 1).astype(bool)


@dataclass
class Near:
    """What searches by products need of a graph and its vectors: rows in single precision about their mean, of length 1 at most."""

    low: np.ndarray
    squares: np.ndarray
    centre: np.ndarray
    unit: float
    slack: float
    adjacency: np.ndarray
    degree: np.ndarray

    @classmethod
    def of(cls, adjacency: np.ndarray, x: np.ndarray, metric: Metric) -> Near | None:
        n = len(x)
        if not 0 < n <= COARSE_POINTS or metric.name not in ("l2", "chord"):
            return None
        centre = x.mean(axis=0)
        low = x - centre
        unit = float(np.sqrt(np.einsum("ij,ij->i", low, low).max()))
        if not 1e-100 < unit < 1e100:
            return None
        low = (low / unit).astype(np.float32)
        there = adjacency >= 0
        return cls(low, np.einsum("ij,ij->i", low, low), centre, unit, 16 * (x.shape[1] + 8) * 6e-8, np.where(there, adjacency, n).astype(np.int64), there.sum(axis=1))

    def keys(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(one more than the squares of the distances of ``queries`` to all rows, with -1 in a last column, and the error of each query's); -1 is the key of a padded place."""
        q = (queries - self.centre) / self.unit
        own = np.einsum("ij,ij->i", q, q)
        out = np.empty((len(q), len(self.low) + 1), np.float32)
        out[:, -1] = -1
        np.matmul((-2 * q).astype(np.float32), self.low.T, out=out[:, :-1])
        out[:, :-1] += self.squares
        out[:, :-1] += (own + 1).astype(np.float32)[:, None]
        return out, self.slack * (1 + own)


class Queues:
    """The queues of a batch of queries: each its nearest so far, sorted, and which of them were expanded."""

    def __init__(self, b: int, width: int, starts: np.ndarray, dist: np.ndarray):
        self.ids, self.dist, self.done = np.full((b, width), -1, np.int64), np.full((b, width), np.inf), np.ones((b, width), bool)
        self.ids[:, 0], self.dist[:, 0], self.done[:, 0] = starts, dist, False

    def expand(self, live: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(queries that go on, the nearest unexpanded vertex of each, its distance), now marked as expanded."""
        open_ = ~self.done[live]
        at = open_.argmax(axis=1)
        go = open_[np.arange(len(live)), at]
        live, at = live[go], at[go]
        self.done[live, at] = True
        return live, self.ids[live, at], self.dist[live, at]

    def enter(self, live: np.ndarray, r: np.ndarray, v: np.ndarray, d: np.ndarray) -> None:
        _enter(self.ids, self.dist, self.done, live, r, v, d)

    def finish(self) -> None:
        pass


class BufferedQueues(Queues):
    """The same with new entries beside the sorted ones, for wide queues, which are sorted again only when that can matter.

    An entry may be expanded while it is among the first ``width`` of both; so they are joined as soon as the sorted
    ones before it and all new ones could be as many. The last sorted distance may then be too large a bound, which lets in
    entries that the next sorting cuts off.
    """

    def __init__(self, b: int, width: int, starts: np.ndarray, dist: np.ndarray, size: int):
        super().__init__(b, width, starts, dist)
        #: Distances of new entries, those of unexpanded ones alone, places, and how many there are.
        self.new, self.open, self.places = np.full((b, size), np.inf), np.full((b, size), np.inf), np.full((b, size), -1, np.int64)
        self.fill = np.zeros(b, np.int64)

    def _join(self, rows: np.ndarray) -> None:
        rows = rows[self.fill[rows] > 0]
        if not len(rows):
            return
        width, m = self.ids.shape[1], int(self.fill[rows].max())
        new, places = self.new[rows, :m], self.places[rows, :m]
        packed = np.concatenate([2 * self.ids[rows] + self.done[rows], 2 * places + (self.open[rows, :m] == np.inf)], axis=1)
        order, d = _order(np.concatenate([self.dist[rows], new], axis=1), packed)
        self.dist[rows] = d[:, :width]
        packed = packed.ravel()[order[:, :width]]
        self.ids[rows], self.done[rows] = packed >> 1, (packed & 1).astype(bool)
        self.new[rows, :m], self.open[rows, :m], self.places[rows, :m], self.fill[rows] = np.inf, np.inf, -1, 0

    def expand(self, live: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        width = self.ids.shape[1]
        open_ = ~self.done[live]
        at = open_.argmax(axis=1)
        go = open_[np.arange(len(live)), at]
        late = np.flatnonzero((self.fill[live] > 0) & (~go | (at + self.fill[live] >= width)))
        if len(late):
            self._join(live[late])
            open_ = ~self.done[live[late]]
            at[late] = open_.argmax(axis=1)
            go[late] = open_[np.arange(len(late)), at[late]]
        live, at = live[go], at[go]
        ids, dist = self.ids[live, at], self.dist[live, at]
        m = int(self.fill[live].max(initial=0))
        if m:
            beside = self.open[live, :m]
            place = beside.argmin(axis=1)
            near = beside[np.arange(len(live)), place]
            for i in np.flatnonzero((np.count_nonzero(beside == near[:, None], axis=1) > 1) & (near < np.inf)).tolist():
                tied = np.flatnonzero(beside[i] == near[i])
                place[i] = tied[self.places[live[i], tied].argmin()]
            found = self.places[live, place]
            other = (near < dist) | ((near == dist) & (found < ids))
            rows = live[other]
            ids[other], dist[other] = found[other], near[other]
            self.open[rows, place[other]] = np.inf
            self.done[live[~other], at[~other]] = True
        else:
            self.done[live, at] = True
        return live, ids, dist

    def enter(self, live: np.ndarray, r: np.ndarray, v: np.ndarray, d: np.ndarray) -> None:
        many = np.bincount(r, minlength=len(live))
        self._join(live[self.fill[live] + many > self.new.shape[1]])
        rows = live[r]
        at = self.fill[rows] + np.arange(len(r)) - (np.cumsum(many) - many)[r]
        self.new[rows, at], self.open[rows, at], self.places[rows, at] = d, d, v
        self.fill[live] += many

    def finish(self) -> None:
        self._join(np.arange(len(self.ids)))


def _coarse_batch(near: Near, x, queries, starts, width, metric, pools, traces, most) -> Found:
    """As _batch, by keys: that of an evaluated vertex is made negative."""
    b, n = len(queries), len(x)
    keys, slack = near.keys(queries)
    if not (slack < 0.5).all():
        # A query so far from all vertices that the product tells little.
        return _batch(np.where(near.adjacency == n, -1, near.adjacency), x, queries, starts, width, metric, pools, traces)
    flat = keys.ravel()
    every = np.arange(b)
    row_at = every * (n + 1)
    size, first = max(64, near.adjacency.shape[1]), metric.rows(x[starts], queries)
    queues = BufferedQueues(b, width, starts, first, size) if width >= 3 * size else Queues(b, width, starts, first)
    keys[every, starts] *= -1
    ndc, hops, edges = np.ones(b, np.int64), np.zeros(b, np.int64), np.zeros(b, np.int64)
    steps: list[list[tuple[int, float]]] = [[] for _ in range(b)] if traces else []
    live = every
    while len(live):
        live, current, at_d = queues.expand(live)
        hops[live] += 1
        if traces:
            for q, c, d in zip(live.tolist(), current.tolist(), at_d.tolist()):
                steps[q].append((c, d))
        edges[live] += near.degree[current]
        places = near.adjacency[current]
        places += row_at[live][:, None]
        got = flat.take(places)
        new = got > 0
        ndc[live] += np.count_nonzero(new, axis=1)
        flat[places] = -np.abs(got)
        # Only what comes before a queue's last entry enters it.
        last = queues.dist[live, -1]
        bound = 1 + (last / near.unit) ** 2 * (1 + 1e-6) + slack[live]
        new &= got <= bound.astype(np.float32)[:, None]
        at = np.flatnonzero(new)
        if not len(at):
            continue
        r = at // new.shape[1]
        v = places.ravel()[at] - row_at[live[r]]
        d = metric.rows(x[v], queries[live[r]])
        enters = d <= last[r]
        if not enters.all():
            r, v, d = r[enters], v[enters], d[enters]
            if not len(r):
                continue
        queues.enter(live, r, v, d)
    queues.finish()
    out = Found(queues.ids, queues.dist, ndc, hops, edges, traces=steps)
    if pools:
        for q in range(b):
            seen = np.flatnonzero(keys[q, :-1] < 0)
            if most is not None and len(seen) > most:
                key = -keys[q, seen]
                seen = seen[key <= np.partition(key, most - 1)[most - 1] + 2 * slack[q]]
            out.pools.append((seen, metric.rows(x[seen], queries[q])))
    return out


def _order(dist: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(flat places, distances) of each row by (distance, id). The queue is sorted already, so a stable sort is quick; ids settle ties."""
    base = np.arange(0, dist.size, dist.shape[1])[:, None]
    order = np.argsort(dist, axis=1, kind="stable") + base
    d = dist.ravel()[order]
    tied = np.flatnonzero(((d[:, 1:] == d[:, :-1]) & (d[:, 1:] < np.inf)).any(axis=1))
    if len(tied):
        order[tied] = np.lexsort((ids[tied], dist[tied]), axis=1) + base[tied]
    return order, d


def greedy_route(adjacency: np.ndarray, x: np.ndarray, queries: np.ndarray, entries: np.ndarray | int, metric: Metric = Metric()) -> Found:
    """Beam search of width one: a chain of falling distances whose last hop is the answer."""
    return beam_search(adjacency, x, queries, entries, 1, 1, metric, traces=True)


def padded(neighbors: list) -> np.ndarray:
    """Neighbour lists as one array of places, -1 padded."""
    widest = max([1, *map(len, neighbors)])
    out = np.full((len(neighbors), widest), -1, np.int32)
    for i, row in enumerate(neighbors):
        out[i, : len(row)] = row
    return out
