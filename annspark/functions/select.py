"""Neighbour selection for one point: the ordered greedy filter and its variants.

Candidates come sorted by (distance to p, id). The filter keeps the first live
candidate and clears those of the later ones that the rule drops; distances
between candidates come from matrix products, a block of rows at a time.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from annspark.functions.metric import Metric, l2_sql
from annspark.functions.rules import Rule, ScaledShiftedBall, alpha_bar


#: Candidates whose pairs with all later ones come from one matrix product.
BLOCK = 32


@dataclass
class Selection:
    """Kept candidates (places in the sorted list) and the work done."""

    kept: list[int]
    alpha_used: float | None = None
    steps: int = 1
    #: Distances between candidates that were computed.
    pairs: int = 0
    #: Different candidates kept at any step.
    distinct: int = 0


def select_neighbors(dist: np.ndarray, vecs: np.ndarray, rule: Rule, cap: int | None = None, metric: Metric = Metric()) -> Selection:
    """The shortcut set; with ``cap`` it stops after so many, which equals cutting the set to its nearest."""
    n, alpha = len(dist), getattr(rule, "alpha", None)
    if n and metric.name in ("l2", "chord"):
        pu = np.asarray(dist, float)
        kept = Pairs(vecs, metric).filter(pu, rule.radius(pu), rule.drops, cap)
        return Selection(kept, alpha, 1, sum(n - 1 - i for i in _measured(kept, cap)), len(kept))
    kept, pairs = [], 0
    alive, i = np.ones(n, bool), 0
    while i < n:
        if alive[i]:
            kept.append(i)
            if cap is not None and len(kept) >= cap:
                break
            pairs += n - 1 - i
            alive[i + 1 :] &= ~rule.drops(dist[i + 1 :], metric.rows(vecs[i + 1 :], vecs[i]))
        i += 1
    return Selection(kept, alpha, 1, pairs, len(kept))


def _measured(kept: list[int], cap: int | None) -> list[int]:
    """The kept ones that are measured against later candidates: all but one that fills the cap."""
    return kept if cap is None or len(kept) < cap else kept[:-1]


class Pairs:
    """The filter over candidates whose distances to each other come from matrix products, a block of rows at a time.

    Pairs within the product's error of a rule's ball are measured by direct differences, so kept sets are those of
    distances measured directly. With ``keep`` the products of a row serve all later filters.
    """

    def __init__(self, vecs: np.ndarray, metric: Metric, keep: bool = False):
        self.vecs, self.metric = vecs, metric
        self.squares = np.einsum("ij,ij->i", vecs, vecs)
        self.slack = 4e-9 * float(self.squares.max()) + 1e-300
        self.near = np.empty((len(vecs), len(vecs))) if keep else None
        self.made = np.zeros(len(vecs), bool)

    def _coarse(self, rows: np.ndarray, start: int) -> np.ndarray:
        """Squares of distances of ``rows`` to all candidates from ``start`` on, negative."""
        out = (2 * self.vecs[rows]) @ self.vecs[start:].T
        out -= self.squares[start:]
        out -= self.squares[rows][:, None]
        return out

    def _rows(self, rows: np.ndarray, start: int) -> np.ndarray:
        if self.near is None:
            return self._coarse(rows, start)
        new = rows[~self.made[rows]]
        if len(new):
            # A row has the candidates from the block's first on, which are all that come after it.
            self.near[new, new[0] :] = self._coarse(new, int(new[0]))
            self.made[new] = True
        return self.near[rows, start:]

    def filter(self, dist: np.ndarray, radius: np.ndarray, drops, cap: int | None) -> list[int]:
        """Places kept, nearest first; a kept one drops those within their ``radius`` of it, as ``drops`` says of direct distances."""
        n, kept = len(dist), []
        squares = np.copysign(radius * radius, radius)
        slack = self.slack + 1e-9 * float(np.abs(squares).max())
        # Those that may be kept are the bits of a number, as are those that a candidate drops.
        live, size = (1 << n) - 1, (n + 7) // 8
        while live:
            head = np.flatnonzero(np.unpackbits(np.frombuffer(live.to_bytes(size, "little"), np.uint8), bitorder="little"))[:BLOCK]
            start = int(head[0])
            depth = self._rows(head, start) + squares[start:]
            sure, may = depth > slack, ~(depth < -slack)
            if np.count_nonzero(sure) != np.count_nonzero(may):
                row, col = np.nonzero(may & ~sure)
                col += start
                later = col > head[row]
                row, col = row[later], col[later]
                sure[row, col - start] = drops(dist[col], self.metric.rows(self.vecs[col], self.vecs[head[row]]))
            packed = np.packbits(sure, axis=1, bitorder="little")
            width, raw = packed.shape[1], packed.tobytes()
            for j, i in enumerate(head.tolist()):
                if not live >> i & 1:
                    continue
                kept.append(i)
                if cap is not None and len(kept) >= cap:
                    return kept
                live &= ~(int.from_bytes(raw[j * width : (j + 1) * width], "little") << start)
            live &= ~((2 << int(head[-1])) - 1)
        return kept


def cap_nearest(kept: list[int], m: int) -> list[int]:
    """The m nearest of a kept set, which is sorted by distance."""
    return kept[:m]


def fixed_select(dist: np.ndarray, vecs: np.ndarray, m: int, alpha: float, tau: float, metric: Metric = Metric()) -> Selection:
    return select_neighbors(dist, vecs, ScaledShiftedBall(alpha, tau), m, metric)


def alpha_steps(start: float, stop: float, step: float) -> list[float]:
    """start + k * step up to ``stop``, by whole steps so that the last is not lost to rounding."""
    return [start + k * step for k in range(int(round((stop - start) / step)) + 1)]


def adaptive_select(
    dist: np.ndarray, vecs: np.ndarray, m: int, a0: float = 0.9, amax: float = 1.6, da: float = 0.05, tau: float = 0.0, reuse: bool = True, metric: Metric = Metric()
) -> Selection:
    """Raise alpha from ``a0`` until at least half of ``m`` are kept or ``amax`` was tried; the last set counts.

    With ``reuse`` the threshold row of a neighbour is computed when it is first
    kept and only compared with later alphas. Kept sets for growing alpha are not
    nested, so nothing but distances carries over.
    """
    n = len(dist)
    if n and a0 > 0 and metric.name in ("l2", "chord"):
        return _adaptive_by_pairs(np.asarray(dist, float), vecs, m, alpha_steps(a0, amax, da), tau, reuse, metric)
    rows: dict[int, np.ndarray] = {}
    pairs = 0
    ever: set[int] = set()
    kept: list[int] = []
    used, steps = a0, 0
    for alpha in alpha_steps(a0, amax, da):
        used, steps = alpha, steps + 1
        alive = np.ones(n, bool)
        kept = []
        i = 0
        while i < n:
            kept.append(i)
            if len(kept) >= m:
                break
            row = rows.get(i) if reuse else None
            if row is None:
                d = metric.rows(vecs[i + 1 :], vecs[i])
                pairs += len(d)
                row = alpha_bar(dist[i + 1 :], d, tau)
                if reuse:
                    rows[i] = row
            rest = alive[i + 1 :]
            rest &= row <= alpha
            if not len(rest):
                break
            step = int(rest.argmax())
            if not rest[step]:
                break
            i += 1 + step
        ever.update(kept)
        if 2 * len(kept) >= m:
            break
    return Selection(kept[:m], used, steps, pairs, len(ever))


def _adaptive_by_pairs(dist: np.ndarray, vecs: np.ndarray, m: int, alphas: list[float], tau: float, reuse: bool, metric: Metric) -> Selection:
    n, pairs, steps = len(dist), 0, 0
    ever: set[int] = set()
    measured: set[int] = set()
    kept: list[int] = []
    used, between = alphas[0] if alphas else 0.0, None
    for used in alphas:
        steps += 1
        if between is None or not reuse:
            between = Pairs(vecs, metric, keep=reuse)
        kept = between.filter(dist, (dist - tau) / used - tau, lambda pu, uv, alpha=used: ~(alpha_bar(pu, uv, tau) <= alpha), max(m, 1))
        now = _measured(kept, max(m, 1))
        pairs += sum(n - 1 - i for i in now if not reuse or i not in measured)
        measured.update(now)
        ever.update(kept)
        if 2 * len(kept) >= m:
            break
    return Selection(kept[:m], used, steps, pairs, len(ever))


class Many:
    """The filter over the candidates of many points at once, as Pairs of each: ``ids`` are rows of places in ``x``, -1 padded, nearest first."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, metric: Metric):
        self.x, self.metric, self.there = x, metric, ids >= 0
        self.at = np.where(self.there, ids, ids[:, :1])
        # Single precision about the nearest candidate, so that errors are small beside a point's own candidates.
        v = x[self.at]
        v -= v[:, :1].copy()
        squares = np.einsum("bij,bij->bi", v, v)
        self.unit2 = squares.max(axis=1, keepdims=True)
        self.unit2[~((self.unit2 > 1e-200) & (self.unit2 < 1e200))] = 1.0
        v /= np.sqrt(self.unit2)[:, :, None]
        self.low, self.squares = v.astype(np.float32), (squares / self.unit2).astype(np.float32)
        self.error = 16 * (x.shape[1] + 8) * 6e-8

    def filter(self, dist: np.ndarray, radius: np.ndarray, drops, cap: int | None, todo: np.ndarray | None = None) -> np.ndarray:
        """Which are kept of the rows ``todo`` (all if none)."""
        rows = np.arange(len(dist)) if todo is None else np.flatnonzero(todo)
        alive, kept, found = self.there.copy(), np.zeros(self.there.shape, bool), np.zeros(len(dist), np.int64)
        squares = np.where(self.there, np.copysign(radius * radius, radius) / self.unit2, 0.0)
        slack = (self.error * (1 + np.abs(squares).max(axis=1))).astype(np.float32)
        shift = squares.astype(np.float32) - self.squares
        while True:
            rows = rows[alive[rows].any(axis=1) & (cap is None or found[rows] < cap)]
            if not len(rows):
                return kept
            live = alive[rows]
            head = np.argsort(~live, axis=1, kind="stable")[:, :BLOCK]
            low = self.low if len(rows) == len(self.low) else self.low[rows]
            every, own = np.arange(len(rows))[:, None], rows[:, None]
            depth = np.matmul(2 * low[every, head], low.transpose(0, 2, 1))
            depth += shift[rows][:, None, :]
            depth -= self.squares[own, head][:, :, None]
            edge = slack[rows][:, None, None]
            sure, may = depth > edge, ~(depth < -edge)
            if np.count_nonzero(sure) != np.count_nonzero(may):
                at, col = np.divmod(np.flatnonzero(sure != may), depth.shape[2])
                r, j = np.divmod(at, head.shape[1])
                place = head[r, j]
                open_ = (col > place) & live[r, col] & live[r, place]
                r, j, col, place = r[open_], j[open_], col[open_], place[open_]
                sure[r, j, col] = drops(dist[rows[r], col], self.metric.rows(self.x[self.at[rows[r], col]], self.x[self.at[rows[r], place]]))
            n, each = found[rows], every[:, 0]
            for j in range(head.shape[1]):
                at = head[:, j]
                keep = live[each, at]
                if cap is not None:
                    keep &= n < cap
                kept[rows, at] |= keep
                n += keep
                live &= ~(sure[:, j] & keep[:, None])
            live[every, head] = False
            alive[rows], found[rows] = live, n


def _chunks(ids: list[np.ndarray], dist: list[np.ndarray], width: int, cells: int = 1_000_000):
    """(numbers, padded ids, padded distances) of some lists of like length at a time."""
    size = np.array([len(i) for i in ids])
    order = np.argsort(-size, kind="stable")
    order = order[size[order] > 0]
    i = 0
    while i < len(order):
        part = order[i : i + max(1, cells // (int(size[order[i]]) * max(1, width)))]
        i += len(part)
        wide = (len(part), int(size[part[0]]))
        out_i, out_d, there = np.full(wide, -1, np.int64), np.full(wide, np.inf), np.arange(wide[1]) < size[part][:, None]
        out_i[there], out_d[there] = np.concatenate([ids[p] for p in part.tolist()]), np.concatenate([dist[p] for p in part.tolist()])
        yield part, out_i, out_d


def select_many(x: np.ndarray, ids: list[np.ndarray], dist: list[np.ndarray], rule: Rule, cap: int | None = None, metric: Metric = Metric()) -> list[Selection]:
    """select_neighbors of many points, each with places ``ids`` in ``x`` at distances ``dist``, sorted."""
    if metric.name not in ("l2", "chord") or cap is not None and cap < 1:
        return [select_neighbors(d, x[i], rule, cap, metric) for i, d in zip(ids, dist)]
    alpha = getattr(rule, "alpha", None)
    out = [Selection([], alpha, 1, 0, 0) for _ in ids]
    for part, i, d in _chunks(ids, dist, x.shape[1]):
        d = np.where(i >= 0, d, 0.0)
        kept = Many(x, i, metric).filter(d, rule.radius(d), rule.drops, cap)
        for p, own in zip(part.tolist(), kept):
            row = np.flatnonzero(own).tolist()
            out[p] = Selection(row, alpha, 1, _pairs(row, len(ids[p]), cap), len(row))
    return out


def _pairs(kept: list[int], n: int, cap: int | None) -> int:
    now = _measured(kept, cap)
    return (n - 1) * len(now) - sum(now)


def adaptive_many(
    x: np.ndarray, ids: list[np.ndarray], dist: list[np.ndarray], m: int, a0: float = 0.9, amax: float = 1.6, da: float = 0.05, tau: float = 0.0, reuse: bool = True, metric: Metric = Metric()
) -> list[Selection]:
    """adaptive_select of many points, as select_many. ``pairs`` counts what the method measures; products are made anew for each alpha."""
    alphas = alpha_steps(a0, amax, da)
    if metric.name not in ("l2", "chord") or a0 <= 0 or m < 1:
        return [adaptive_select(d, x[i], m, a0, amax, da, tau, reuse, metric) for i, d in zip(ids, dist)]
    out = [adaptive_select(np.empty(0), np.empty((0, x.shape[1])), m, a0, amax, da, tau, reuse, metric) if not len(i) else Selection([]) for i in ids]
    for part, i, d in _chunks(ids, dist, x.shape[1]):
        d = np.where(i >= 0, d, 0.0)
        between, todo = Many(x, i, metric), np.ones(len(part), bool)
        size, places = between.there.sum(axis=1), np.arange(i.shape[1])
        ever, measured, pairs = np.zeros(i.shape, bool), np.zeros(i.shape, bool), np.zeros(len(part), np.int64)
        for steps, alpha in enumerate(alphas, 1):
            kept = between.filter(d, (d - tau) / alpha - tau, lambda pu, uv, alpha=alpha: ~(alpha_bar(pu, uv, tau) <= alpha), m, todo)
            count = kept.sum(axis=1)
            now = kept.copy()
            full = np.flatnonzero(count >= m)
            now[full, i.shape[1] - 1 - now[full, ::-1].argmax(axis=1)] = False
            pairs += ((now & ~measured if reuse else now) * np.maximum(size[:, None] - 1 - places, 0)).sum(axis=1)
            measured |= now
            ever |= kept
            ends = todo & ((2 * count >= m) | (steps == len(alphas)))
            for r in np.flatnonzero(ends).tolist():
                out[part[r]] = Selection(np.flatnonzero(kept[r]).tolist(), alpha, steps, int(pairs[r]), int(ever[r].sum()))
            todo &= ~ends
            if not todo.any():
                break
    return out


def scan_pairs(dist: np.ndarray, vecs: np.ndarray, rule: Rule, cap: int | None = None, metric: Metric = Metric()) -> tuple[list[int], int]:
    """Plain double loop with short circuit: the kept set and how many pairs it looks at. For tests and counts."""
    kept: list[int] = []
    looked = 0
    for u in range(len(dist)):
        for v in kept:
            looked += 1
            if bool(rule.drops(dist[u], metric.rows(vecs[u : u + 1], vecs[v])[0])):
                break
        else:
            kept.append(u)
            if cap is not None and len(kept) >= cap:
                break
    return kept, looked


def fold_sql(cands: str, rule: Rule, cap: int | None = None) -> str:
    """SQL for the same filter over array<struct<d double, id bigint, e array<double>>>, as a fold."""
    state = "cast(array() AS array<struct<d: double, id: bigint, e: array<double>>>)"
    test = f"exists(s, v -> {rule.sql('u.d', l2_sql('u.e', 'v.e'))})"
    full = f"size(s) >= {cap} OR " if cap is not None else ""
    return f"aggregate(array_sort({cands}), {state}, (s, u) -> if({full}{test}, s, array_append(s, u)))"
