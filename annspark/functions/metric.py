"""Metrics: distances that satisfy the triangle inequality, which every guarantee needs.

Decisions are made in doubles from direct differences, so that engines and SQL
agree on ties and borderline cases.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Squared L2, inner product and 1 - cosine break the triangle inequality.
METRICS = ("l2", "l1", "chord", "angular")
#: Rows of a ranking that are measured together.
RANKED = 2048
#: Pairs that a search for the nearest ranks together, at most about so many.
NEAREST_CELLS = 5_000_000


@dataclass(frozen=True)
class Metric:
    name: str = "l2"

    def __post_init__(self):
        if self.name not in METRICS:
            raise ValueError(f"{self.name} is not a metric here; use one of {', '.join(METRICS)}")

    def prepare(self, x: np.ndarray) -> np.ndarray:
        """Rows as doubles; unit length where the metric is about directions."""
        x = np.asarray(x, np.float64)
        if self.name in ("chord", "angular"):
            x = x / np.linalg.norm(x, axis=-1, keepdims=True)
        return x

    def of_differences(self, diff: np.ndarray) -> np.ndarray:
        """Distances from differences of prepared rows (last axis)."""
        if self.name == "l1":
            return np.abs(diff).sum(axis=-1)
        d = np.sqrt(np.einsum("...i,...i->...", diff, diff))
        return 2 * np.arcsin(np.minimum(d / 2, 1)) if self.name == "angular" else d

    def rows(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Distances between matching rows (``b`` may be one row)."""
        return self.of_differences(a - b)

    def ranking(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Distances between matching rows, rounded as the SQL engine rounds them.

        It adds squares in order with a fused multiply-add, which matters where two distances are equal but for
        rounding: their order is then the engine's. A square and its rounding error are added without loss.
        """
        if self.name not in ("l2", "chord"):
            return self.rows(a, b)
        if a.ndim == 2 and len(a) > RANKED:
            # A few rows at a time stay in the cache.
            return np.concatenate([self.ranking(a[i : i + RANKED], b[i : i + RANKED] if b.ndim == 2 else b) for i in range(0, len(a), RANKED)])
        diff = np.ascontiguousarray(np.asarray(a - b, np.float64).T)
        s = np.zeros(diff.shape[1:])
        with np.errstate(over="ignore", invalid="ignore"):
            for d in diff:
                square, wide = d * d, d * 134217729.0
                head = wide - (wide - d)
                tail = d - head
                lost = ((head * head - square) + 2 * head * tail) + tail * tail
                total = s + square
                share = total - s
                s = total + (((s - (total - share)) + (square - share)) + lost)
        out = np.sqrt(s)
        return np.where(np.isfinite(out), out, self.of_differences(diff.T))

    def cross(self, a: np.ndarray, b: np.ndarray, cells: int = 4_000_000) -> np.ndarray:
        """All distances between rows of ``a`` and rows of ``b``, in slices of bounded memory."""
        step = max(1, cells // max(1, len(b) * a.shape[1]))
        out = np.empty((len(a), len(b)))
        for i in range(0, len(a), step):
            out[i : i + step] = self.of_differences(a[i : i + step, None, :] - b[None, :, :])
        return out

    def extremes(self, a: np.ndarray, b: np.ndarray, high: float = 0.0, low: float = np.inf, block: int = 512) -> tuple[float, float]:
        """(largest, smallest positive) Euclidean distance between rows of ``a`` and of ``b``, and of ``high`` and ``low``.

        A matrix product ranks coarsely, and what can be an extreme is measured again by direct differences.
        """
        bb = np.einsum("ij,ij->i", b, b)
        for i in range(0, len(a), block):
            x = a[i : i + block]
            xx = np.einsum("ij,ij->i", x, x)
            coarse = xx[:, None] + bb[None, :] - 2 * (x @ b.T)
            slack = 1e-9 * (float(bb.max()) + float(xx.max())) + 1e-300
            over = max(high * high, float(coarse.max())) - slack
            apart = coarse[coarse > slack]
            under = min(low * low, float(apart.min(initial=np.inf))) + slack
            rows, cols = np.nonzero((coarse >= over) | (coarse <= under))
            for j in range(0, len(rows), 100_000):
                d = self.rows(b[cols[j : j + 100_000]], x[rows[j : j + 100_000]])
                high, low = max(high, float(d.max())), min(low, float(d[d > 0].min(initial=np.inf)))
        return high, low

    def nearest(
        self, a: np.ndarray, b: np.ndarray, b_ids: np.ndarray, k: int, skip: np.ndarray | None = None, block: int = 512, bound: np.ndarray | None = None
    ) -> tuple[np.ndarray, np.ndarray]:
        """(ids, distances) of the k rows of ``b`` nearest to each row of ``a``, by (distance, id).

        ``skip`` has an id for each row of ``a`` that isn't its own neighbour;
        ``bound`` has a distance beyond which a neighbour is of no use, and such
        ones may be left out. A matrix product ranks coarsely; what can be among
        the k is measured again by direct differences. Missing places hold id -1
        and infinity.
        """
        n = len(b)
        ids, dist = np.full((len(a), k), -1, np.int64), np.full((len(a), k), np.inf)
        if not n:
            return ids, dist
        euclid = self.name != "l1"
        bb = np.einsum("ij,ij->i", b, b)
        scale = float(bb.max(initial=0))
        block = min(block, max(1, NEAREST_CELLS // n))
        for i in range(0, len(a), block):
            x = a[i : i + block]
            if euclid:
                xx = np.einsum("ij,ij->i", x, x)
                coarse = xx[:, None] + bb[None, :] - 2 * (x @ b.T)
                slack = 1e-9 * (scale + float(xx.max(initial=0))) + 1e-300
            else:
                coarse, slack = self.cross(x, b), 1e-12
            if skip is not None:
                coarse[skip[i : i + block][:, None] == b_ids[None, :]] = np.inf
            cut = np.full(len(x), np.inf)
            if bound is not None:
                lim = bound[i : i + block]
                lim = 2 * np.sin(np.minimum(lim, np.pi) / 2) if self.name == "angular" else lim
                cut = (lim * lim if euclid else lim) * (1 + 1e-12)
            many = np.flatnonzero((coarse <= cut[:, None] + slack).sum(axis=1) > k) if n > k else np.empty(0, np.int64)
            if len(many):
                cut[many] = np.minimum(cut[many], np.partition(coarse[many], k - 1, axis=1)[:, k - 1])
            rows, cols = np.nonzero((coarse <= cut[:, None] + slack) & np.isfinite(coarse))
            if not len(rows):
                continue
            d = self.ranking(x[rows], b[cols])
            order = np.lexsort((b_ids[cols], d, rows))
            rows, cols, d = rows[order], cols[order], d[order]
            place = np.arange(len(rows)) - np.searchsorted(rows, rows)
            top = place < k
            ids[i + rows[top], place[top]], dist[i + rows[top], place[top]] = b_ids[cols[top]], d[top]
        return ids, dist


def l2_sql(a: str, b: str) -> str:
    """SQL for the Euclidean distance of two array columns, in doubles."""
    return f"sqrt(aggregate(zip_with({a}, {b}, (x, y) -> (cast(x AS double) - cast(y AS double)) * (cast(x AS double) - cast(y AS double))), 0D, (s, z) -> s + z))"
