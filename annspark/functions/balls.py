"""Rows of few components in small balls, so that whole balls are told apart from a point at once."""

from __future__ import annotations

import numpy as np

from annspark.functions.metric import Metric

#: Components up to which balls are small beside distances, and rows of a ball at most, copies aside.
FEW_COMPONENTS, BALL_ROWS = 8, 64


class Balls:
    """Balls around rows that were cut at the middle of their widest side, or at its median if few are beyond; a radius is a little too large rather than too small."""

    def __init__(self, x: np.ndarray, rows: int = BALL_ROWS):
        todo, parts = [np.arange(len(x))] if len(x) else [], []
        while todo:
            own = todo.pop()
            wide = x[own].max(axis=0) - x[own].min(axis=0)
            side = int(np.argmax(wide))
            if len(own) <= rows or not wide[side] > 0:
                parts.append(own)
                continue
            value = x[own, side]
            below = value <= (value.min() + value.max()) / 2
            if min(below.sum(), len(own) - below.sum()) * 16 < len(own):
                below = np.argsort(np.argsort(value, kind="stable")) < len(own) // 2
            todo += [own[below], own[~below]]
        self.order = np.concatenate(parts) if parts else np.empty(0, np.int64)
        self.size = np.array([len(own) for own in parts], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.centre = np.array([x[own].mean(axis=0) for own in parts]).reshape(len(parts), x.shape[1])
        self.radius = np.array([Metric().rows(x[own], c).max() for own, c in zip(parts, self.centre)]) * (1 + 1e-9)

    def members(self, balls: np.ndarray) -> np.ndarray:
        """The rows of some balls."""
        size = self.size[balls]
        return self.order[np.repeat(self.start[balls] - np.cumsum(size) + size, size) + np.arange(size.sum())]


class Near:
    """Least distances to some of the rows ``x``, between bounds, from matrix products."""

    def __init__(self, x: np.ndarray):
        self.middle = x.mean(axis=0) if len(x) else 0.0
        self.x, self.squares = self.of(x)
        self.slack = 1e-9 * float(self.squares.max(initial=0)) + 1e-300

    def of(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Other rows, made ready for ``least``."""
        q = q - self.middle
        return q, np.einsum("ij,ij->i", q, q)

    def least(self, q: np.ndarray, squares: np.ndarray, to: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bounds of each row's distance to the nearest of the places ``to``."""
        c = (-2 * q) @ self.x[to].T
        c += self.squares[to]
        c = c.min(axis=1) + squares
        slack = self.slack + 1e-9 * float(squares.max(initial=0))
        return np.sqrt(np.maximum(c - slack, 0)), np.sqrt(np.maximum(c, 0) + slack)
