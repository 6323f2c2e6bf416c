"""Edge-pruning rules: a candidate is dropped if a kept neighbour lies in a ball around it.

For a point p, a candidate u and a kept neighbour v that is nearer to p, u is
dropped when d(u, v) is smaller than the rule's radius r(d(p, u)). The rules
differ in the radius alone; a negative radius drops nothing.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Rule:
    """Base: subclasses give the threshold form ``drops`` and its SQL."""

    name = "rule"

    def radius(self, d_pu):
        raise NotImplementedError

    def drops(self, d_pu, d_uv):
        return np.asarray(d_uv) < self.radius(d_pu)

    def sql(self, d_pu: str, d_uv: str) -> str:
        raise NotImplementedError


@dataclass(frozen=True)
class UnitBall(Rule):
    """Radius d(p, u)."""

    name = "unit"

    def radius(self, d_pu):
        return np.asarray(d_pu)

    def sql(self, d_pu: str, d_uv: str) -> str:
        return f"({d_uv} < {d_pu})"


@dataclass(frozen=True)
class ShiftedBall(Rule):
    """Radius d(p, u) - 3 tau."""

    tau: float = 0.0
    name = "shifted"

    def radius(self, d_pu):
        return np.asarray(d_pu) - 3 * self.tau

    def sql(self, d_pu: str, d_uv: str) -> str:
        return f"({d_uv} < {d_pu} - {3 * self.tau!r})"


@dataclass(frozen=True)
class ScaledBall(Rule):
    """Radius d(p, u) / alpha."""

    alpha: float = 1.2
    name = "scaled"

    def radius(self, d_pu):
        return np.asarray(d_pu) / self.alpha

    def drops(self, d_pu, d_uv):
        return np.asarray(d_pu) > self.alpha * np.asarray(d_uv)

    def sql(self, d_pu: str, d_uv: str) -> str:
        return f"({d_pu} > {self.alpha!r} * {d_uv})"


@dataclass(frozen=True)
class ScaledShiftedBall(Rule):
    """Radius (d(p, u) - (alpha + 1) tau) / alpha: first shifted, then scaled."""

    alpha: float = 1.2
    tau: float = 0.0
    name = "scaled_shifted"

    def radius(self, d_pu):
        return (np.asarray(d_pu) - (self.alpha + 1) * self.tau) / self.alpha

    def drops(self, d_pu, d_uv):
        return np.asarray(d_pu) > self.alpha * np.asarray(d_uv) + (self.alpha + 1) * self.tau

    def sql(self, d_pu: str, d_uv: str) -> str:
        return f"({d_pu} > {self.alpha!r} * {d_uv} + {(self.alpha + 1) * self.tau!r})"


def alpha_bar(d_pu, d_uv, tau: float):
    """The threshold above alpha at which v stops dropping u: u is dropped exactly if alpha is below it.

    With d(u, v) + tau = 0 it is infinite if d(p, u) > tau, else minus infinity.
    """
    above, below = np.asarray(d_pu, float) - tau, np.asarray(d_uv, float) + tau
    if below.ndim and (below > 1e-150).all():
        return above / below
    with np.errstate(divide="ignore", invalid="ignore", over="ignore"):
        out = above / below
    return np.where(below > 0, out, np.where(above > 0, np.inf, -np.inf))


def alpha_bar_sql(d_pu: str, d_uv: str, tau: float) -> str:
    return f"(({d_pu} - {tau!r}) / ({d_uv} + {tau!r}))"
