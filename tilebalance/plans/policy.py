"""When and how a run is rebalanced."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from ..operators.cost import LoadMap
from ..operators.diffusion import strip_exchange
from ..operators.partition import Cut, imbalance, share_cut, strips, tethered_cut, tethered_or_full

Rebalancer = Callable[[Cut, LoadMap, int], Cut]


def full(cut: Cut, loads: LoadMap, t: int) -> Cut:
    """Proportional bisection from scratch."""
    return share_cut(loads, cut.parts, cut.first_dim)


def tethered(level: int | None = None) -> Rebalancer:
    return lambda cut, loads, t: tethered_cut(cut, loads, level)


def tether_or_full(level: int | None = None, theta: float = 1.25) -> Rebalancer:
    return lambda cut, loads, t: tethered_or_full(cut, loads, level, theta)[0]


def fresh_strips(cut: Cut, loads: LoadMap, t: int) -> Cut:
    return strips(loads, list(cut.rows), cut.first_dim)


def neighbours(column_period: int | None = 4, eps: float = 0.0) -> Rebalancer:
    """One step of exchange between strips; it needs no load of any other pair, so no owner waits for all others."""

    def pairwise(cut: Cut, loads: LoadMap, t: int) -> Cut:
        return strip_exchange(cut, loads, t, column_period, eps)

    pairwise.global_ = False
    return pairwise


@dataclass(frozen=True)
class Never:
    rebalance: Rebalancer = full

    def due(self, cut: Cut, loads: LoadMap, t: int) -> bool:
        return False


@dataclass(frozen=True)
class Every:
    k: int
    rebalance: Rebalancer = full

    def due(self, cut: Cut, loads: LoadMap, t: int) -> bool:
        return t % self.k == 0


@dataclass(frozen=True)
class Threshold:
    theta: float
    rebalance: Rebalancer = full

    def due(self, cut: Cut, loads: LoadMap, t: int) -> bool:
        return imbalance(cut.reloaded(loads).loads()) > self.theta
