"""Cost of tiles: records are reduced to one row per tile before anything is partitioned."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .grid import Grid, locate

#: Tiles that a driver may hold; beyond, cuts are made by the level-wise plan.
DRIVER_TILES = 1 << 18


def tile_load(particles: DataFrame | None, grid: Grid, elements: DataFrame | None = None, a: int = 1, b: int = 0, weight: str | None = None, sample: int = 1) -> DataFrame:
    """TILE_LOAD: particles, elements and a * particles + b * elements of each tile that has any.

    weight: a column summed instead of counting particles. sample: one particle in so many, by hash of its place, scaled up."""
    parts = []
    zero = F.lit(0).cast("long")
    if particles is not None:
        rows = particles if sample == 1 else particles.where(F.pmod(F.xxhash64("x", "y", "vx", "vy"), F.lit(sample)) == 0)
        rows = locate(rows, grid)
        parts.append(rows.select("ti", "tj", (F.col(weight) if weight else F.lit(1)).cast("long").alias("p"), zero.alias("e")))
    if elements is not None:
        parts.append(locate(elements, grid, "bx", "by").select("ti", "tj", zero.alias("p"), F.lit(1).cast("long").alias("e")))
    if not parts:
        raise ValueError("neither particles nor elements")
    both = parts[0] if len(parts) == 1 else parts[0].union(parts[1])
    p, e = F.sum("p") * sample, F.sum("e")
    return both.groupBy("ti", "tj").agg(p.alias("particles"), e.alias("elements"), (a * p + b * e).alias("cost"))


class LoadMap:
    """Costs of all tiles of a grid as an array, with their prefix sums. Its size is the grid's, whatever the number of records."""

    def __init__(self, cost: np.ndarray):
        self.cost = np.asarray(cost, np.int64)
        self.n, self.m = self.cost.shape
        self.prefix = np.zeros((self.n + 1, self.m + 1), np.int64)
        self.prefix[1:, 1:] = self.cost.cumsum(0).cumsum(1)

    @property
    def total(self) -> int:
        return int(self.prefix[-1, -1])

    def box(self, x0: int, x1: int, y0: int, y1: int) -> int:
        s = self.prefix
        return int(s[x1, y1] - s[x0, y1] - s[x1, y0] + s[x0, y0])

    def running(self, x0: int, x1: int, y0: int, y1: int, dim: str) -> np.ndarray:
        """Cost of the box up to each line of a dimension, both ends included."""
        s = self.prefix
        if dim == "x":
            return s[x0 : x1 + 1, y1] - s[x0 : x1 + 1, y0] - (s[x0, y1] - s[x0, y0])
        return s[x1, y0 : y1 + 1] - s[x0, y0 : y1 + 1] - (s[x1, y0] - s[x0, y0])

    def of_owners(self, owner: np.ndarray, parts: int) -> np.ndarray:
        return np.bincount(owner.ravel(), self.cost.ravel().astype(float), parts).astype(np.int64)


def gather(loads: DataFrame, grid: Grid, value: str = "cost") -> LoadMap:
    """The gather step: at most one row per tile comes to the driver, and the grid's size is checked."""
    if grid.tiles > DRIVER_TILES:
        raise ValueError(f"{grid.tiles} tiles are more than {DRIVER_TILES}; use the level-wise engine")
    cost = np.zeros((grid.n, grid.m), np.int64)
    rows = loads.select("ti", "tj", value).toArrow()
    cost[rows.column("ti").to_numpy(), rows.column("tj").to_numpy()] = rows.column(value).to_numpy()
    return LoadMap(cost)
