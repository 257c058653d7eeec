"""Whole runs: push, count tiles, rebalance, own, measure."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import metrics
from ..operators.cost import gather, tile_load
from ..operators.grid import Grid, locate
from ..operators.lineage import shared, stored
from ..operators.partition import Cut, imbalance, share_cut
from ..operators.pic import deposit, interpolate, push, step
from ..operators.placement import move, site_owner
from ..schema import STEP_METRIC
from .policy import Every, Never, Threshold


#: Rows of tiles by owners that a run gathers in a step at most.
GATHERED = 1 << 22


@dataclass(frozen=True)
class Run:
    """placement: `site` or `fixed` ownership. initial: the first cut. kick: steps with fields instead of drift alone.

    checkpoint: steps between cuts of lineage; at each of them the particles are written to the shared checkpoint folder."""

    grid: Grid
    parts: int = 32
    steps: int = 20
    placement: str = "site"
    policy: Never | Every | Threshold = Every(10)
    initial: Callable | None = None
    elements: DataFrame | None = None
    cost: tuple[int, int] = (1, 0)
    kick: bool = False
    checkpoint: int = 5


def run(particles: DataFrame, how: Run) -> tuple[DataFrame, DataFrame]:
    """(state, STEP_METRIC). Each step reads its particles once: owners of both moments, tiles and counts come from one aggregate.

    Under drift alone the state of any step is a projection of the last checkpoint, so nothing is written between."""
    spark = particles.sparkSession
    shared(spark)
    grid = how.grid
    if grid.tiles * how.parts > GATHERED:
        raise ValueError("too many tiles and owners for a table of both on the driver; cut by levels instead")
    static = tile_load(None, grid, how.elements) if how.elements is not None and how.cost[1] else None
    fixed_cost = gather(static, grid, "elements").cost * how.cost[1] if static is not None else 0

    def costs(counted) -> object:
        from ..operators.cost import LoadMap

        return LoadMap(how.cost[0] * counted + fixed_cost)

    began = time.perf_counter()
    counted = gather(tile_load(particles, grid), grid).cost
    cut: Cut = (how.initial or (lambda loads: share_cut(loads, how.parts)))(costs(counted))
    state = site_owner(particles, cut, grid)
    rows, syncs = [_metric(0, counted, cut.reloaded(costs(counted)), 0, 0, None, 1, True, began)], 1
    for t in range(1, how.steps + 1):
        began = time.perf_counter()
        state = step(state, grid) if how.kick else push(state, grid)
        if t % how.checkpoint == 0 or how.kick:
            state = state.checkpoint()
        now = state.withColumn("site", cut.owner(*_tile(grid)))
        per = locate(now, grid).groupBy("ti", "tj", "owner", "site").agg(F.count("*").alias("n")).toArrow()  # at most tiles x owners rows, as checked
        ti, tj, own, site, n = (per.column(c).to_numpy() for c in ("ti", "tj", "owner", "site", "n"))
        counted = np.zeros((grid.n, grid.m), np.int64)
        np.add.at(counted, (ti, tj), n)
        loads = costs(counted)
        was = cut
        due = how.policy.due(cut, loads, t)
        if due:
            cut = how.policy.rebalance(cut.reloaded(loads), loads, t)
            syncs += getattr(how.policy.rebalance, "global_", True)  # pairs wait for each other alone
        cut = cut.reloaded(loads)
        new = cut.owners()[ti, tj]
        if how.placement == "site" or due:
            state = state.withColumn("owner", cut.owner(*_tile(grid)))
            moved, holder = int(n[own != new].sum()), new
        else:
            moved, holder = 0, own
        held = np.bincount(holder, n.astype(float), cut.parts)
        seen = np.bincount(np.unique(np.stack([holder, ti * grid.m + tj]), axis=1)[0], minlength=cut.parts)
        tiles_moved = int((was.owners() != cut.owners()).sum())
        rows.append(_metric(t, counted, cut, tiles_moved, moved, (held, seen), syncs, due, began))
    return state, spark.createDataFrame(rows, STEP_METRIC)


def phases(particles: DataFrame, how: Run, cut: Cut | None = None) -> dict[str, float]:
    """Seconds of each phase of one step with fields, every one made whole by itself from stored results of the one before:
    deposit, field, interpolation with push, counting and cutting, and moving those that change their owner."""
    from ..operators.fields import tile_gradient

    grid, seconds = how.grid, {}
    cut = cut or share_cut(gather(tile_load(particles, grid), grid), how.parts)
    now = stored(site_owner(particles, cut, grid))

    def phase(name: str, make: Callable[[], DataFrame]) -> DataFrame:
        began = time.perf_counter()
        out = stored(make())
        seconds[name] = time.perf_counter() - began
        return out

    charge = phase("deposit", lambda: deposit(now, grid, "tile"))
    field = phase("field", lambda: tile_gradient(charge, grid))
    moved = phase("push", lambda: push(interpolate(now, field, grid, how.placement), grid, force=True))
    began = time.perf_counter()
    after = how.policy.rebalance(cut, gather(tile_load(moved, grid), grid), 1)
    seconds["rebalance"] = time.perf_counter() - began
    owned = site_owner(moved.withColumnRenamed("owner", "owner0"), after, grid)
    phase("move", lambda: move(owned, how.parts) if how.placement == "site" else owned)
    return seconds


def _tile(grid: Grid):
    from ..operators.grid import tile_x, tile_y

    return tile_x(grid), tile_y(grid)


def _metric(t: int, counted: np.ndarray, cut: Cut, tiles_moved: int, moved: int, held, syncs: int, due: bool, began: float) -> tuple:
    loads = cut.loads() if held is None else [int(x) for x in held[0]]
    seen = int(max((x.x1 - x.x0) * (x.y1 - x.y0) for x in cut.leaves)) if held is None else int(held[1].max())
    border = sum(2 * (x.x1 - x.x0 + x.y1 - x.y0) for x in cut.leaves)
    return (t, int(counted.sum()), max(loads), sum(loads) / len(loads), imbalance(loads), tiles_moved, moved, border, metrics.mean_aspect(cut), seen, syncs, bool(due), round((time.perf_counter() - began) * 1000, 3))
