"""The phases of a particle-in-cell step: deposit, interpolation and push; the field solvers are in fields."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .grid import Grid, div, locate

#: Fixed-point weight of one whole particle in the bilinear share.
UNIT = 256


def _flows(scale: Column | int = 1) -> list[Column]:
    w = F.col("weight") * scale
    return [F.sum(w).alias("charge"), F.sum(w * F.col("vx")).alias("jx"), F.sum(w * F.col("vy")).alias("jy")]


def deposit(particles: DataFrame, grid: Grid, by: str = "tile") -> DataFrame:
    """Charge and current of particles by `tile`, by `element` (a column elem), or shared bilinearly over four `node`s in units of 1/256**2.

    Sums are combined in each task first, so that what is shuffled is the mesh, not the particles."""
    if by == "tile":
        return locate(particles, grid).groupBy("ti", "tj").agg(*_flows())
    if by == "element":
        return particles.groupBy("elem").agg(*_flows())
    if by != "node":
        raise ValueError(f"deposits go by tile, element or node, not {by}")
    u, v = (div(F.pmod(F.col(c) * n, F.lit(size)) * UNIT, size) for c, n, size in (("x", grid.n, grid.lx), ("y", grid.m, grid.ly)))
    rows = locate(particles, grid).withColumns({"u": u, "v": v})
    i, j = F.col("ti"), F.col("tj")
    corner = lambda a, b: F.struct(
        F.pmod(i + a, F.lit(grid.n)).alias("ti"), F.pmod(j + b, F.lit(grid.m)).alias("tj"), ((F.col("u") if a else UNIT - F.col("u")) * (F.col("v") if b else UNIT - F.col("v"))).alias("share")
    )
    spread = rows.select("weight", "vx", "vy", F.explode(F.array(*[corner(a, b) for a in (0, 1) for b in (0, 1)])).alias("c"))
    return spread.select("weight", "vx", "vy", "c.*").groupBy("ti", "tj").agg(*_flows(F.col("share")))


def interpolate(particles: DataFrame, field: DataFrame, grid: Grid, placement: str = "fixed", broadcast_tiles: int = 1 << 20) -> DataFrame:
    """Particles with the force (fx, fy) of their tile.

    Under `fixed` ownership particles read fields from everywhere: the field is broadcast, if the grid it
    covers is within its bound. Under `site` ownership both sides are dealt out by tile."""
    force = field.select("ti", "tj", "fx", "fy")
    force = F.broadcast(force) if placement == "fixed" and grid.tiles <= broadcast_tiles else force.hint("SHUFFLE_HASH")
    return locate(particles, grid).join(force, ["ti", "tj"], "left").withColumns({"fx": F.coalesce("fx", F.lit(0)), "fy": F.coalesce("fy", F.lit(0))}).drop("ti", "tj")


def _bounced(z: Column, size: int) -> Column:
    """A place and its direction after walls at 0 and size throw it back: the path unfolds to twice the size."""
    wide = F.pmod(z, F.lit(2 * size))
    return F.when(wide < size, wide).otherwise(2 * size - 1 - wide)


def push(particles: DataFrame, grid: Grid, steps: int = 1, force: bool = False, magnetic: float | None = None) -> DataFrame:
    """Particles after a number of steps of drift, or after one step of kick by (fx, fy) and drift.

    The kick is charge by force, of either sign by species; magnetic turns velocities by an angle first, in
    doubles rounded to whole units. Walls are the grid's: periodic, reflecting or absorbing."""
    if force and steps != 1:
        raise ValueError("fields change after each step")
    df = particles
    if force:
        sign = F.when(F.col("species") == 0, 1).otherwise(-1)
        df = df.withColumns({"vx": F.col("vx") + sign * F.col("fx"), "vy": F.col("vy") + sign * F.col("fy")}).drop("fx", "fy")
    if magnetic is not None:
        c, s = F.cos(F.lit(magnetic)), F.sin(F.lit(magnetic))
        df = df.withColumns({"vx": F.round(c * F.col("vx") + s * F.col("vy")).cast("long"), "vy": F.round(c * F.col("vy") - s * F.col("vx")).cast("long")})
    x, y = F.col("x") + steps * F.col("vx"), F.col("y") + steps * F.col("vy")
    if grid.boundary == "periodic":
        return df.withColumns({"x": F.pmod(x, F.lit(grid.lx)), "y": F.pmod(y, F.lit(grid.ly))})
    if grid.boundary == "absorb":
        return df.withColumns({"x": x, "y": y}).where((F.col("x") >= 0) & (F.col("x") < grid.lx) & (F.col("y") >= 0) & (F.col("y") < grid.ly))
    turned = lambda z, size: F.pmod(z, F.lit(2 * size)) >= size
    return df.withColumns({
        "x": _bounced(x, grid.lx), "y": _bounced(y, grid.ly),
        "vx": F.when(turned(x, grid.lx), -F.col("vx")).otherwise(F.col("vx")), "vy": F.when(turned(y, grid.ly), -F.col("vy")).otherwise(F.col("vy")),
    })


def relocate(particles: DataFrame, grid: Grid) -> DataFrame:
    """Particles with their tile after a motion."""
    return locate(particles.drop("ti", "tj"), grid)


def step(particles: DataFrame, grid: Grid, k: int = 1, placement: str = "fixed") -> DataFrame:
    """One whole step with the whole-number field: deposit, field, interpolation, push. No action is called."""
    from .fields import tile_gradient

    field = tile_gradient(deposit(particles, grid, "tile"), grid, k)
    return push(interpolate(particles, field, grid, placement), grid, force=True)
