"""Who owns a particle: a fixed owner for life, or the owner of its place; what moves, and how it is moved."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .grid import Grid, locate, tile_x, tile_y
from .partition import Cut

#: Owners up to which ownership is one expression; beyond, the rectangles are joined by tile.
EXPRESSION_OWNERS = 512
#: Tiles of which an owner table may be broadcast: 24 bytes each, 64 MB at most.
BROADCAST_TILES = 1 << 21


def site_owner(particles: DataFrame, cut: Cut, grid: Grid, to: str = "owner") -> DataFrame:
    """particles with the owner of the tile they are in."""
    if cut.parts <= EXPRESSION_OWNERS:
        return particles.withColumn(to, cut.owner(tile_x(grid), tile_y(grid)))
    from .partition import expand

    return join_owner(locate(particles, grid), expand(cut.frame(particles.sparkSession)), grid, to).drop("ti", "tj")


def join_owner(located: DataFrame, tile_owner: DataFrame, grid: Grid, to: str = "owner") -> DataFrame:
    """Located particles with the owner of their tile from a table; it is broadcast only if its size, the grid's, allows."""
    small = F.broadcast(tile_owner) if grid.tiles <= BROADCAST_TILES else tile_owner
    return located.join(small.withColumnRenamed("pid", to), ["ti", "tj"])


def fixed_owner(start: DataFrame, cut: Cut, grid: Grid, to: str = "owner") -> DataFrame:
    """The initial particles with the owner they keep for life."""
    return site_owner(start, cut, grid, to)


def migrations(particles: DataFrame, before: str = "owner0", after: str = "owner") -> DataFrame:
    """(src, dst, n) of particles whose owner changed; both owners are on the row, so nothing is joined."""
    return particles.where(F.col(before) != F.col(after)).groupBy(F.col(before).alias("src"), F.col(after).alias("dst")).agg(F.count("*").alias("n"))


def leavers(particles: DataFrame, subdomains: DataFrame, grid: Grid, owner: str = "owner") -> DataFrame:
    """Particles outside of their owner's rectangle, by two comparisons in either dimension."""
    boxes = F.broadcast(subdomains.select(F.col("pid").alias(owner), "x0", "x1", "y0", "y1"))  # one row for each owner
    ti, tj = tile_x(grid), tile_y(grid)
    return particles.join(boxes, owner).where((ti < F.col("x0")) | (ti >= F.col("x1")) | (tj < F.col("y0")) | (tj >= F.col("y1"))).drop("x0", "x1", "y0", "y1")


def move(particles: DataFrame, parts: int, before: str = "owner0", after: str = "owner") -> DataFrame:
    """Only particles that change their owner are shuffled, to the partition of the new one; residents stay where they are."""
    stay, go = particles.where(F.col(before) == F.col(after)), particles.where(F.col(before) != F.col(after))
    return stay.unionByName(by_owner(go, parts, after))


def by_owner(particles: DataFrame, parts: int, owner: str = "owner") -> DataFrame:
    """Each owner's particles in a partition of their own, in the order of their tiles' interleaved bits if they are located."""
    return particles.repartitionById(parts, F.col(owner).cast("int"))


def own_elements(elements: DataFrame, cut: Cut, grid: Grid) -> DataFrame:
    """Mesh elements with the owner of the tile of their barycentre."""
    return elements.withColumn("owner", cut.owner(tile_x(grid, "bx"), tile_y(grid, "by")))


def hash_owner(particles: DataFrame, parts: int, key: str = "pid_key") -> DataFrame:
    """The baseline that spreads particles by key, whatever their place."""
    return particles.withColumn("owner", F.pmod(F.col(key), F.lit(parts)))
