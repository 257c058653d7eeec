"""Measures of a partition, a placement and a run."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .grid import Grid, locate, neighbours
from .partition import Cut


def timed(run: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """A run's result, made whole by a sink that keeps nothing, and its seconds."""
    began = time.perf_counter()
    df = run()
    df.write.format("noop").mode("overwrite").save()
    return df, time.perf_counter() - began


def owner_loads(particles: DataFrame, parts: int, owner: str = "owner", weight: str | None = None) -> DataFrame:
    """(pid, load) of every owner, those without particles included."""
    counted = particles.groupBy(F.col(owner).alias("pid")).agg((F.sum(weight) if weight else F.count("*")).cast("long").alias("load"))
    return particles.sparkSession.range(parts).select(F.col("id").alias("pid")).join(counted, "pid", "left").select("pid", F.coalesce("load", F.lit(0)).alias("load"))


def imbalance(loads: DataFrame, *by: str) -> DataFrame:
    """(max_load, mean_load, imbalance), greatest load by the mean."""
    top, mean = F.max("load"), F.avg("load")
    return loads.groupBy(*by).agg(top.alias("max_load"), F.round(mean, 6).alias("mean_load"), F.round(top / mean, 6).alias("imbalance"))


def migration(old: DataFrame, new: DataFrame, loads: DataFrame, value: str = "cost") -> DataFrame:
    """(tiles_moved, particles_moved) between two TILE_OWNERs."""
    both = old.withColumnRenamed("pid", "was").join(new, ["ti", "tj"]).where("was <> pid").join(loads.select("ti", "tj", value), ["ti", "tj"], "left")
    return both.agg(F.count("*").alias("tiles_moved"), F.coalesce(F.sum(value), F.lit(0)).alias("particles_moved"))


def perimeter(subdomains: DataFrame) -> DataFrame:
    """(total, greatest) border length in tiles."""
    length = 2 * (F.col("x1") - F.col("x0") + F.col("y1") - F.col("y0"))
    return subdomains.agg(F.sum(length).alias("perimeter_sum"), F.max(length).alias("perimeter_max"))


def aspect(subdomains: DataFrame) -> DataFrame:
    """(max_aspect, mean_aspect), long side by short side."""
    a, b = F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0")
    ratio = F.greatest(a, b) / F.least(a, b)
    return subdomains.agg(F.round(F.max(ratio), 6).alias("max_aspect"), F.round(F.avg(ratio), 6).alias("mean_aspect"))


def cut_edges(tile_owner: DataFrame, grid: Grid) -> DataFrame:
    """Adjacent tiles of different owners, over the periodic edges, each pair once."""
    beside = neighbours(tile_owner, grid, halves=True)
    other = tile_owner.select(F.col("ti").alias("ni"), F.col("tj").alias("nj"), F.col("pid").alias("other"))
    return beside.join(other, ["ni", "nj"]).agg(F.count("*").alias("pairs"), F.count_if(F.col("pid") != F.col("other")).alias("cut"))


def footprint(particles: DataFrame, grid: Grid, owner: str = "owner", approximate: bool = False) -> DataFrame:
    """(pid, tiles_seen): different tiles whose fields an owner's particles read."""
    tile = F.col("ti") * grid.m + F.col("tj")
    count: Column = F.approx_count_distinct(tile, 0.01) if approximate else F.count_distinct(tile)
    return locate(particles, grid).groupBy(F.col(owner).alias("pid")).agg(count.alias("tiles_seen"))


def conservation(particles: DataFrame) -> DataFrame:
    return particles.agg(F.count("*").alias("particles"), F.sum("weight").alias("charge"))


def model_cost(loads: DataFrame, seen: DataFrame, left: DataFrame, borders: DataFrame, a: int = 1, b: int = 4, c: int = 8, d: int = 16) -> DataFrame:
    """Modelled cost of a step, its slowest owner's: particles, tiles seen, leavers and border, each by its price.

    loads (pid, load), seen (pid, tiles_seen), left (pid, n), borders (pid, length)."""
    z = lambda x: F.coalesce(F.col(x), F.lit(0))
    every = loads.join(seen, "pid", "left").join(left, "pid", "left").join(borders, "pid", "left")
    return every.agg(F.max(a * z("load") + b * z("tiles_seen") + c * z("n") + d * z("length")).alias("step_cost"))


def ratio(table: DataFrame, key: str, base: str, value: str) -> DataFrame:
    """Each row's value by that of the row called base."""
    one = table.where(F.col(key) == base).select(F.col(value).alias("_base"))
    return table.join(F.broadcast(one)).select(key, value, F.round(F.col(value) / F.col("_base"), 6).alias("ratio"))


def growth_rate(history: DataFrame, t: str = "t", energy: str = "energy") -> DataFrame:
    """Slope of the logarithm of the field's energy."""
    return history.where(F.col(energy) > 0).agg(F.regr_slope(F.log(energy), F.col(t)).alias("rate"))


def phase_split(seconds: dict[str, float]) -> dict[str, float]:
    """Share of each phase in a step."""
    whole = sum(seconds.values())
    return {k: v / whole for k, v in seconds.items()} if whole else dict(seconds)


def mean_aspect(cut: Cut) -> float:
    return max(max(x.x1 - x.x0, x.y1 - x.y0) / min(x.x1 - x.x0, x.y1 - x.y0) for x in cut.leaves)
