"""Field solvers: prescribed fields, a whole-number gradient, and explicit leapfrog on quads and on any mesh."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .grid import Grid, densify, tiles


def prescribed(spark: SparkSession, grid: Grid, fx: Column, fy: Column) -> DataFrame:
    """(ti, tj, fx, fy) of every tile, from expressions over ti and tj."""
    return tiles(spark, grid).select("ti", "tj", fx.cast("long").alias("fx"), fy.cast("long").alias("fy"))


def tile_gradient(deposited: DataFrame, grid: Grid, k: int = 1) -> DataFrame:
    """(ti, tj, fx, fy): k times the charge of the tile before less that of the tile behind, over the periodic edges.

    Each charge is sent to the four tiles beside it and summed there, one small shuffle."""
    c = F.col("charge") * k
    zero = F.lit(0).cast("long")
    to = lambda a, b, fx, fy: F.struct(F.pmod(F.col("ti") + a, F.lit(grid.n)).alias("ti"), F.pmod(F.col("tj") + b, F.lit(grid.m)).alias("tj"), fx.alias("fx"), fy.alias("fy"))
    sent = F.explode(F.array(to(1, 0, c, zero), to(-1, 0, -c, zero), to(0, 1, zero, c), to(0, -1, zero, -c)))
    return deposited.select(sent.alias("s")).select("s.*").groupBy("ti", "tj").agg(F.sum("fx").alias("fx"), F.sum("fy").alias("fy"))


def _sent(df: DataFrame, grid: Grid, own: list[str], *out: tuple[int, int, str, str]) -> DataFrame:
    """Each tile's own values, and values sent to it by tiles beside it: (di, dj, value, name). One shuffle; df is read once."""
    names = [*own, *[name for _, _, _, name in out]]
    null = F.lit(None).cast("double")

    def to(a: int, b: int, filled: dict[str, str]) -> Column:
        return F.struct(F.pmod(F.col("ti") + a, F.lit(grid.n)).alias("ti"), F.pmod(F.col("tj") + b, F.lit(grid.m)).alias("tj"), *[(F.col(filled[n]) if n in filled else null).alias(n) for n in names])

    rows = F.explode(F.array(to(0, 0, {n: n for n in own}), *[to(a, b, {name: value}) for a, b, value, name in out]))
    return df.select(rows.alias("s")).select("s.*").groupBy("ti", "tj").agg(*[F.max(n).alias(n) for n in names])


def leapfrog_quads(field: DataFrame, deposited: DataFrame, grid: Grid, dt: float, steps: int = 1) -> DataFrame:
    """(ti, tj, ex, ey, bz) after steps of the staggered scheme on a periodic grid of unit cells.

    ex lies on the lower edge of a cell, ey on its left edge, bz in its middle; currents (jx, jy) come from deposits."""
    j = tiles(field.sparkSession, grid).join(deposited.select("ti", "tj", "jx", "jy"), ["ti", "tj"], "left").select("ti", "tj", F.coalesce("jx", F.lit(0)).cast("double").alias("jx"), F.coalesce("jy", F.lit(0)).cast("double").alias("jy"))
    now = field.select("ti", "tj", *[F.col(c).cast("double").alias(c) for c in ("ex", "ey", "bz")]).join(j, ["ti", "tj"])
    own = ["ex", "ey", "bz", "jx", "jy"]
    for _ in range(steps):
        now = _sent(now, grid, own, (0, -1, "ex", "ex_up"), (-1, 0, "ey", "ey_right"))
        now = now.withColumn("bz", F.col("bz") - dt * (F.col("ey_right") - F.col("ey") - F.col("ex_up") + F.col("ex"))).drop("ex_up", "ey_right")
        now = _sent(now, grid, own, (0, 1, "bz", "bz_down"), (1, 0, "bz", "bz_left"))
        ex, ey = F.col("ex") + dt * (F.col("bz") - F.col("bz_down") - F.col("jx")), F.col("ey") + dt * (F.col("bz_left") - F.col("bz") - F.col("jy"))
        now = now.withColumns({"ex": ex, "ey": ey}).drop("bz_down", "bz_left")
    return now.select("ti", "tj", "ex", "ey", "bz")


def leapfrog_mesh(edges: DataFrame, faces: DataFrame, incidence: DataFrame, dt: float, steps: int = 1, current: DataFrame | None = None, store=None) -> DataFrame:
    """(edge, e) and the faces' (elem, b) after steps on any mesh, as one frame (kind, id, value).

    incidence: (elem, edge, sign). A face's b falls by the circulation of e around it, by its area; an edge's e grows by the
    signed b of the faces beside it, by its weight, less its current: two sparse products per step.
    edges: (edge, e, weight). faces: (elem, b, area). store: cuts the lineage of both after each step; without it plans of many
    steps grow fast."""
    e, b = edges, faces
    for _ in range(steps):
        turn = incidence.join(e.select("edge", "e"), "edge").groupBy("elem").agg(F.sum(F.col("sign") * F.col("e")).alias("c"))
        b = b.join(turn, "elem", "left").select("elem", (F.col("b") - dt * F.coalesce("c", F.lit(0.0)) / F.col("area")).alias("b"), "area")
        curl = incidence.join(b.select("elem", "b"), "elem").groupBy("edge").agg(F.sum(F.col("sign") * F.col("b")).alias("c"))
        e = e.join(curl, "edge", "left")
        given = F.lit(0.0)
        if current is not None:
            e = e.join(current.select("edge", "j"), "edge", "left")
            given = F.coalesce("j", F.lit(0.0))
        e = e.select("edge", (F.col("e") + dt * (F.coalesce("c", F.lit(0.0)) - given) / F.col("weight")).alias("e"), "weight")
        e, b = (store(e), store(b)) if store else (e, b)
    return e.select(F.lit("edge").alias("kind"), F.col("edge").alias("id"), F.col("e").alias("value")).union(b.select(F.lit("face"), "elem", "b"))


def energy(field: DataFrame) -> DataFrame:
    return field.agg(F.sum(F.col("ex") ** 2 + F.col("ey") ** 2 + F.col("bz") ** 2).alias("energy"))


def charge_grid(deposited: DataFrame, grid: Grid) -> DataFrame:
    return densify(deposited, grid, "charge")
