"""The tile grid: locating records, dense tiles, line sums, prefix sums and neighbours."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Grid:
    """n by m tiles over a domain of lx by ly fixed-point units; boundary: periodic, reflect or absorb."""

    n: int
    m: int
    lx: int
    ly: int
    boundary: str = "periodic"

    def __post_init__(self):
        if min(self.n, self.m, self.lx, self.ly) < 1:
            raise ValueError("a grid needs at least one tile and one unit in each dimension")
        if self.boundary not in ("periodic", "reflect", "absorb"):
            raise ValueError(f"no boundary is called {self.boundary}")

    @property
    def tiles(self) -> int:
        return self.n * self.m


def div(a: Column, b: Column | int) -> Column:
    """Whole quotient of non-negative numbers."""
    return F.call_function("div", a, b if isinstance(b, Column) else F.lit(b))


def tile_x(grid: Grid, x: str | Column = "x") -> Column:
    return div((F.col(x) if isinstance(x, str) else x) * grid.n, grid.lx)


def tile_y(grid: Grid, y: str | Column = "y") -> Column:
    return div((F.col(y) if isinstance(y, str) else y) * grid.m, grid.ly)


def locate(df: DataFrame, grid: Grid, x: str = "x", y: str = "y") -> DataFrame:
    """df with the tile (ti, tj) of each record; a projection inside whole-stage code, no join."""
    return df.withColumns({"ti": tile_x(grid, x), "tj": tile_y(grid, y)})


def tiles(spark: SparkSession, grid: Grid) -> DataFrame:
    """(ti, tj) of every tile."""
    return spark.range(grid.tiles).select(div(F.col("id"), grid.m).alias("ti"), F.pmod("id", F.lit(grid.m)).alias("tj"))


def densify(loads: DataFrame, grid: Grid, value: str = "cost") -> DataFrame:
    """(ti, tj, value) of every tile, 0 where there was none."""
    return tiles(loads.sparkSession, grid).join(loads.select("ti", "tj", value), ["ti", "tj"], "left").select("ti", "tj", F.coalesce(value, F.lit(0)).alias(value))


def line_sums(loads: DataFrame, axis: str = "ti", value: str = "cost") -> DataFrame:
    """Sum over each column (ti) or row (tj) of tiles."""
    return loads.groupBy(axis).agg(F.sum(value).alias(value))


def prefix_table(loads: DataFrame, grid: Grid, value: str = "cost") -> DataFrame:
    """(i, j, s): the sum over tiles with ti < i and tj < j, for 0 <= i <= n, 0 <= j <= m, by one running sum along either axis."""
    dense = densify(loads, grid, value)
    along = dense.withColumn("r", F.sum(value).over(Window.partitionBy("ti").orderBy("tj")))
    whole = along.select((F.col("ti") + 1).alias("i"), (F.col("tj") + 1).alias("j"), F.sum("r").over(Window.partitionBy("tj").orderBy("ti")).alias("s"))
    spark = loads.sparkSession
    edge = spark.range(grid.n + 1).select(F.col("id").alias("i"), F.lit(0).cast("long").alias("j"), F.lit(0).cast("long").alias("s"))
    return whole.union(edge).union(spark.range(1, grid.m + 1).select(F.lit(0).cast("long"), "id", F.lit(0).cast("long")))


def neighbours(df: DataFrame, grid: Grid, halves: bool = False) -> DataFrame:
    """df once for each tile beside its own, as (ni, nj), over the periodic edges; with `halves` each adjacent pair once."""
    ti, tj = F.col("ti"), F.col("tj")
    steps = [(1, 0), (0, 1)] if halves else [(1, 0), (-1, 0), (0, 1), (0, -1)]
    beside = F.array(*[F.struct(F.pmod(ti + a, F.lit(grid.n)).alias("ni"), F.pmod(tj + b, F.lit(grid.m)).alias("nj")) for a, b in steps])
    return df.withColumn("_beside", F.explode(beside)).select("*", "_beside.ni", "_beside.nj").drop("_beside")
