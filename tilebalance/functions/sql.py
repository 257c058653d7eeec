"""Functions for SQL users: inlined SQL functions, table functions and grouped pandas forms."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from ..operators.cost import LoadMap
from ..operators.diffusion import pairs


@udtf(returnType="pid bigint, x0 bigint, x1 bigint, y0 bigint, y1 bigint, height bigint, load bigint")
class ShareCut:
    """Leaves of the proportional cut of TABLE(tile loads): ti, tj, cost; the grid's size and the number of owners.

    Called with the whole table in one partition; its rows are tiles."""

    def __init__(self):
        self.rows, self.how = [], None

    def eval(self, row, n: int, m: int, parts: int):
        self.rows.append((row["ti"], row["tj"], row["cost"]))
        self.how = n, m, parts

    def terminate(self):
        from tilebalance.operators.partition import share_cut

        if self.how:
            n, m, parts = self.how
            cost = np.zeros((n, m), np.int64)
            for i, j, w in self.rows:
                cost[i, j] += w
            for x in share_cut(LoadMap(cost), parts).leaves:
                yield x.pid, *x.box, x.height, x.load


@udtf(returnType="col bigint, upper bigint, lower bigint")
class PairSchedule:
    """Pairs of rows of a column of a size that meet at step t."""

    def eval(self, size: int, t: int):
        for c, a, b in pairs((size,), t):
            yield c, a, b


@pandas_udf(T.DoubleType())
def imbalance_of(loads: pd.Series) -> float:
    """Grouped aggregate: greatest load by the mean."""
    return float(loads.max() / loads.mean())


def register(spark: SparkSession) -> None:
    """SQL functions tile_of and cut_error, which the optimizer inlines, and the table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tile_of(x BIGINT, n BIGINT, lx BIGINT) RETURNS BIGINT RETURN (x * n) div lx")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cut_error(s BIGINT, w BIGINT, p BIGINT, pl BIGINT) RETURNS BIGINT RETURN abs(s * p - w * pl)")
    spark.udtf.register("share_cut_udtf", ShareCut)
    spark.udtf.register("pair_schedule", PairSchedule)
    spark.udf.register("imbalance_of", imbalance_of)


def column_exchange(lines: DataFrame, borders: DataFrame, t: int) -> DataFrame:
    """Row borders of every column after one step, each column by itself.

    lines: (col, line, w) for all lines; borders: (col, pos, line) of inner borders, pos from 1."""

    def one(key, ls: pd.DataFrame, bs: pd.DataFrame) -> pd.DataFrame:
        w = ls.sort_values("line")["w"].to_numpy()
        bs = bs.sort_values("pos")
        edge = [0, *bs["line"].tolist(), len(w)]
        s = np.concatenate([[0], np.cumsum(w)])
        for _, r, low in pairs((len(edge) - 1,), t):
            a, b, old = edge[r], edge[low + 1], edge[low]
            edge[low] = min(range(a + 1, b), key=lambda q: (abs(2 * (s[q] - s[a]) - (s[b] - s[a])), abs(q - old), q))
        return pd.DataFrame({"col": key[0], "pos": bs["pos"], "line": edge[1:-1]})

    return lines.groupBy("col").cogroup(borders.groupBy("col")).applyInPandas(one, "col long, pos long, line long")


def rotated(vx: str, vy: str, angle: float):
    """Velocities turned by an angle, as an Arrow scalar function; pic.push has the same in SQL."""
    c, s = float(np.cos(angle)), float(np.sin(angle))

    @arrow_udf("struct<vx:bigint,vy:bigint>")
    def turn(a: pa.Array, b: pa.Array) -> pa.Array:
        half = lambda v: pc.cast(pc.round(v, round_mode="half_towards_infinity"), pa.int64())
        a, b = pc.cast(a, pa.float64()), pc.cast(b, pa.float64())
        x, y = pc.add(pc.multiply(a, c), pc.multiply(b, s)), pc.subtract(pc.multiply(b, c), pc.multiply(a, s))
        return pa.StructArray.from_arrays([half(x), half(y)], ["vx", "vy"])

    return turn(F.col(vx), F.col(vy))
