"""Balancing between neighbours only: diffusion on a graph of owners, coloured pairs, and borders of strips."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .cost import LoadMap
from .grid import div
from .lineage import stored
from .partition import Cut

#: Steps after which loads are stored: a step's plan holds that of the step before several times.
STORED = 2


def diffuse(loads: DataFrame, links: DataFrame, alpha: float | str = "uniform", created: DataFrame | None = None, consumed: DataFrame | None = None, steps: int = 1, store=stored) -> DataFrame:
    """(t, pid, load) after each of 0..steps: every link carries alpha of its ends' difference, and load is created and consumed.

    loads: (pid, load). links: (a, b), with a column alpha of their own if alpha is `link`. `uniform` is 1 / (largest
    degree + 1). created, consumed: (pid, load) per step. Loads are stored every other step, so the plan stays
    in proportion to the steps."""
    both = links.select("a", "b", *(["alpha"] if alpha == "link" else [])).unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"), *(["alpha"] if alpha == "link" else [])))
    if alpha == "uniform":
        widest = both.groupBy("a").count().agg(F.max("count").alias("degree"))
        both = both.join(F.broadcast(widest.select((1.0 / (F.col("degree") + 1)).alias("alpha"))))
    elif alpha != "link":
        both = both.withColumn("alpha", F.lit(float(alpha)))
    given = None
    for df, sign in ((created, 1), (consumed, -1)):
        if df is not None:
            part = df.select("pid", (sign * F.col("load").cast("double")).alias("g"))
            given = part if given is None else given.union(part)
    now = loads.select("pid", F.col("load").cast("double").alias("load"))
    out = now.select(F.lit(0).cast("long").alias("t"), "pid", "load")
    for t in range(1, steps + 1):
        a, b = now.select(F.col("pid").alias("a"), F.col("load").alias("mine")), now.select(F.col("pid").alias("b"), F.col("load").alias("theirs"))
        flow = both.join(a, "a").join(b, "b").select(F.col("a").alias("pid"), (F.col("alpha") * (F.col("theirs") - F.col("mine"))).alias("g"))
        flow = flow if given is None else flow.union(given)
        now = now.join(flow.groupBy("pid").agg(F.sum("g").alias("g")), "pid", "left").select("pid", (F.col("load") + F.coalesce("g", F.lit(0.0))).alias("load"))
        now = store(now) if t % STORED == 0 else now
        out = out.union(now.select(F.lit(t).cast("long").alias("t"), "pid", "load"))
    return out


def colour_grid(spark: SparkSession, rows: int, columns: int, torus: bool = False) -> DataFrame:
    """LINK of a grid of owners numbered row by row from 0, in four staggered colours: no owner has two links of a colour.

    Horizontal links have colours 1 and 2, vertical ones 3 and 0. A torus needs even sizes."""
    if torus and (rows % 2 or columns % 2):
        raise ValueError("a torus in four colours needs even sizes")
    cells = spark.range(rows * columns).select(div(F.col("id"), columns).alias("r"), F.pmod("id", F.lit(columns)).alias("c"))
    odd = F.pmod(F.col("r") + F.col("c"), F.lit(2)) == 1
    here = F.col("r") * columns + F.col("c")
    right, down = F.pmod(F.col("c") + 1, F.lit(columns)), F.pmod(F.col("r") + 1, F.lit(rows))
    across = cells.where("true" if torus and columns > 2 else f"c + 1 < {columns}").select(here.alias("a"), (F.col("r") * columns + right).alias("b"), F.when(odd, 1).otherwise(2).cast("long").alias("colour"))
    along = cells.where("true" if torus and rows > 2 else f"r + 1 < {rows}").select(here.alias("a"), (down * columns + F.col("c")).alias("b"), F.when(odd, 3).otherwise(0).cast("long").alias("colour"))
    return across.union(along)


def active(links: DataFrame, t: int) -> DataFrame:
    """Links whose turn step t is; owners without one idle."""
    return links.where(F.col("colour") == t % 4)


def exchange(loads: DataFrame, links: DataFrame, steps: int, store=stored) -> DataFrame:
    """(t, pid, load) after each of 0..steps, the active pairs of each step meeting at their mean; stored every other step."""
    now = loads.select("pid", F.col("load").cast("double").alias("load"))
    out = now.select(F.lit(0).cast("long").alias("t"), "pid", "load")
    for t in range(1, steps + 1):
        turn = active(links, t)
        pair = turn.select("a", "b").union(turn.select("b", "a"))
        other = pair.join(now.select(F.col("pid").alias("b"), F.col("load").alias("theirs")), "b").select(F.col("a").alias("pid"), "theirs")
        now = now.join(other, "pid", "left").select("pid", F.when(F.col("theirs").isNull(), F.col("load")).otherwise((F.col("load") + F.col("theirs")) / 2).alias("load"))
        now = store(now) if t % STORED == 0 else now
        out = out.union(now.select(F.lit(t).cast("long").alias("t"), "pid", "load"))
    return out


def chain(spark: SparkSession, n: int) -> DataFrame:
    """LINK of a chain: odd steps pair 0-1, 2-3, ..., even ones 1-2, 3-4, ... ."""
    pairs = spark.range(n - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    return pairs.select("a", "b", F.explode(F.when(F.pmod("a", F.lit(2)) == 0, F.array(F.lit(1), F.lit(3))).otherwise(F.array(F.lit(0), F.lit(2))).cast("array<bigint>")).alias("colour"))


def volume(w_a: float, w_b: float, unit: float) -> int:
    """Whole tiles of a cost that half the difference of two loads amounts to."""
    return int(abs(w_a - w_b) / 2 // unit)


def convergence(history: DataFrame) -> DataFrame:
    """(t, spread, total) of each step."""
    return history.groupBy("t").agg((F.max("load") - F.min("load")).alias("spread"), F.sum("load").alias("total"))


def pairs(rows: tuple[int, ...], t: int) -> list[tuple[int, int, int]]:
    """(column, upper, lower) rows that meet at step t: 1-2, 3-4 at odd steps, 2-3, 4-5 at even ones; the pair of a column of two always."""
    out = []
    for c, count in enumerate(rows):
        start = 0 if t % 2 or count == 2 else 1
        out += [(c, r, r + 1) for r in range(start, count - 1, 2)]
    return out


def _nearest(s: np.ndarray, low: int, old: int) -> int:
    """The inner line at which twice the running cost is nearest to the total; the least moved, then the smallest."""
    inner = range(1, len(s) - 1)
    return low + min(inner, key=lambda i: (abs(2 * int(s[i]) - int(s[-1])), abs(low + i - old), i))


def strip_exchange(cut: Cut, loads: LoadMap, t: int, column_period: int | None = None, eps: float = 0.0) -> Cut:
    """Strips after step t: pairs of rows move their common border, and every column_period steps columns theirs.

    Only pairs whose loads differ by more than eps of an owner's mean act. Columns pair like rows, by the parity of
    their own count of steps; their rows' borders are kept."""
    first = cut.first_dim
    rows = cut.rows
    starts = np.cumsum([0, *rows])
    boxes = [list(x.box) for x in cut.leaves]
    lo, hi = (2, 3) if first == "x" else (0, 1)
    mean = loads.total / max(1, len(boxes))
    for c, r, _ in pairs(rows, t):
        up, down = boxes[starts[c] + r], boxes[starts[c] + r + 1]
        if abs(loads.box(*up) - loads.box(*down)) <= eps * mean:
            continue
        both = list(up)
        both[hi] = down[hi]
        up[hi] = down[lo] = _nearest(loads.running(*both, "y" if first == "x" else "x"), both[lo], up[hi])
    if column_period and t % column_period == 0:
        lo, hi = (0, 1) if first == "x" else (2, 3)
        count = len(rows)
        turn = t // column_period
        for c in range(0 if turn % 2 or count == 2 else 1, count - 1, 2):
            left, right = boxes[starts[c] : starts[c + 1]], boxes[starts[c + 1] : starts[c + 2]]
            whole = [left[0][0], right[0][1], 0, loads.m] if first == "x" else [0, loads.n, left[0][2], right[0][3]]
            border = left[0][hi]
            s = loads.running(*whole, first)
            shares = (len(left), len(right))
            inner = range(1, len(s) - 1)
            new = whole[lo] + min(inner, key=lambda i: (abs(int(s[i]) * sum(shares) - int(s[-1]) * shares[0]), abs(whole[lo] + i - border), i))  # noqa: B023
            for b in left:
                b[hi] = new
            for b in right:
                b[lo] = new
    leaves = tuple(replace(x, x0=b[0], x1=b[1], y0=b[2], y1=b[3], load=loads.box(*b)) for x, b in zip(cut.leaves, boxes, strict=True))
    return replace(cut, leaves=leaves)
