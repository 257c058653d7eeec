"""Scalar expressions over tiles and coordinates."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def interleave(a: Column, b: Column, bits: int = 16) -> Column:
    """The bits of two whole numbers in turn, lowest first: a key that keeps near tiles near."""
    key = F.lit(0).cast("long")
    for k in range(bits):
        for shift, part in ((2 * k, a), (2 * k + 1, b)):
            key = key.bitwiseOR(F.shiftleft(F.shiftright(part.cast("long"), k).bitwiseAND(F.lit(1)), shift))
    return key


def snapshot(pid: str = "pid", load: str = "load") -> Column:
    """Aggregate: a map of owners to loads."""
    return F.map_from_entries(F.array_sort(F.collect_list(F.struct(pid, load))))
