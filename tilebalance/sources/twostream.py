"""A Python data source of the two-stream start, in batch and as a stream, with pushed tile ranges."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThanOrEqual, InputPartition, LessThan, SimpleDataSourceStreamReader


def _rows(first: int, last: int, n: int, lx: int, ly: int, v0: int) -> dict[str, np.ndarray]:
    i = np.arange(first, last, dtype=np.int64)
    even = np.floor(i * (lx / n)).astype(np.int64)
    angle = lx / 1000 * np.cos(2 * np.pi / lx * even)
    shift = np.where(angle >= 0, np.floor(angle + 0.5), np.ceil(angle - 0.5)).astype(np.int64)
    return {"pid_key": i, "x": (even + shift) % lx, "y": i * 648_056 % ly, "vx": np.where(i % 2 == 0, v0, -v0), "vy": np.zeros(len(i), np.int64), "weight": np.ones(len(i), np.int64), "species": i % 2}


class TwoStream(DataSource):
    """Options: n, lx, ly, v0, parts; for streams, rows per batch; pushdown=1 where the session has spark.sql.python.filterPushdown.enabled."""

    @classmethod
    def name(cls) -> str:
        return "two_stream"

    def schema(self) -> str:
        return "pid_key long, x long, y long, vx long, vy long, weight long, species long"

    def _numbers(self) -> dict[str, int]:
        asked = {k.lower(): int(v) for k, v in self.options.items()}
        return {"n": 1000, "lx": 1 << 20, "ly": 1 << 20, "v0": 1 << 12, "parts": 8, "rows": 100, "pushdown": 0} | asked

    def reader(self, schema):
        how = self._numbers()
        return PushedReader(how) if how["pushdown"] else TwoStreamReader(how)

    def simpleStreamReader(self, schema):
        return TwoStreamBatches(self._numbers())


class Span(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class TwoStreamReader(DataSourceReader):
    """x rises with the particle's number but for the small cosine, so ranges of x become ranges of numbers."""

    def __init__(self, how: dict[str, int]):
        self.how, self.low, self.high, self.species = how, 0, how["n"], None

    def partitions(self) -> list[Span]:
        k = max(1, self.how["parts"])
        wide = max(0, self.high - self.low)
        return [Span(self.low + wide * i // k, self.low + wide * (i + 1) // k) for i in range(k)]

    def read(self, partition: Span) -> Iterator[pa.RecordBatch]:
        h = self.how
        for at in range(partition.first, partition.last, 100_000):
            columns = _rows(at, min(at + 100_000, partition.last), h["n"], h["lx"], h["ly"], h["v0"])
            if self.species is not None:
                keep = columns["species"] == self.species
                columns = {k: v[keep] for k, v in columns.items()}
            yield pa.RecordBatch.from_pydict({k: pa.array(v, pa.int64()) for k, v in columns.items()})


class PushedReader(TwoStreamReader):
    def pushFilters(self, filters) -> Iterator:
        n, lx = self.how["n"], self.how["lx"]
        slack = lx // 1000 + 1
        for f in filters:
            if isinstance(f, GreaterThanOrEqual) and f.attribute == ("x",) and slack <= f.value < lx - slack:
                self.low = max(self.low, int((f.value - slack) * n // lx))
            elif isinstance(f, LessThan) and f.attribute == ("x",) and slack < f.value <= lx - slack:
                # a particle near the start may be thrown to the far end, never the other way
                self.high = min(self.high, int((f.value + slack) * n // lx) + 1)
            elif isinstance(f, EqualTo) and f.attribute == ("species",):
                self.species = f.value
            yield f  # spans only narrow what is made; Spark still tests every row


class TwoStreamBatches(SimpleDataSourceStreamReader):
    def __init__(self, how: dict[str, int]):
        self.how = how

    def initialOffset(self) -> dict:
        return {"at": 0}

    def _tuples(self, first: int, last: int) -> Iterator[tuple]:
        h = self.how
        columns = _rows(first, last, h["n"], h["lx"], h["ly"], h["v0"])
        return iter(list(zip(*(v.tolist() for v in columns.values()), strict=True)))

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        last = min(start["at"] + self.how["rows"], self.how["n"])
        return self._tuples(start["at"], last), {"at": last}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return self._tuples(start["at"], end["at"])
