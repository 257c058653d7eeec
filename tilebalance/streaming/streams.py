"""Loads over event time, owners that follow the stream, and rebalancing by micro-batch."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Callable, Iterator
from pathlib import Path

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators.cost import LoadMap, gather, tile_load
from ..operators.grid import Grid, locate
from ..operators.lineage import shared
from ..operators.partition import Cut, share_cut, tethered_or_full
from ..operators.placement import BROADCAST_TILES


def events(spark: SparkSession, path: str, files: int = 1, late: str = "2 days") -> DataFrame:
    """The events as a stream with a watermark; times are taken as UTC."""
    schema = spark.read.parquet(path).schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    folder, name = path.rsplit("/", 1)
    stream = source.option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") and _is_file(spark, path) else source.parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def _is_file(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(where).isFile()


def place(stream: DataFrame, grid: Grid) -> DataFrame:
    """Events with their tile, by the same whole-number rule as the batch adapter."""
    micros = F.unix_micros("ts") - F.lit(1_704_067_200_000_000)
    return locate(stream.withColumns({"x": F.pmod(micros, F.lit(grid.lx)), "y": F.pmod(F.round(F.col("value") * 100).cast("long"), F.lit(grid.ly))}), grid)


def tumbling(stream: DataFrame, grid: Grid, size: str = "1 day") -> DataFrame:
    return place(stream, grid).groupBy(F.window("ts", size).alias("w"), "ti", "tj").agg(F.count("*").alias("load")).select(F.unix_seconds("w.start").alias("start_s"), "ti", "tj", "load")


def sliding(stream: DataFrame, size: str = "3 days", slide: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", size, slide).alias("w"), "event_type").agg(F.count("*").alias("load")).select(F.unix_seconds("w.start").alias("start_s"), "event_type", "load")


def sessions(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("load")).select("user_id", F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "load")


def owned(stream: DataFrame, tile_owner: DataFrame, grid: Grid) -> DataFrame:
    """A stream with the owners of a mapping that stands still; it has one row for each tile, and is broadcast only if the grid allows."""
    return place(stream, grid).join(F.broadcast(tile_owner) if grid.tiles <= BROADCAST_TILES else tile_owner, ["ti", "tj"])


def follow_ups(stream: DataFrame, first: str = "view", then: str = "purchase", within: str = "1 hour") -> DataFrame:
    """Pairs of a user's events of two types, the second within a time of the first, once for each pair of event ids."""
    a = stream.where(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u"), F.col("ts").alias("first_ts"))
    b = stream.where(F.col("event_type") == then).select(F.col("event_id").alias("then_id"), "user_id", "ts")
    return a.join(b, F.expr(f"u = user_id AND ts >= first_ts AND ts <= first_ts + INTERVAL {within}")).select("first_id", "then_id", "user_id")


def once(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"])


class OwnerLoad(StatefulProcessor):
    """Load of each owner so far, and a signal when it passes a bar and again only after it grew by a margin."""

    bar, margin = 100, 0.5

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.load = handle.getValueState("load", "load long, told long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        load, told = self.load.get() if self.load.exists() else (0, 0)
        load += sum(len(x) for x in rows)
        signal = load >= self.bar and (not told or load >= told * (1 + self.margin))
        told = load if signal else told
        self.load.update((load, told))
        yield pd.DataFrame({"owner": [key[0]], "load": [load], "signal": [signal]})

    def close(self) -> None:
        pass


def owner_loads(stream: DataFrame) -> DataFrame:
    """(owner, load, signal) of an owned stream, as it changes; state lives in the session's state store."""
    return stream.withColumnRenamed("pid", "owner").groupBy("owner").transformWithStateInPandas(OwnerLoad(), "owner long, load long, signal boolean", "Update", "None")


class Rebalancer:
    """A foreachBatch sink: each micro-batch is a step. Its load is added, and the cut limited or remade.

    Batches that come again after a restart are known by their number and change nothing."""

    def __init__(self, grid: Grid, parts: int, level: int | None = None, theta: float = 1.25):
        self.grid, self.parts, self.level, self.theta = grid, parts, level, theta
        self.cost, self.cut, self.done, self.history = None, None, -1, []

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.done:
            return
        counted = gather(tile_load(batch, self.grid), self.grid).cost
        self.cost = counted if self.cost is None else self.cost + counted
        loads = LoadMap(self.cost)
        if self.cut is None:
            self.cut, full = share_cut(loads, self.parts), True
        else:
            self.cut, full = tethered_or_full(self.cut.reloaded(loads), loads, self.level, self.theta)
        self.done = number
        self.history.append((number, loads.total, max(self.cut.loads()), full))

    def mapping(self) -> Cut:
        return self.cut


def _remove(spark: SparkSession, path: str) -> None:
    try:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001  the session has ended before: the files stay in the checkpoint folder
        return


def collected(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """The rows a bounded stream gives, after all of its input has been read.

    They are written to the shared folder, never held by the driver: in complete mode each batch holds all rows so far, so
    the last one is the result. Files are removed when the driver's program ends, state as soon as the stream has."""
    spark = stream.sparkSession
    shared(spark)
    path = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/stream-{uuid.uuid4().hex}"
    out, state, numbers = f"{path}/rows", f"{path}-state", []
    atexit.register(_remove, spark, path)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{number}")
        numbers.append(number)

    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True)
    try:
        (writer.format("parquet").start(out) if mode == "append" else writer.foreachBatch(keep).start()).awaitTermination()
    finally:
        _remove(spark, state)
    found = [out] if mode == "append" else [f"{out}/{n}" for n in (numbers[-1:] if mode == "complete" else numbers)]
    return spark.read.schema(stream.schema).parquet(*found) if found else spark.createDataFrame([], stream.schema)


def drained(stream: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str | Path) -> None:
    """Run a foreachBatch sink over all the input there is."""
    stream.writeStream.foreachBatch(sink).option("checkpointLocation", str(checkpoint)).trigger(availableNow=True).start().awaitTermination()
