"""Snapshots of particles by step and owner, and plain files for trees and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.exprs import interleave
from ..operators.grid import Grid, locate
from ..operators.placement import by_owner


def write_snapshot(particles: DataFrame, path: str, t: int, grid: Grid, parts: int) -> None:
    """Particles with owners under t=/owner=, each owner's rows together and near tiles near each other, so that later reads skip."""
    rows = by_owner(locate(particles, grid), parts).sortWithinPartitions("owner", interleave(F.col("ti"), F.col("tj")))
    rows.withColumn("t", F.lit(t)).write.mode("append").partitionBy("t", "owner").parquet(path)


def read_snapshot(spark: SparkSession, path: str, t: int | None = None, owner: int | None = None) -> DataFrame:
    """A snapshot; step and owner prune folders, tile ranges asked of the result prune row groups."""
    df = spark.read.parquet(path)
    df = df if t is None else df.where(F.col("t") == t)
    return df if owner is None else df.where(F.col("owner") == owner)


def write_bucketed(particles: DataFrame, name: str, buckets: int, key: str = "owner") -> None:
    """A table whose later joins by owner need no shuffle; for owners too many for folders."""
    particles.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def write_plain(df: DataFrame, path: str, kind: str) -> None:
    """csv, json, orc or text (one JSON document per line)."""
    if kind == "text":
        df.select(F.to_json(F.struct("*")).alias("value")).write.mode("overwrite").text(path)
    else:
        df.write.mode("overwrite").format(kind).options(**({"header": "true"} if kind == "csv" else {})).save(path)


def read_plain(spark: SparkSession, path: str, kind: str, schema) -> DataFrame:
    if kind == "text":
        return spark.read.text(path).select(F.from_json("value", schema).alias("v")).select("v.*")
    return spark.read.schema(schema).options(**({"header": "true"} if kind == "csv" else {})).format(kind).load(path)
