"""Declared schemas; rectangles are half-open in tile units."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

_KINDS = {"long": T.LongType(), "string": T.StringType(), "double": T.DoubleType(), "boolean": T.BooleanType()}


def _of(text: str) -> T.StructType:
    return T.StructType([T.StructField(name, _KINDS[kind]) for name, kind in (x.split(":") for x in text.split())])


PARTICLE = _of("pid_key:long x:long y:long vx:long vy:long weight:long species:long")
TILE_LOAD = _of("ti:long tj:long particles:long elements:long cost:long")
CUT_TREE = _of("node:long depth:long dim:string cut:long x0:long x1:long y0:long y1:long p_first:long p_count:long load:long is_leaf:boolean")
SUBDOMAIN = _of("pid:long x0:long x1:long y0:long y1:long height:long load:long")
TILE_OWNER = _of("ti:long tj:long pid:long")
LINK = _of("a:long b:long colour:long")
PROC_LOAD = _of("t:long pid:long load:long")
STEP_METRIC = _of(
    "t:long particles:long max_load:long mean_load:double imbalance:double tiles_moved:long particles_moved:long "
    "perimeter:long max_aspect:double elements_seen_max:long syncs:long rebalanced:boolean wall_ms:double"
)
ELEMENT = T.StructType(
    [
        T.StructField("elem", T.LongType()),
        T.StructField("kind", T.StringType()),
        T.StructField("verts", T.ArrayType(T.StructType([T.StructField("x", T.LongType()), T.StructField("y", T.LongType())]))),
        T.StructField("bx", T.LongType()),
        T.StructField("by", T.LongType()),
    ]
)


def expect(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df, if it has the schema's columns with their types; others may follow."""
    have = {f.name: f.dataType for f in df.schema}
    wrong = [f"{f.name}: {f.dataType.simpleString()} wanted, {have[f.name].simpleString() if f.name in have else 'missing'}" for f in schema if have.get(f.name) != f.dataType]
    if wrong:
        raise TypeError("; ".join(wrong))
    return df
