"""Shared plumbing of the corpus operators: stored intermediates, connected components, word hashes."""

from __future__ import annotations

import atexit
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Java pattern of the separators between words.
SPACES = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
_stored: list[tuple[SparkSession, str]] = []
_paths: dict[int, tuple[weakref.ref, str]] = {}


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder all executors share; a temporary one only where a session on a single machine names none."""
    context = spark.sparkContext
    found = context._jsc.sc().getCheckpointDir()
    if not found.isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local"):
            raise ValueError("a cluster needs spark.checkpoint.dir, a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="tilebalance-"))
        found = context._jsc.sc().getCheckpointDir()
    return found.get()


def stash(df: DataFrame, label: str) -> DataFrame:
    """Cut lineage: write to the shared folder and read back, so that a lost executor costs nothing done before.

    Files are removed when the driver's program ends, or by `discard`. What earlier steps shuffled is not needed again:
    collecting the driver's garbage has Spark remove it from the disks now, not when the driver's memory runs short."""
    spark = df.sparkSession
    spark.sparkContext._jvm.System.gc()
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    spark.sparkContext._jvm.System.gc()
    if not _stored:
        atexit.register(_forget)
    stored = spark.read.schema(df.schema).parquet(path)
    _stored.append((spark, path))
    _paths[id(stored)] = weakref.ref(stored), path
    return stored


def discard(*stored: DataFrame) -> None:
    """Remove the files of what was stashed; nothing that still has to read them may follow."""
    for df in stored:
        _, path = _paths.pop(id(df))
        _stored.remove((df.sparkSession, path))
        _delete(df.sparkSession, path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(conf).delete(where, True)


def _forget() -> None:
    for spark, path in _stored:
        try:
            _delete(spark, path)
        except Exception:  # noqa: BLE001  the session has ended before: the files stay in the checkpoint folder
            return


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(name: str, *frames: DataFrame) -> str:
    """A column name like this one that none of the frames has, whatever the case of letters."""
    taken = {c.lower() for frame in frames for c in frame.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, component): the smallest node reachable over the undirected edges (a, b), for each node of an edge.

    Alternates the large-star and small-star rewrites. Each is a minimum per node, combined before the
    shuffle, and a join that Spark may split, so a node with very many links needs no single task."""
    now = stash(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    last = None
    while True:
        n, mark, apart = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.count_distinct("u")).first()
        if n == 0 or (n, mark) == last:
            break
        last = (n, mark)
        if n == apart and now.select("u").join(now.select(F.col("v").alias("u")), "u", "left_semi").isEmpty():
            break
        both = now.union(now.select("v", "u"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        lower = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(lower, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(lower.select("u", F.col("m").alias("v")))
        before, now = now, stash(small.distinct(), "edges")
        discard(before)
    roots = now.select(F.col("v").alias("node")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots.select("node", F.col("node").alias("component")))
