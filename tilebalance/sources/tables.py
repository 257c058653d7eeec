"""The given tables, and each of them as particles or weighted items with whole coordinates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.grid import Grid
from ..schema import PARTICLE, expect

#: Domain of each adapter (lx, ly).
DOMAINS = {
    "EV": (2_592_000_000_000, 65_536),
    "LP": (16_777_216, 4_096),
    "LQ": (16_777_216, 64),
    "OR": (67_108_864, 4_096),
    "EM": (2_097_152, 2_097_152),
    "DOC": (65_536, 32),
    "PG": (65_536, 65_536),
    "CV": (65_536, 32),
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def grid_of(adapter: str, n: int = 32, m: int | None = None, boundary: str = "periodic") -> Grid:
    return Grid(n, m or n, *DOMAINS[adapter], boundary)


def _cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def _sign(c: str) -> Column:
    return F.when(F.pmod(F.col(c), F.lit(2)) == 0, 1).otherwise(-1)


def _days(c: str) -> Column:
    return F.pmod(F.datediff(F.to_date(c), F.lit("1995-01-01")), F.lit(4096))


def _particles(df: DataFrame, *columns) -> DataFrame:
    names = PARTICLE.fieldNames()
    return expect(df.select(*[(c if isinstance(c, Column) else F.lit(c)).cast("long").alias(n) for c, n in zip(columns, names, strict=True)]), PARTICLE)


def events_particles(df: DataFrame, weight: Column | int = 1) -> DataFrame:
    lx, ly = DOMAINS["EV"]
    x = F.pmod(F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01', ts)"), F.lit(lx))
    return _particles(df, F.col("event_id"), x, F.pmod(_cents("value"), F.lit(ly)), _sign("event_id") * F.lit(lx // 256), (F.pmod(F.col("user_id"), F.lit(7)) - 3) * F.lit(ly // 512), weight, F.pmod(F.col("event_id"), F.lit(2)))


def json_weight() -> Column:
    """The whole number k of an event's properties."""
    return F.get_json_object("props", "$.k").cast("long")


def lineitem_particles(df: DataFrame) -> DataFrame:
    """Lines by price and day; they have no key, so pid_key is null."""
    return _particles(df, F.lit(None), F.pmod(_cents("l_extendedprice"), F.lit(DOMAINS["LP"][0])), _days("l_shipdate"), _sign("l_suppkey") * 65_536, 0, 1, F.pmod(F.col("l_suppkey"), F.lit(2)))


def quantity_particles(df: DataFrame) -> DataFrame:
    """Lines by price and quantity, strongly correlated."""
    q = F.col("l_quantity").cast("long")
    return _particles(df, F.lit(None), F.pmod(_cents("l_extendedprice"), F.lit(DOMAINS["LQ"][0])), F.pmod(q - 1, F.lit(64)), (q - 25) * 4_096, 1, 1, F.pmod(F.col("l_linenumber"), F.lit(2)))


def orders_particles(df: DataFrame) -> DataFrame:
    return _particles(df, F.col("o_orderkey"), F.pmod(_cents("o_totalprice"), F.lit(DOMAINS["OR"][0])), _days("o_orderdate"), _sign("o_orderkey") * 262_144, 1, 1, F.pmod(F.col("o_orderkey"), F.lit(2)))


def embedding_particles(df: DataFrame) -> DataFrame:
    e = [F.get("embedding", F.lit(i)).cast("double") for i in range(4)]
    return _particles(df, F.col("vec_id"), F.floor((e[0] + 1) * 2**20), F.floor((e[1] + 1) * 2**20), F.floor(e[2] * 2**14), F.floor(e[3] * 2**14), 1, F.pmod(F.col("label"), F.lit(2)))


def _scattered(key: str) -> Column:
    return F.pmod(F.col(key) * 40_503, F.lit(65_536))


def document_items(df: DataFrame) -> DataFrame:
    """Documents by scattered id and the number in the name of their source; 0 for a name without one."""
    number = F.when(F.col("source").isNotNull(), F.coalesce(F.regexp_extract("source", r"(\d+)", 1).try_cast("long"), F.lit(0).cast("long")))
    return _particles(df, F.col("doc_id"), _scattered("doc_id"), number, 0, 0, F.col("n_chars"), 0)


def page_items(df: DataFrame) -> DataFrame:
    return _particles(df, F.col("page_id"), _scattered("page_id"), F.least(F.length("html"), F.lit(65_535)), 0, 0, F.length("html"), 0)


def conversation_items(df: DataFrame) -> DataFrame:
    return _particles(df, F.col("conv_id"), _scattered("conv_id"), F.pmod(F.col("turn"), F.lit(32)), 0, 0, F.length("text"), 0)


ADAPTERS = {
    "EV": ("events", events_particles),
    "LP": ("lineitem", lineitem_particles),
    "LQ": ("lineitem", quantity_particles),
    "OR": ("orders", orders_particles),
    "EM": ("embeddings", embedding_particles),
    "DOC": ("documents", document_items),
    "PG": ("pages", page_items),
    "CV": ("conversations", conversation_items),
}


def particles(spark: SparkSession, sf_dir: str, adapter: str) -> DataFrame:
    """A table as particles; only the columns that an adapter reads are scanned."""
    name, make = ADAPTERS[adapter]
    return make(load(spark, sf_dir, name))


def two_stream(spark: SparkSession, n: int, lx: int = 1 << 20, ly: int = 1 << 20, v0: int = 1 << 12, partitions: int | None = None) -> DataFrame:
    """Two beams of n particles together, evenly spread along x but for a small cosine, low-discrepancy along y."""
    i = F.col("id")
    even = F.floor(i * F.lit(lx / n)).cast("long")
    shift = F.round(F.lit(lx / 1000) * F.cos(F.lit(2 * 3.141592653589793 / lx) * even)).cast("long")
    ranged = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    return _particles(ranged, i, F.pmod(even + shift, F.lit(lx)), F.pmod(i * 648_056, F.lit(ly)), F.when(F.pmod(i, F.lit(2)) == 0, v0).otherwise(-v0), 0, 1, F.pmod(i, F.lit(2)))
