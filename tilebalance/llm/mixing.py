"""Mixing sources to target sizes by entropy balancing, with DataFrame operations alone.

Every document has a rate between 0 and `most`, the nearest in relative entropy to one copy each among
all rates whose sizes sum to the source's target. The dual of that problem is convex: a rate is
exp(tilt * size), cut off at `most`, and each source's tilt solves one equation. Newton's steps solve it
for all sources at once, safeguarded by a bracket; each is an aggregate over the counts of equal sizes in
each source, which do not grow with the number of documents of a size.

Rates become whole copies: over the sizes of a source in falling order the fractions are carried on, so
that copies never lag behind rates by a document, and what is left of the target goes to the largest size
that fits, again and again. Which documents of equal size get one more is decided by a hash of doc_id."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, stash

#: Weights of the sources in turn, the share of all words to take, copies at most.
WEIGHTS, SHARE, MOST = (5, 2, 1), 1.5, 2
_SALTS = 64


def words(text: str = "text") -> Column:
    """Words of a text; 0 if null."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """(source, source_size, target) from (source, source_size).

    Sources weigh `weights` in turn, by code point with null last, and share `share` of all sizes; a target
    stops at `most` times its source's size and what is above is shared anew. The level at which all
    targets are reached is found by going through the sources in the order in which they stop."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    rank = F.row_number().over(order) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights) + 1).cast("int"))
    ranked = sizes.select("source", F.col("source_size").cast("double").alias("size"), "source_size", weight.alias("w")).withColumn("stop", F.lit(float(most)) * F.col("size") / F.col("w"))
    by_stop = Window.orderBy("stop", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    level = (F.lit(share) * F.sum("size").over(whole) - F.lit(float(most)) * F.coalesce(F.sum("size").over(by_stop), F.lit(0.0))) / (F.sum("w").over(whole) - F.coalesce(F.sum("w").over(by_stop), F.lit(0.0)))
    levels = ranked.withColumn("level", level)
    # the first source, in that order, that the level does not stop has the true level
    true_level = F.min(F.when(F.col("level") <= F.col("stop"), F.struct("stop", "level"))).over(whole)["level"]
    return levels.withColumn("true", true_level).select("source", "source_size", F.coalesce(F.least(F.col("w") * F.col("true"), most * F.col("size")), most * F.col("size")).alias("target"))


def tilts(cells: DataFrame, targets: DataFrame, most: int = MOST, tolerance: float = 1e-9) -> DataFrame:
    """(source, target, source_size, scale, tilt) of each source that can reach its target below `most` copies each; tilt is per `scale` words.

    Newton's steps are taken until all targets are met, or a tilt's bracket holds no other number. cells: (source, size, n) with size > 0. Where every document must be taken `most` times, tilt is null."""
    scales = cells.groupBy("source").agg((F.sum(F.col("n") * F.col("size")) / F.sum("n")).alias("scale"), F.min("size").alias("least"))
    state = targets.join(scales, targets["source"].eqNullSafe(scales["source"])).drop(scales["source"])
    bounded = F.col("target") < F.lit(float(most)) * F.col("source_size") * (1 - 1e-12)
    # at the upper end even the smallest document is taken `most` times; the lower end is found by doubling
    state = stash(state.select("*", F.when(bounded, F.lit(0.0)).alias("tilt"), F.lit(None).cast("double").alias("low"), (F.lit(1e-9) + F.log(F.lit(float(most))) * F.col("scale") / F.col("least")).alias("high"), F.lit(False).alias("done")), "tilts")
    while True:
        a, s = cells.alias("c"), state.where("tilt is not null").alias("s")
        x = F.col("c.size") / F.col("s.scale")
        rate = F.least(F.exp(F.least(F.col("s.tilt") * x, F.lit(700.0))), F.lit(float(most)))
        sums = a.join(s, F.col("c.source").eqNullSafe(F.col("s.source"))).groupBy(F.col("s.source").alias("source")).agg(
            F.sum(F.col("c.n") * F.col("c.size") * rate).alias("got"),
            F.sum(F.when(rate < most, F.col("c.n") * F.col("c.size") * rate * x)).alias("slope"),
        )
        got = state.join(sums, state["source"].eqNullSafe(sums["source"]), "left").drop(sums["source"])
        over = F.col("got") > F.col("target")
        low, high = F.when(over, F.col("low")).otherwise(F.greatest("low", "tilt")), F.when(over, F.least("high", "tilt")).otherwise(F.col("high"))
        newton = F.col("tilt") + (F.col("target") - F.col("got")) / F.nullif("slope", F.lit(0.0))
        got = got.withColumns({"low": low, "high": high, "next": newton, "done": F.col("tilt").isNull() | (F.abs(F.col("got") - F.col("target")) <= tolerance * F.greatest("target", F.lit(1.0)))})
        inside = (F.col("next") > F.coalesce("low", F.col("high") - 2 * (F.col("high") - F.col("tilt")) - 1)) & (F.col("next") < F.col("high"))
        halved = F.coalesce((F.col("low") + F.col("high")) / 2, 2 * F.col("tilt") - 1)
        moved = F.when(F.col("tilt").isNull() | F.col("done"), F.col("tilt")).when(inside, F.col("next")).otherwise(halved)
        got = got.withColumn("moved", moved).withColumn("done", F.col("done") | (F.col("moved") == F.col("tilt"))).withColumn("tilt", F.col("moved")).drop("moved")
        state = stash(got.drop("got", "slope", "next"), "tilts")
        if state.where("not done").isEmpty():
            break
    return state


def mixed(docs: DataFrame, size: Column, source: str = "source", key: str = "doc_id", weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST, repairs: int = 6) -> DataFrame:
    """(key, size, source_size, target, copies, taken) of each row of docs.

    Rows of size 0 get one copy of nothing. A null source is a source of its own, last in order. Rows that
    share a key are rows of their own; reruns over the same rows agree."""
    rows = stash(docs.select(F.col(key).alias("key"), F.col(source).cast("string").alias("source"), size.cast("long").alias("size")), "sizes")
    salt = F.pmod(F.xxhash64("key", F.lit("copies")), F.lit(_SALTS)).cast("int")
    fine = stash(rows.groupBy("source", "size", salt.alias("salt")).agg(F.count("*").alias("n")), "counts")
    cells = fine.groupBy("source", "size").agg(F.sum("n").alias("n"))
    targets = stash(source_targets(cells.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size")), weights, share, most), "targets")
    full = cells.where("size > 0")
    solved = tilts(full, targets, most).select("source", "target", "scale", "tilt")
    c, s = full.alias("c"), solved.alias("s")
    rate = F.coalesce(F.least(F.exp(F.least(F.col("tilt") * F.col("c.size") / F.col("scale"), F.lit(700.0))), F.lit(float(most))), F.lit(float(most)))
    rated = c.join(s, F.col("c.source").eqNullSafe(F.col("s.source"))).select("c.source", "c.size", "c.n", "s.target", (F.col("c.n") * rate).alias("due"))
    falling = Window.partitionBy("source").orderBy(F.desc("size"))
    carried = F.sum("due").over(falling.rowsBetween(Window.unboundedPreceding, 0))
    given = rated.withColumn("upto", F.floor(carried + 0.5)).withColumn("copies", F.least(F.col("upto") - F.coalesce(F.lag("upto").over(falling), F.lit(0)), most * F.col("n")))
    of_source = Window.partitionBy("source")
    for _ in range(repairs):
        left = F.col("target") - F.sum(F.col("copies") * F.col("size")).over(of_source)
        given = given.withColumn("left", left)
        room = F.when(F.col("left") > 0, most * F.col("n") - F.col("copies")).otherwise(F.col("copies"))
        given = given.withColumn("room", room)
        pick = F.max(F.when((F.col("room") > 0) & (F.col("size") <= F.abs("left")), F.col("size"))).over(of_source)
        step = F.least("room", F.floor(F.abs("left") / F.col("size")))
        given = given.withColumn("pick", pick).withColumn("copies", F.col("copies") + F.when(F.col("size") == F.col("pick"), F.signum("left").cast("long") * step).otherwise(0)).drop("left", "room", "pick")
    base = given.select("source", "size", F.expr("copies div n").alias("base"), F.expr("copies % n").alias("extra"))
    # a document's rank among those of its source and size: those of lower salts, and its rank in its own
    before = F.coalesce(F.sum("n").over(Window.partitionBy("source", "size").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    fine = fine.withColumn("before", before)
    f, b = fine.alias("f"), base.alias("b")
    plan = f.join(b, F.col("f.source").eqNullSafe(F.col("b.source")) & (F.col("f.size") == F.col("b.size")), "left").select("f.source", "f.size", "f.salt", "f.before", "b.base", "b.extra")
    plan = stash(plan.join(targets.alias("t"), F.col("f.source").eqNullSafe(F.col("t.source"))).select("f.source", "f.size", "f.salt", "before", "base", "extra", "source_size", "target"), "plan")
    rank = F.row_number().over(Window.partitionBy("source", "size", "salt").orderBy(F.xxhash64("key"), "key"))
    ranked = rows.withColumn("salt", salt).withColumn("rank", rank)
    r, p = ranked.alias("r"), plan.alias("p")
    joined = r.join(p, F.col("r.source").eqNullSafe(F.col("p.source")) & (F.col("r.size") == F.col("p.size")) & (F.col("r.salt") == F.col("p.salt")))
    copies = F.coalesce(F.col("base") + F.when(F.col("before") + F.col("rank") <= F.col("extra"), 1).otherwise(0), F.lit(1))
    return joined.select(F.col("key").alias(key), F.col("r.size").alias("size"), "source_size", "target", copies.cast("long").alias("copies"), (copies * F.col("r.size")).cast("long").alias("taken"))
