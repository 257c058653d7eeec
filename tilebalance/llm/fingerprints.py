"""Document fingerprints by one-permutation MinHash, with DataFrame functions alone.

Each shingle of five words is hashed once; the first bits of the hash name its bin, and a bin keeps its least
hash. One sort of the hashes, with a sentinel at the end of each bin, finds all of them. An empty bin takes the value
of the first filled bin on its own walk through all bins, the same walk in every document (optimal densification). The low
bits of the values are packed as hexadecimal digits. Likeness is the share of equal digits groups, freed of
the share that agrees by chance.

Null and empty texts have no shingles: their fingerprint is empty, like nothing but another empty one
(1.0), and unlike any other (0.0). A text of fewer than five words is one shingle. Equal texts have equal
fingerprints; extra columns are passed through by `fingerprinted`."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACES, partitions, stash

#: Words in a shingle, bins (a power of two), and hexadecimal digits kept of each bin's value.
SHINGLE, BINS, DIGITS = 5, 256, 2
_WALK = 6


def _hashes(words: Column, n: int) -> Column:
    """A hash of each run of n words; of all the words if they are fewer."""
    runs = F.transform(F.sequence(F.lit(1), F.size(words) - F.lit(n - 1)), lambda i: F.xxhash64(*[F.element_at(words, (i + k).cast("int")) for k in range(n)]))
    return F.when(F.size(words) >= n, runs).when(F.size(words) > 0, F.array(F.xxhash64(words))).otherwise(F.array().cast("array<bigint>"))


def _table(values) -> Column:
    """A constant array."""
    return F.expr("array(" + ", ".join(repr(v) for v in values) + ")")


def _walks(bins: int) -> tuple[list[int], list[int]]:
    """Start and odd stride of each bin's walk through all bins, by a fixed rule."""
    return [(b * 2654435761 >> 7) % bins for b in range(bins)], [(b * 2246822519 >> 9) % (bins // 2) * 2 + 1 for b in range(bins)]


def fingerprinted(rows: DataFrame, text: str, to: str, shingle: int = SHINGLE, bins: int = BINS, digits: int = DIGITS) -> DataFrame:
    """rows with the fingerprint of a text column; a column of that name is replaced."""
    bits = bins.bit_length() - 1
    top = 64 - bits
    sentinels = F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda b: F.shiftleft(b.cast("long"), top).bitwiseOR(F.lit((1 << top) - 1)))
    words = F.filter(F.split(F.coalesce(F.col(text).cast("string"), F.lit("")), SPACES), lambda w: w != "")
    rows = rows.withColumn("_words", words)
    rows = rows.withColumn("_sorted", F.when(F.size("_words") > 0, F.sort_array(F.concat(_hashes(F.col("_words"), shingle), sentinels)))).drop("_words")
    number = lambda x: F.shiftrightunsigned(x, top).cast("int")
    firsts = F.filter("_sorted", lambda x, i: (i == 0) | (number(x) != number(F.get("_sorted", i - 1))))
    rows = rows.withColumn("_firsts", firsts).drop("_sorted")
    # unsigned order puts the bins of negative hashes last; signed order puts them first: half a turn apart
    place = lambda b: F.pmod(b + F.lit(bins // 2), F.lit(bins)).cast("int")
    low = lambda x: x.bitwiseAND(F.lit((1 << top) - 1))
    value = F.transform("_firsts", lambda x: F.when(low(x) != (1 << top) - 1, low(x).bitwiseAND(F.lit(16**digits - 1)).cast("int")))
    rows = rows.withColumn("_values", value).drop("_firsts")
    filled = F.filter(F.sequence(F.lit(0), F.lit(bins - 1)), lambda b: F.get("_values", place(b)).isNotNull())
    rows = rows.withColumn("_filled", F.when(F.exists("_values", lambda v: v.isNull()), filled))

    starts, strides = _walks(bins)
    first, inverse = _table(starts), _table([pow(x, -1, bins) for x in strides])
    steps = [_table([(a + k * x) % bins for a, x in zip(starts, strides, strict=True)]) for k in range(_WALK)]

    def dense(b: Column) -> Column:
        at = [F.get("_values", place(F.get(step, b))) for step in steps]
        # the filled bin that stands first on the walk: at step (j - start) / stride
        turn = F.array_min(F.transform("_filled", lambda j: F.pmod((j - F.get(first, b)) * F.get(inverse, b), F.lit(bins)) * bins + j))
        return F.coalesce(F.get("_values", place(b)), *at, F.when(F.size("_filled") > 0, F.get("_values", place(F.pmod(turn, F.lit(bins))))))

    written = _table([f"{v:0{digits}x}" for v in range(16**digits)])
    packed = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda b: F.get(written, dense(b))), "")
    return rows.withColumn(to, F.when(F.col("_values").isNull(), F.lit("")).otherwise(packed)).drop("_values", "_filled")


def with_likeness(rows: DataFrame, pairs: dict[str, tuple[str, str]], digits: int = DIGITS) -> DataFrame:
    """rows with the estimated Jaccard likeness, from 0 to 1, of pairs of fingerprint columns; digits are 2 or 4."""
    names = sorted({c for pair in pairs.values() for c in pair})
    raw = rows.withColumns({f"_raw_{c}": F.unhex(c) for c in names})  # places in bytes are found at once, in text by counting
    step, chance = digits // 2, 16.0**-digits
    out = {}
    for to, (a, b) in pairs.items():
        x, y = F.col(f"_raw_{a}"), F.col(f"_raw_{b}")
        n = F.length(x) / step
        same = F.size(F.filter(F.sequence(F.lit(0), n.cast("int") - 1), lambda i: F.substring(x, i * step + 1, F.lit(step)) == F.substring(y, i * step + 1, F.lit(step))))  # noqa: B023
        share = F.least(F.lit(1.0), F.greatest(F.lit(0.0), (same / n - chance) / (1 - chance)))
        out[to] = F.when((F.length(a) == 0) | (F.length(b) == 0), F.when(F.length(a) == F.length(b), 1.0).otherwise(0.0)).otherwise(share)
    return raw.withColumns(out).drop(*[f"_raw_{c}" for c in names])


def with_next(rows: DataFrame, key: str, columns: dict[str, str], made=lambda df: df) -> DataFrame:
    """rows with columns of the row of the next key, and after the last of the first; keys are unique.

    Rows are dealt out once, by ranges of keys whose bounds are quantiles; the first row of a range follows
    the last of the range before. made: adds columns after that first row is found, and before rows are dealt out."""
    n = 4 * partitions(rows.sparkSession)
    cuts = sorted(set(rows.agg(F.percentile_approx(key, [i / n for i in range(1, n)], 10_000)).first()[0] or []))
    ladder = F.array(*[F.lit(c) for c in cuts]) if cuts else F.array().cast("array<bigint>")
    ranged = rows.withColumn("_span", F.size(F.filter(ladder, lambda c: c < F.col(key))))
    # one row for each range: its first key, and the range before it; the first comes after the last
    by_span, whole = Window.orderBy("_span"), Window.partitionBy()
    heads = ranged.groupBy("_span").agg(F.min(key).alias(key)).select(key, F.coalesce(F.lag("_span").over(by_span), F.max("_span").over(whole)).alias("_span"))
    ends = rows.join(F.broadcast(heads), key)  # as many rows as ranges
    both = made(ranged.withColumn("_ghost", F.lit(False)).unionByName(ends.withColumn("_ghost", F.lit(True))))
    order = Window.partitionBy("_span").orderBy("_ghost", key)
    took = both.select("*", *[F.lead(c).over(order).alias(to) for c, to in columns.items()])
    return took.where("not _ghost").drop("_ghost", "_span")


def compared(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next) of each row.

    The edited text has its last floor(n/2) code points replaced by as many of the next row's first, or all of them."""
    rows = docs.select(F.col(key).alias("_key"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("_text"))
    half = F.floor(F.length("_text") / 2).cast("int")
    rows = with_next(rows, "_key", {"_text": "_other", "fingerprint": "_mark"}, lambda df: fingerprinted(df, "_text", "fingerprint"))
    edited = F.concat(F.substring("_text", F.lit(1), F.length("_text") - half), F.substring("_other", F.lit(1), half))
    rows = rows.select("_key", F.length("_text").cast("long").alias("n_chars"), "fingerprint", "_mark", edited.alias("_edited")).withColumn("edited_sha256", F.sha2("_edited", 256))
    rows = with_likeness(fingerprinted(rows, "_edited", "edited_fingerprint"), {"near_edited": ("fingerprint", "edited_fingerprint"), "near_next": ("fingerprint", "_mark")})
    return rows.select(F.col("_key").alias(key), "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")
