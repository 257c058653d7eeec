"""Exact n-gram Jaccard join with a token-group matrix.

A document is the set of hashes of its n-word shingles, in one order everywhere: by rising frequency over all
documents, counted in a table of fixed size, then by hash. Documents of equal sets are one. Similar documents
are put into groups: those with the same least hash are compared with the leaders among them, and what
links is a group. Each group has its token union, a column of a sparse token-group matrix; of the union only
the tokens that a prefix filter needs are stored, each with the shortest and longest member that has it and the
foremost place it has. A document's own foremost tokens, joined with the matrix, bound its overlap with every
other group; only groups it could reach the threshold with are opened, and their members compared with it
exactly.

Documents link when threshold_percent * union <= 100 * intersection. A document with fewer words than a
shingle has its whole sequence as its one shingle; without words, or null, it has none and links with
nothing. Links are reported as spanning edges, never as all pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import connected_components, discard, partitions, stash
from .textkit import chunks, mixed, windows_hash, word_hashes

#: Cells of the frequency table (a power of two), cells in a row of it, members of a group that are compared together.
CELLS, SLICE, BLOCK = 1 << 20, 1 << 12, 400
#: Rows of a frame, about.
FRAME = 4096


def shingle_sets(texts: list[bytes], n: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text, A-Z lower-cased."""
    words, starts = word_hashes([t.lower() for t in texts])
    runs = windows_hash(words, n)
    out = []
    for a, b in zip(starts[:-1].tolist(), starts[1:].tolist(), strict=True):
        if b - a >= n:
            out.append(np.unique(runs[a : b - n + 1]))
        else:
            out.append(windows_hash(words[a:b], b - a) if b > a else np.zeros(0, np.uint64))
    return out


def _needed(n: int, percent: int) -> int:
    """Least overlap of a set of n with any set it links with."""
    return -(-n * percent // 100)


def _shared(n: Column, short: Column, long: Column, percent: int) -> Column:
    """Least number of common tokens in the prefixes of a set of n and one of any size from short to long that it links with.

    Two sets share at least what their overlap needs beyond the longer of their remainders. That grows with the other's
    size up to n and falls from there but for rounding, by which the last sizes before the upper end may need one less than it."""
    beyond = lambda x: F.ceil(percent * (n + x) / (100 + percent) - 1e-9) - F.ceil(F.greatest(n, x) * percent / 100 - 1e-9) + 1
    steps = -(-100 * (100 + percent) // percent**2)  # it falls by more than one over so many sizes, or by one
    return F.greatest(F.lit(1), F.least(beyond(short), *[beyond(F.greatest(short, long - k)) for k in range(steps)]))


def _texts(batch: pa.RecordBatch) -> list[tuple[int, bytes]]:
    return [(i, t or b"") for i, t in zip(batch.column("key").to_pylist(), batch.column("text").to_pylist(), strict=True)]


def _sets(texts: DataFrame, n: int) -> DataFrame:
    """Rows of two kinds: (key, n, set, least) of each text, and (cell, counts) of the frequency table of each task."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.zeros(CELLS, np.int64)
        names = ["key", "n", "h1", "h2", "least", "cell", "counts"]
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()]
        for batch in batches:
            for part in chunks(_texts(batch), lambda r: len(r[1])):
                sets = shingle_sets([t for _, t in part], n)
                every = np.concatenate(sets)
                table += np.bincount((every >> np.uint64(64 - CELLS.bit_length() + 1)).astype(np.int64), minlength=CELLS)
                once, twice = mixed(every), mixed(every + np.uint64(12345))
                ends = np.cumsum([0, *map(len, sets)])
                one, two = (np.concatenate([np.zeros(1, np.uint64), np.cumsum(x)]) for x in (once, twice))
                h1, h2 = (one[ends[1:]] - one[ends[:-1]]).view(np.int64), (two[ends[1:]] - two[ends[:-1]]).view(np.int64)
                least = np.array([int(s[0] >> np.uint64(1)) if len(s) else -1 for s in sets], np.int64)
                m = len(part)
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in part], pa.int64()), pa.array(np.diff(ends)), pa.array(h1), pa.array(h2), pa.array(least), pa.nulls(m, pa.int32()), pa.nulls(m, pa.binary())], names)
        for at in range(0, CELLS, SLICE):
            row = table[at : at + SLICE]
            if row.any():
                yield pa.RecordBatch.from_arrays([*(pa.nulls(1, k) for k in kinds[:5]), pa.array([at // SLICE], pa.int32()), pa.array([row.tobytes()], pa.binary())], names)

    return stash(texts.mapInArrow(count, "key long, n long, h1 long, h2 long, least long, cell int, counts binary"), "sets")


def _frequencies(sets: DataFrame) -> np.ndarray:
    """How often each cell of the table was met, in powers of two; of one size whatever the input."""

    def add(group: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(SLICE, np.int64)
        for raw in group["counts"]:
            total += np.frombuffer(raw, np.int64)
        return pd.DataFrame({"cell": [int(group["cell"].iloc[0])], "level": [np.frexp(total.astype(float))[1].astype(np.uint8).tobytes()]})

    out = np.zeros(CELLS, np.uint8)
    for row in sets.where("cell is not null").select("cell", "counts").groupBy("cell").applyInPandas(add, "cell int, level binary").collect():
        out[row["cell"] * SLICE : (row["cell"] + 1) * SLICE] = np.frombuffer(row["level"], np.uint8)
    return out


def _links(a: np.ndarray, others: list[np.ndarray], percent: int) -> np.ndarray:
    """Whether the sorted set a links with each of the others."""
    sizes = np.fromiter(map(len, others), np.int64, len(others))
    able = (100 * np.minimum(sizes, len(a)) >= percent * np.maximum(sizes, len(a))) & (len(a) > 0)
    out = np.zeros(len(others), bool)
    at = np.flatnonzero(able)
    if len(at):
        every = np.concatenate([others[i] for i in at])
        found = a[np.minimum(np.searchsorted(a, every), len(a) - 1)] == every
        starts = np.concatenate([[0], np.cumsum(sizes[at])[:-1]])
        common = np.add.reduceat(found.astype(np.int64), starts)
        out[at] = 100 * common >= percent * (sizes[at] + len(a) - common)
    return out


def _share(spark, rows: int, *names: str) -> Column:
    """A number by which cells, named so, are dealt to frames: as many as the rows need for some thousands in each."""
    return F.pmod(F.xxhash64(*names), F.lit(max(8 * partitions(spark), rows // FRAME))).alias("share")


def linked(docs: DataFrame, key: str = "doc_id", text: str = "text", n: int = 3, percent: int = 90, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """((key, n_shingles, rep) of every row, (a, b) spanning edges between reps, the least keys of equal sets); keys are unique integers."""
    spark = docs.sparkSession
    texts = docs.select(F.col(key).cast("long").alias("key"), F.col(text).cast("string").cast("binary").alias("text"))
    sets = _sets(texts, n)
    rows = sets.where("cell is null").select("key", "n", "h1", "h2", "least")
    full = rows.where("n > 0")
    reps = full.groupBy("h1", "h2").agg(F.min("key").alias("rep"), F.first("n").alias("n"), F.first("least").alias("least"))
    reps = stash(reps, "classes")
    members = full.select("key", "n", "h1", "h2").join(reps.select("h1", "h2", "rep"), ["h1", "h2"]).select("key", F.col("n").alias("n_shingles"), "rep")
    members = members.union(rows.where("n = 0").select("key", "n", "key"))
    # those that share their least hash with another are compared; many of them in blocks
    alike = reps.groupBy("least").agg(F.count("*").alias("k")).where("k > 1")
    marked = reps.join(alike, "least", "left").select(F.col("rep").alias("key"), F.when(F.col("k").isNotNull(), F.struct("least", F.pmod(F.xxhash64("rep"), F.ceil(F.col("k") / block)).alias("part"))).alias("group"))
    levels = spark.sparkContext.broadcast(_frequencies(sets))

    def prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level = levels.value
        for batch in batches:
            grouped = batch.column("grouped").to_pylist()
            for part in chunks(list(zip(_texts(batch), range(batch.num_rows), strict=True)), lambda r: len(r[0][1])):
                found = shingle_sets([t for (_, t), _ in part], n)
                heads, packed = [], []
                for tokens, (_, at) in zip(found, part, strict=True):
                    m = len(tokens) - _needed(len(tokens), percent) + 1
                    if m == 1 and 100 * len(tokens) // percent == len(tokens):
                        m = 0  # too short to link with any other set
                    rare = level[(tokens >> np.uint64(64 - CELLS.bit_length() + 1)).astype(np.int64)]
                    heads.append(tokens[np.lexsort((tokens, rare))[:m]].view(np.int64))
                    packed.append(tokens.tobytes() if grouped[at] else None)
                rows_ = [at for _, at in part]
                yield pa.RecordBatch.from_arrays([batch.column("key").take(pa.array(rows_)), pa.array(np.fromiter(map(len, found), np.int64, len(found))), pa.array(heads, pa.list_(pa.int64())), pa.array(packed, pa.binary()), batch.column("group").take(pa.array(rows_))], ["key", "n", "head", "tokens", "group"])

    kind = "group struct<least:long,part:long>"
    headed = texts.join(marked, "key").select("key", "text", F.col("group").isNotNull().alias("grouped"), "group")
    headed = stash(headed.mapInArrow(prefixes, f"key long, n long, head array<long>, tokens binary, {kind}"), "heads")

    def lead(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        for _, group in frame.groupby(["least", "part"], sort=False):
            group = group.sort_values("key")
            keys, found = group["key"].tolist(), [np.frombuffer(x, np.uint64) for x in group["tokens"]]
            leaders: list[int] = []
            for i, tokens in enumerate(found):
                hit = _links(tokens, [found[j] for j in leaders], percent)
                out.extend((keys[i], keys[leaders[k]]) for k in np.flatnonzero(hit))
                if not hit.any():
                    leaders.append(i)
        return pd.DataFrame(out, columns=["a", "b"])

    # many small groups share a frame
    alike_rows = headed.where("group is not null").select("key", "tokens", "group.least", "group.part")
    near = stash(alike_rows.select("*", _share(spark, alike.agg(F.sum("k")).first()[0] or 0, "least", "part")).groupBy("share").applyInPandas(lead, "a long, b long"), "leaders")
    groups = stash(connected_components(near), "groups")
    # the matrix: a group is what is known to be linked, in parts of bounded size
    heads = headed.join(groups.withColumnRenamed("node", "key"), "key", "left").select("key", "n", "head", F.coalesce("component", "key").alias("of"))
    heads = heads.select("key", "n", "of", F.posexplode("head").alias("place", "token"))
    tokens = heads.repartition("token")
    matrix = tokens.groupBy("token", "of").agg(F.min("n").alias("shortest"), F.max("n").alias("longest"), F.max(F.col("n") - F.col("place")).alias("rest"))
    several = matrix.groupBy("token").agg(F.count("*").alias("k")).where("k > 1").select("token")
    q, g = tokens.join(several, "token").alias("q"), matrix.alias("g")
    short, long = F.greatest(F.col("g.shortest"), F.ceil(F.col("q.n") * percent / 100)), F.least(F.col("g.longest"), F.floor(F.col("q.n") * 100 / percent))
    least = F.ceil(percent * (F.col("q.n") + short) / (100 + percent) - 1e-9)
    rest = F.least(F.col("q.n") - F.col("q.place"), F.col("g.rest"))
    bound = (F.col("q.token") == F.col("g.token")) & (F.col("q.of") > F.col("g.of")) & (short <= long)
    # where they meet first, no more than what is left of both can be common
    met = q.join(g, bound).where(rest >= least).groupBy(F.col("q.key").alias("query"), F.col("g.of").alias("of")).agg(F.min(_shared(F.col("q.n"), short, long, percent)).alias("need"))
    met = stash(met, "met")
    # each group's union, in parts of bounded size, against the foremost tokens of those that met it, in parts too: a cell
    # is a part of the group and a part of those
    members_of = headed.join(groups.withColumnRenamed("node", "key"), "key", "left").select("key", "head", F.coalesce("component", "key").alias("of"))
    members_of = members_of.join(met.select("of").distinct(), "of", "left_semi")
    asked = met.groupBy("of").agg(F.count("*").alias("asked"))
    sizes = members_of.groupBy("of").agg(F.count("*").alias("members")).join(asked, "of")
    sizes = stash(sizes.withColumns({"parts": F.ceil(F.col("members") / block).cast("int"), "turns": F.ceil(F.col("asked") / (4 * block)).cast("int")}), "sizes")
    held_in = sizes.agg(F.sum(F.col("members") * F.col("turns") + F.col("asked") * F.col("parts"))).first()[0] or 0
    sizes = sizes.select("of", "parts", "turns")
    part, turn = F.pmod(F.xxhash64("key"), F.col("parts")).cast("int").alias("part"), F.pmod(F.xxhash64("query"), F.col("turns")).cast("int").alias("turn")
    each = lambda n, name: F.explode(F.sequence(F.lit(0), F.col(n) - 1)).alias(name)
    heads = headed.select(F.col("key").alias("query"), "head")
    united = members_of.join(sizes, "of").select("of", part, each("turns", "turn"), F.lit(-1).cast("long").alias("query"), "head", F.lit(-1).cast("long").alias("need"))
    bounded = met.join(sizes, "of").join(heads, "query").select("of", each("parts", "part"), turn, "query", "head", "need")
    cells = united.union(bounded)

    def qualify(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        for (of, k, t), group in frame.groupby(["of", "part", "turn"], sort=False):
            own = group["need"].to_numpy() < 0
            union = np.unique(np.concatenate(group["head"][own].tolist() or [np.zeros(0, np.int64)]))
            asked = group[~own]
            if len(asked) and len(union):
                lengths = asked["head"].map(len).to_numpy()
                every = np.concatenate(asked["head"].tolist())
                hit = union[np.minimum(np.searchsorted(union, every), len(union) - 1)] == every
                common = np.bincount(np.repeat(np.arange(len(asked)), lengths), hit, len(asked))
                out.extend((q, of, k, t) for q in asked["query"].to_numpy()[common >= asked["need"].to_numpy()])
        return pd.DataFrame(out, columns=["query", "of", "part", "turn"])

    cells = cells.select("*", _share(spark, held_in, "of", "part", "turn"))
    opened = stash(cells.groupBy("share").applyInPandas(qualify, "query long, of long, part int, turn int"), "opened")
    inside = members_of.select("of", "key").join(sizes, "of").select("of", part, "key").join(opened.select("of", "part", "turn").distinct(), ["of", "part"])
    inside = stash(inside.select("of", "part", "turn", "key"), "inside")
    discard(met)
    met_in = opened.count() + inside.count()
    wanted = opened.select(F.col("query").alias("key")).union(inside.select("key")).distinct()
    small = texts.join(wanted, "key")

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(_texts(batch), lambda r: len(r[1])):
                found = shingle_sets([t for _, t in part], n)
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in part], pa.int64()), pa.array([x.tobytes() for x in found], pa.binary())], ["key", "tokens"])

    held = stash(small.mapInArrow(packed, "key long, tokens binary"), "held")
    inside = inside.join(held, "key").select("of", "part", "turn", "key", "tokens", F.lit(False).alias("asks"))
    asking = opened.join(held.withColumnRenamed("key", "query"), "query").select("of", "part", "turn", F.col("query").alias("key"), "tokens", F.lit(True).alias("asks"))

    def open_(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        for _, group in frame.groupby(["of", "part", "turn"], sort=False):
            asks = group["asks"].to_numpy()
            keys = group["key"].to_numpy()[~asks]
            found = [np.frombuffer(x, np.uint64) for x in group["tokens"][~asks]]
            for query, raw in zip(group["key"][asks], group["tokens"][asks], strict=True):
                hit = _links(np.frombuffer(raw, np.uint64), found, percent)
                if hit.any():  # the members of a group are linked already
                    out.append((query, keys[hit.argmax()]))
        return pd.DataFrame(out, columns=["a", "b"])

    together = inside.union(asking).select("*", _share(spark, met_in, "of", "part", "turn"))
    late = stash(together.groupBy("share").applyInPandas(open_, "a long, b long"), "late")
    discard(held, headed)
    return members, groups.select(F.col("node").alias("a"), F.col("component").alias("b")).union(late)


def components(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """(key, n_shingles, component_id) of each row."""
    members, edges = linked(docs, key, text, **how)
    roots = connected_components(edges).select(F.col("node").alias("rep"), "component")
    return members.join(roots, "rep", "left").select(F.col("key").alias(key), "n_shingles", F.coalesce("component", "rep").alias("component_id"))
