"""Near-duplicate vectors by cross-polytope hashing after fast Hadamard rotations.

Exact copies are one vector that counts as many. In each of several tables a vector is rotated twice, by
sign flips and fast Hadamard transforms; in either rotation its code is the axis it is nearest to, with the
sign, and both codes name its bucket. A vector is stored in its own bucket and probes, besides that, the buckets
it was nearest to missing. Pairs that meet are verified in double precision where they meet first. A bucket with more
members than a block holds is compared block by block, every block with every other, so none is cut
short. Tasks report sums of links and a spanning forest of them, never the pairs.

Vectors that are null, zero, or hold null or non-finite components, and rows without a label, link with nothing.
Only vectors of equal label and equal length are compared. An empty table gives an empty result."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, partitions, stash

#: Cosine of a link; tables, buckets a vector looks into in each, and vectors in a block at most.
COSINE, TABLES, PROBES, BLOCK = 0.93, 8, 4, 2048
#: Rows of a frame, about.
FRAME = 1 << 16


def _rotate(x: np.ndarray, signs: np.ndarray) -> np.ndarray:
    """Three rounds of sign flips and Hadamard transforms over the last axis, whose length is a power of two."""
    n = x.shape[-1]
    for flip in signs:
        x = x * flip
        step = 1
        while step < n:
            pairs = x.reshape(-1, n // (2 * step), 2, step)
            x = np.stack([pairs[:, :, 0] + pairs[:, :, 1], pairs[:, :, 0] - pairs[:, :, 1]], 2).reshape(-1, n)
            step *= 2
        x = x / np.sqrt(n)
    return x


def codes(x: np.ndarray, tables: int = TABLES, probes: int = PROBES, seed: int = 7) -> np.ndarray:
    """(vectors, tables, probes) buckets of unit vectors, in rising order of what each would miss; the first is the vector's own."""
    n, dim = x.shape
    width = 1 << max(1, (dim - 1).bit_length())
    padded = np.zeros((n, width), np.float32)
    padded[:, :dim] = x
    rng, rows = np.random.default_rng([seed, width]), np.arange(n)[:, None]
    near = min(4, width)
    out = np.zeros((n, tables, probes), np.int64)
    for t in range(tables):
        axes, losses = [], []
        for _ in range(2):
            y = _rotate(padded, rng.choice(np.float32([-1, 1]), (3, width)))
            size = np.abs(y)
            best = np.argpartition(-size, near - 1, 1)[:, :near]
            best = np.take_along_axis(best, np.argsort(-size[rows, best], 1, kind="stable"), 1)
            axes.append(2 * best + (y[rows, best] < 0))
            losses.append((size[rows, best[:, :1]] - size[rows, best]) ** 2)
        both = (axes[0][:, :, None] * (2 * width) + axes[1][:, None, :]).reshape(n, -1)
        loss = (losses[0][:, :, None] + losses[1][:, None, :]).reshape(n, -1)
        order = np.argsort(loss, 1, kind="stable")[:, :probes]
        got = both[rows, order]
        out[:, t, : got.shape[1]] = got
        out[:, t, got.shape[1] :] = got[:, :1]
    return out


def _meetings(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether a's own bucket is among those b looks into, by pair and table."""
    return (a[:, :, :1] == b).any(2)


def distinct(vectors: DataFrame, key: str, embedding: str, label: str) -> tuple[DataFrame, DataFrame]:
    """(key, rep) of every comparable row, and (rep, label, vector, copies) of each different vector."""
    v = F.transform(embedding, lambda x: x.cast("double"))
    whole = F.forall(embedding, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    nonzero = F.exists(embedding, lambda x: x != 0)
    rows = vectors.where(F.col(label).isNotNull() & F.col(key).isNotNull() & F.col(embedding).isNotNull() & whole & nonzero).select(F.col(key).alias("key"), F.col(label).alias("label"), v.alias("vector"))
    rows = rows.withColumns({"h1": F.xxhash64("label", "vector"), "h2": F.xxhash64(F.lit("second"), "vector", "label")})
    reps = stash(rows.groupBy("h1", "h2").agg(F.min("key").alias("rep"), F.count("*").alias("copies")), "reps")
    members = stash(rows.select("key", "h1", "h2").join(reps, ["h1", "h2"]).select("key", "rep", "copies"), "members")
    firsts = rows.join(reps.select(F.col("rep").alias("key"), "copies"), "key").select(F.col("key").alias("rep"), "label", "vector", "copies").dropDuplicates(["rep"])
    return members, firsts


def links(firsts: DataFrame, cosine: float = COSINE, tables: int = TABLES, probes: int = PROBES, block: int = BLOCK) -> DataFrame:
    """(rep, links, parent): parts of each vector's number of links with other vectors, copies counted, and of a spanning forest."""

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            frame = batch.to_pandas()
            for dim, part in frame.groupby(frame["vector"].map(len)):
                x = np.array(part["vector"].tolist(), float)
                norm = np.sqrt((x / (top := np.abs(x).max(1, keepdims=True))) ** 2 @ np.ones(dim))[:, None] * top
                found = codes(x / norm, tables, probes).reshape(len(part), -1)
                single = x.astype(np.float32)
                raw = [(a if (a == b).all() else b).tobytes() for a, b in zip(single, x, strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(part["rep"], pa.int64()), pa.array(part["label"].astype(str)), pa.array(np.full(len(part), dim), pa.int32()), pa.array(part["copies"], pa.int64()), pa.array(raw, pa.binary()), pa.array(list(found), pa.list_(pa.int64())), pa.array([f.astype(np.int32).tobytes() for f in found], pa.binary())],
                    ["rep", "label", "dim", "copies", "vector", "codes", "packed"],
                )

    held = stash(firsts.select("rep", "label", "vector", "copies").mapInArrow(place, "rep long, label string, dim int, copies long, vector binary, codes array<long>, packed binary"), "codes")
    slots = held.select("rep", "label", "dim", F.posexplode("codes").alias("slot", "bucket"))
    t, own = F.call_function("div", F.col("slot"), F.lit(probes)).cast("int"), F.pmod("slot", F.lit(probes)) == 0
    slots = slots.select("rep", t.alias("t"), own.alias("own"), F.xxhash64(t, "bucket", "dim", "label").alias("key"))
    # only buckets in which two meet; one of several blocks is a square of tasks: what is stored in it goes to a row, what looks into it to a column
    crowd = slots.groupBy("key").agg(F.count("*").alias("n"), F.count_if("own").alias("stored")).where("stored > 0 AND n > 1")
    spread = slots.join(crowd, "key").select("key", "rep", "t", "own", F.greatest(F.lit(1), F.ceil(F.col("n") / F.lit(2 * block))).cast("int").alias("blocks"))
    mine = F.pmod(F.xxhash64("rep", "t"), F.col("blocks")).cast("int")
    cells = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    single = spread.where("blocks = 1").select("key", "rep", "t", F.lit(0).alias("row"), F.lit(0).alias("column"), F.col("own").alias("base"), F.lit(True).alias("looks"))
    several = spread.where("blocks > 1")
    stored = several.where("own").select("key", "rep", "t", mine.alias("row"), cells.alias("column"), F.lit(True).alias("base"), F.lit(False).alias("looks"))
    looking = several.select("key", "rep", "t", cells.alias("row"), mine.alias("column"), F.lit(False).alias("base"), F.lit(True).alias("looks"))
    met = single.union(stored).union(looking).join(held.select("rep", "dim", "copies", "vector", "packed"), "rep")

    def unit(rows: pd.Series, dim: int) -> np.ndarray:
        x = np.stack([np.frombuffer(r, np.float32 if len(r) == 4 * dim else float).astype(float) for r in rows]) if len(rows) else np.zeros((0, dim))
        top = np.abs(x).max(1, keepdims=True, initial=0)
        return x / (np.sqrt(((x / np.maximum(top, 1e-300)) ** 2).sum(1, keepdims=True)) * top + (top == 0))

    def pairs(t: int, base: np.ndarray, looks: np.ndarray, x: np.ndarray, rep: np.ndarray, code: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Linked rows of one bucket that count in table t: in the first where they meet, from the side of the smaller id if either looks at the other."""
        for i in range(0, len(base), 512):
            near = x[base[i : i + 512]] @ x[looks].T >= cosine
            if not near.any():
                continue
            a, b = np.nonzero(near)
            a, b = base[i + a], looks[b]
            other = rep[a] != rep[b]
            a, b = a[other], b[other]
            for j in range(0, len(a), 200_000):
                p, q = a[j : j + 200_000], b[j : j + 200_000]
                forth, back = _meetings(code[p], code[q]), _meetings(code[q], code[p])
                here = ((forth | back).argmax(1) == t) & ((rep[p] < rep[q]) | ~back[:, t])
                yield p[here], q[here]

    def compare(frame: pd.DataFrame) -> pd.DataFrame:
        left, right = [], []
        frame = frame.sort_values(["dim", "key", "row", "column"], ignore_index=True)
        for dim, part in frame.groupby("dim", sort=False):
            rep, base, looks, t = (part[c].to_numpy() for c in ("rep", "base", "looks", "t"))
            x = unit(part["vector"], int(dim))
            code = np.frombuffer(b"".join(part["packed"]), np.int32).reshape(len(part), tables, probes)
            place = part[["key", "row", "column"]].to_numpy()
            starts = np.flatnonzero(np.concatenate([[True], (place[1:] != place[:-1]).any(1)]))
            for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(part)], strict=True):
                if b - a > 1:
                    for p, q in pairs(int(t[a]), a + np.flatnonzero(base[a:b]), a + np.flatnonzero(looks[a:b]), x, rep, code):
                        left.append(part.index.to_numpy()[p])
                        right.append(part.index.to_numpy()[q])
        if not left:
            return pd.DataFrame({"rep": [], "links": [], "parent": []})
        a, b = np.concatenate(left), np.concatenate(right)
        rep, copies = frame["rep"].to_numpy(), frame["copies"].to_numpy()
        ids, at = np.unique(np.concatenate([rep[a], rep[b]]), return_inverse=True)
        i, j = at[: len(a)], at[len(a) :]
        count = np.bincount(i, copies[b], len(ids)) + np.bincount(j, copies[a], len(ids))
        parent = np.arange(len(ids))
        while True:
            before = parent.copy()
            low = np.minimum(parent[i], parent[j])
            np.minimum.at(parent, i, low)
            np.minimum.at(parent, j, low)
            parent = parent[parent]
            if (parent == before).all():
                break
        return pd.DataFrame({"rep": ids, "links": count.astype(np.int64), "parent": ids[parent]})

    # many buckets of few vectors share a frame, of some ten thousand rows at most whatever the input
    shares = max(8 * partitions(firsts.sparkSession), held.count() * tables * probes // FRAME)
    return met.withColumn("share", F.pmod(F.xxhash64("key", "row", "column"), F.lit(shares))).groupBy("share").applyInPandas(compare, "rep long, links long, parent long")


def near_duplicates(vectors: DataFrame, key: str = "vec_id", embedding: str = "embedding", label: str = "label", cosine: float = COSINE, **how) -> DataFrame:
    """(key, n_links, component_id, kept) of every row; keys are unique integers."""
    members, firsts = distinct(vectors, key, embedding, label)
    parts = stash(links(firsts, cosine, **how), "links")
    found = parts.groupBy("rep").agg(F.sum("links").alias("more"))
    roots = connected_components(parts.select(F.col("rep").alias("a"), F.col("parent").alias("b")))
    of = members.join(found, "rep", "left").join(roots.withColumnRenamed("node", "rep"), "rep", "left")
    of = of.select(F.col("key").alias(key), (F.col("copies") - 1 + F.coalesce("more", F.lit(0))).alias("n"), F.coalesce("component", "rep").alias("c"))
    rows = vectors.select(key).join(of, key, "left")
    component = F.coalesce("c", key)
    return rows.select(key, F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (F.col(key) == component).alias("kept"))
