"""Toxicity by two class-conditional Kneser-Ney models over the letters of words.

Each class has interpolated Kneser-Ney counts of letter runs inside words, word ends marked. Long runs are
counted in their own class; the short ones they fall back to are counted over both classes together, as
the number of different letters they follow, so that a rare expression is judged by the same shared counts in
both classes. A text's evidence is the difference of its two log-likelihoods by its number of words, the
same over the words that speak for the class alone, and the mean over its three strongest expressions. A
logistic curve turns these into a score from 0 to 1. The curve is fitted across two folds, each judged by
the models of the other, so that it does not take what the models know by heart for evidence.

All counts are taken over every labelled row that is not held out, and grow with the input: words are counted in
tasks, their runs of letters level by level in Spark. A model that goes to tasks has a place for 2**BITS runs and
as many contexts of each order, found by their hashes; runs that meet in a place are counted together, so its size is
bounded whatever the input. Only the curve, of four numbers, is fitted on at most `bound` rows of each class, those
with the least hash of their key. Every row is scored over its whole text, by word types, whose evidence a task keeps
as long as it runs. Null and empty texts have no evidence and get the score that the curve has there. Rows without a
label or with a null label are scored like any other.

A model stays packed on the driver and on its way; tasks unpack it table by table, and take texts and new words by small parts, so
that what a task holds besides the model and the evidence it keeps does not grow with the rows of an Arrow batch."""

from __future__ import annotations

import functools
import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, stash
from .textkit import chunks, mixed, powers

#: Labelled rows of each class for the curve at most; letters in the longest run; shared orders; discount; word types a task keeps;
#: bits of the place of a run; word types that a task counts before it hands them on; words whose evidence is computed at once.
BOUND, ORDER, SHARED, DISCOUNT, KEPT, BITS, HELD, PART = 2_000, 6, 2, 1.0, 250_000, 22, 200_000, 10_000
_LETTERS = np.uint64(0x9E3779B97F4A7C15)


def _places(words: list[str], order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Letters of all words, each word behind its marks and with one at its end; where those to predict stand; and their words."""
    pad = order - 1
    text = "".join("\x02" * pad + w + "\x03" for w in words)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) + np.uint64(1)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 1
    word = np.repeat(np.arange(len(words)), lengths)
    return codes, np.arange(len(word)) + pad * (word + 1), word


def _cell(total: np.ndarray) -> np.ndarray:
    return (mixed(total) >> np.uint64(64 - BITS)).astype(np.uint32)


def _runs(codes: np.ndarray, at: np.ndarray, order: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For k from 1 to order: cells of the k letters that end at each place, and of the k-1 letters before it."""
    run, context = np.zeros(len(at), np.uint64), np.zeros(len(at), np.uint64)
    for k, power in enumerate(powers(_LETTERS, order)):
        run = run + codes[at - k] * power
        yield _cell(run + np.uint64(k + 1)), _cell(context + np.uint64(k + 101))
        if k + 1 < order:
            context = context + codes[at - 1 - k] * power


def _cells_of(runs: list[str], k: int) -> tuple[np.ndarray, np.ndarray]:
    """The same cells for strings of k letters each, and for their first k-1 letters."""
    codes = np.frombuffer("".join(runs).encode("utf-32-le"), np.uint32).reshape(-1, k).astype(np.uint64) + np.uint64(1)
    power = powers(_LETTERS, k)[::-1]
    return _cell((codes * power).sum(1, dtype=np.uint64) + np.uint64(k)), _cell((codes[:, :-1] * power[1:]).sum(1, dtype=np.uint64) + np.uint64(k + 100))


def _packed(arrays: tuple[np.ndarray, ...]) -> bytes:
    return zlib.compress(pickle.dumps(arrays, protocol=5), 1)  # of this protocol, arrays are not copied as they are loaded


def _unpacked(table: bytes) -> tuple[np.ndarray, ...]:
    return pickle.loads(zlib.decompress(table))


class Model:
    """For each order: sorted cells of runs with their weight in either class, and of contexts with total and number of followers.

    Made of (packed runs, packed contexts) of each order, None where there are none; unpacked when first asked, not when sent."""

    def __init__(self, packed: list[tuple[bytes | None, bytes | None]], discount: float = DISCOUNT):
        self.packed, self.order, self.discount = packed, len(packed), discount

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("tables", "followed", "alphabet")}

    def _open(self) -> None:
        nothing = np.zeros(0, np.uint32), np.zeros((2, 0), np.float32), np.zeros((2, 0), np.float32)
        self.tables = [_unpacked(runs) if runs else nothing[:2] for runs, _ in self.packed]
        self.followed = [_unpacked(contexts) if contexts else nothing for _, contexts in self.packed]
        self.alphabet = max(1, len(self.tables[0][0])) + 1

    def evidence(self, words: list[str]) -> np.ndarray:
        """log P(word | class 1) - log P(word | class 0) of each word."""
        if not words:
            return np.zeros(0)
        if not hasattr(self, "tables"):
            self._open()
        codes, at, word = _places(words, self.order)
        p = np.full((2, len(word)), 1.0 / self.alphabet)
        for k, (runs, contexts) in enumerate(_runs(codes, at, self.order), 1):
            keys, weights = self.tables[k - 1]
            above, totals, kinds = self.followed[k - 1]
            if not len(keys):
                continue
            near, hit = _find(keys, runs)
            up, known = _find(above, contexts)
            for c in (0, 1):
                total = np.where(known, totals[c][up], 0.0)
                got = np.where(hit, weights[c][near], 0.0)
                have = total > 0
                safe = np.where(have, total, 1.0)
                p[c] = np.where(have, np.maximum(got - self.discount, 0) / safe + self.discount * np.where(known, kinds[c][up], 0.0) / safe * p[c], p[c])
        gain = np.log(p[1]) - np.log(p[0])
        return np.bincount(word, gain, len(words))


def _find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(keys, wanted), max(0, len(keys) - 1))
    return at, keys[at] == wanted if len(keys) else np.zeros(len(wanted), bool)


def _models(counted: DataFrame, order: int = ORDER, shared: int = SHARED, discount: float = DISCOUNT) -> dict[int, Model]:
    """Models 0 and 1 of either fold and 2 of both, from (word, n00, n01, n10, n11): how often a word stands in class y of fold f.

    A run of the longest order weighs as often as it stands there, a shorter one by the number of different letters before it."""
    marks = [(y, f) for y in (0, 1) for f in (0, 1)]
    padded = F.concat(F.lit("\x02" * (order - 1)), "word", F.lit("\x03"))
    ends = F.explode(F.transform(F.sequence(F.lit(1), F.length("word") + 1), lambda i: F.substring(padded, i, F.lit(order))))
    longest = stash(counted.select(ends.alias("run"), *(f"n{y}{f}" for y, f in marks)).groupBy("run").agg(*(F.sum(f"n{y}{f}").alias(f"n{y}{f}") for y, f in marks)), "runs")

    folds = {0: (0,), 1: (1,), 2: (0, 1)}
    kept = [F.col(f"p{y}{f}") for y, f in marks]

    def there(which: int, y: int) -> Column:
        """Whether a run is in a class and fold, for shared orders in either class."""
        own, other = (functools.reduce(Column.__or__, (F.col(f"p{c}{f}") for f in folds[which])) for c in (y, 1 - y))
        return own | (other & (F.col("k") <= shared))

    def by(of) -> Column:
        return F.array(*(F.struct(F.lit(which).alias("which"), of(which, 0).cast("double").alias("w0"), of(which, 1).cast("double").alias("w1")) for which in folds)).alias("by")

    seen = longest.select("run", *((F.col(f"n{y}{f}") > 0).alias(f"p{y}{f}") for y, f in marks))
    tails = F.explode(F.transform(F.sequence(F.lit(2), F.lit(order)), lambda k: F.struct((k - 1).alias("k"), F.substring("run", F.lit(order + 1) - k, k).alias("run")))).alias("at")
    apart = seen.select(tails, *kept).select("at.*", *kept).groupBy("k", "run").agg(*(F.max(c).alias(f"p{y}{f}") for c, (y, f) in zip(kept, marks, strict=True)))
    lower = apart.groupBy("k", F.substring("run", 2, order).alias("run")).agg(by(lambda which, y: F.sum(there(which, y).cast("long"))))
    top = longest.select(F.lit(order).alias("k"), "run", by(lambda which, y: sum(F.col(f"n{y}{f}") for f in folds[which])))

    def placed(batches):
        for batch in batches:
            ks = batch.column("k").to_numpy()
            for k in sorted(set(ks.tolist())):
                own = batch.take(pa.array(np.flatnonzero(ks == k)))
                cell, context = _cells_of(own.column("run").to_pylist(), k)
                yield pa.RecordBatch.from_arrays([own.column("k"), pa.array(cell.astype(np.int64)), pa.array(context.astype(np.int64)), own.column("by")], ["k", "cell", "context", "by"])

    rows = top.unionByName(lower).mapInArrow(placed, "k int, cell long, context long, by array<struct<which:int,w0:double,w1:double>>").select("k", "cell", "context", F.inline("by")).where("w0 + w1 > 0")
    kinds = [F.least(F.col(w) / discount, F.lit(1.0)) for w in ("w0", "w1")]
    entries = F.inline(F.array(*(F.struct(F.lit(kind).alias("kind"), F.col(place).alias("cell"), F.col("w0"), F.col("w1"), x.alias("k0"), y.alias("k1")) for kind, place, (x, y) in ((0, "cell", [F.lit(0.0)] * 2), (1, "context", kinds)))))
    every = rows.select("which", "k", entries).groupBy("which", "k", "kind", "cell").agg(*(F.sum(c).alias(c) for c in ("w0", "w1", "k0", "k1")))

    def pack(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("cell")
        columns = [group["cell"].to_numpy(np.uint32), group[["w0", "w1"]].to_numpy(np.float32).T.copy()]
        if key[2]:
            columns.append(group[["k0", "k1"]].to_numpy(np.float32).T.copy())
        return pd.DataFrame({"which": [key[0]], "k": [key[1]], "kind": [key[2]], "table": [_packed(tuple(columns))]})

    # a group has 2**BITS rows at most
    packed = {(r["which"], r["k"], r["kind"]): bytes(r["table"]) for r in every.groupBy("which", "k", "kind").applyInPandas(pack, "which int, k int, kind int, table binary").collect()}
    discard(longest)
    return {which: Model([(packed.get((which, k, 0)), packed.get((which, k, 1))) for k in range(1, order + 1)], discount) for which in folds}


def _slices(batch: pa.RecordBatch, text: str) -> Iterator[pa.RecordBatch]:
    """A batch by runs of rows of about 2 MB of text."""
    at = 0
    for part in chunks(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_pylist(), int):
        yield batch.slice(at, len(part))
        at += len(part)


def _features(texts: list[str], model: Model, known: dict[str, float]) -> np.ndarray:
    """Mean evidence by words, mean of what is for the class, mean of the three strongest; zeros for a text without words."""
    out = np.zeros((len(texts), 3))
    split = [t.lower().split() for t in texts]
    fresh = list({w for words in split for w in words} - known.keys())
    if len(known) + len(fresh) > KEPT:
        known.clear()
        fresh = list({w for words in split for w in words})
    for i in range(0, len(fresh), PART):
        part = fresh[i : i + PART]
        known.update(zip(part, model.evidence(part).tolist(), strict=True))
    for i, words in enumerate(split):
        if words:
            x = np.fromiter(map(known.__getitem__, words), float, len(words))
            top = np.partition(x, -3)[-3:] if len(x) > 3 else x
            out[i] = x.mean(), np.maximum(x, 0).mean(), top.sum() / 3
    return out


def _curve(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(mean, deviation, weights with the constant last) of a logistic curve, by Newton's steps."""
    mean, deviation = x.mean(0), np.maximum(x.std(0), 1e-9)
    z = np.c_[(x - mean) / deviation, np.ones(len(x))]
    w = np.zeros(z.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge * len(x) * np.eye(len(w)), z.T @ (y - p) - ridge * len(x) * w)
        w += step
        if abs(step).max() < 1e-9:
            break
    return mean, deviation, w


class Scorer:
    """A packed model, unpacked where it is used, and the curve."""

    def __init__(self, packed: Model, curve: tuple[np.ndarray, np.ndarray, np.ndarray]):
        self.packed, self.curve = packed, curve

    def model(self) -> Model:
        return Model(self.packed.packed, self.packed.discount)

    def scores(self, features: np.ndarray) -> np.ndarray:
        mean, deviation, w = self.curve
        return 1 / (1 + np.exp(-np.clip(((features - mean) / deviation) @ w[:-1] + w[-1], -30, 30)))


def held_out(key: str = "doc_id") -> Column:
    """Rows kept from training: crc32 of the key as text is divisible by 5."""
    return F.crc32(F.col(key).cast("string")) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", bound: int = BOUND) -> Scorer:
    """Models from all labelled rows that are not held out, the curve from at most `bound` of each class. A key with both labels counts as toxic.

    Without rows of both classes the score is the share of the class that there is, or one half."""
    marked = labels.where(F.col(label).isin(0, 1) & F.col(key).isNotNull() & ~held_out(key)).groupBy(F.col(key).alias("_key")).agg(F.max(label).cast("int").alias("_y"))
    order = F.xxhash64("_key")
    chosen = marked.where("_y = 0").orderBy(order, "_key").limit(bound).union(marked.where("_y = 1").orderBy(order, "_key").limit(bound))
    texts = docs.select(F.col(key).alias("_key"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("_text")).where(F.col("_key").isNotNull() & ~held_out("_key"))

    def labelled(which: DataFrame) -> DataFrame:
        return texts.join(which, "_key").select("_text", "_y", F.pmod(F.xxhash64("_key", F.lit("fold")), F.lit(2)).cast("int").alias("_fold"))

    sample = labelled(F.broadcast(chosen))

    def count(batches):
        from collections import Counter

        def handed(seen: Counter) -> pa.RecordBatch:
            words, ys, folds = zip(*seen, strict=True) if seen else ((), (), ())
            return pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array(ys, pa.int32()), pa.array(folds, pa.int32()), pa.array(seen.values(), pa.int64())], ["word", "y", "fold", "n"])

        seen: Counter = Counter()
        for batch in (part for whole in batches for part in _slices(whole, "_text")):
            for t, y, fold in zip(*(batch.column(c).to_pylist() for c in ("_text", "_y", "_fold")), strict=True):
                for w, n in Counter(t.lower().split()).items():
                    seen[w, y, fold] += n
                if len(seen) > HELD:
                    yield handed(seen)
                    seen = Counter()
        yield handed(seen)

    n = [F.coalesce(F.sum(F.when((F.col("y") == y) & (F.col("fold") == f), F.col("n"))), F.lit(0)).alias(f"n{y}{f}") for y in (0, 1) for f in (0, 1)]
    models = _models(labelled(marked).mapInArrow(count, "word string, y int, fold int, n long").groupBy("word").agg(*n))
    shared = sample.sparkSession.sparkContext.broadcast([models[f] for f in (0, 1)])

    def judge(batches):
        known: list[dict] = [{}, {}]
        fold_models = [Model(m.packed, m.discount) for m in shared.value]
        for batch in (part for whole in batches for part in _slices(whole, "_text")):
            rows = list(zip(batch.column("_text").to_pylist(), batch.column("_y").to_pylist(), batch.column("_fold").to_pylist(), strict=True))
            for f in (0, 1):
                own = [r for r in rows if r[2] == f]
                x = _features([r[0] for r in own], fold_models[1 - f], known[1 - f])
                yield pa.RecordBatch.from_arrays([pa.array([r[1] for r in own], pa.int32()), *(pa.array(x[:, j]) for j in range(3))], ["y", "a", "b", "c"])

    judged = sample.mapInArrow(judge, "y int, a double, b double, c double").toPandas().sort_values(["y", "a", "b", "c"])
    shared.unpersist()
    y = judged["y"].to_numpy(float)
    x = judged[["a", "b", "c"]].to_numpy()
    if len(set(y.tolist())) < 2:
        share = np.clip(y.mean(), 1e-6, 1 - 1e-6) if len(y) else 0.5
        curve = np.zeros(3), np.ones(3), np.array([0, 0, 0, np.log(share / (1 - share))])
    else:
        curve = _curve(x, y)
    return Scorer(models[2], curve)


def score(docs: DataFrame, scorer: Scorer, text: str = "text", to: str = "score") -> DataFrame:
    """docs with a score column, a double from 0 to 1; a column of that name is replaced."""
    shared = docs.sparkSession.sparkContext.broadcast(scorer)
    kept = [c for c in docs.columns if c != to]

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict = {}
        model = shared.value.model()
        for batch in (part for whole in batches for part in _slices(whole, text)):
            values = shared.value.scores(_features([t or "" for t in batch.column(text).to_pylist()], model, known))
            # only what is kept goes back
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(values)], [*kept, to])

    from pyspark.sql import types as T

    return docs.select(*kept, *([] if text in kept else [text])).mapInArrow(scored, T.StructType([docs.schema[c] for c in kept] + [T.StructField(to, T.DoubleType())]))
