"""Substring deduplication by compressed FM-indexes, one for each shard.

A window is a number of consecutive words of one document. Each window is named by its anchor: the run of a
few words in it with the least hash. Consecutive windows with the same anchor make a stretch. Equal windows
have equal anchors, so windows meet if stretches are dealt out by the hash of their anchors; nothing else
needs to meet, and no document is held against all of the corpus.

Stretches of equal words are one, of the document with the least key. Those whose anchor only one of them has
repeat nothing. The others go, with their words, to the shard of their anchor. A shard's words, from the
stretches are one text; its Burrows-Wheeler transform is stored in a wavelet tree of bit vectors with
counts. The documents' stretches are streamed against it from their last word to their first: backward
search extends the match by a word, and where it fails the match loses words at its end until it can go
on. That gives the matching statistics, cut off at the length of a window, with the range of suffixes that
start with the match; a window repeats if the least key among them is below the document's own. What is found for a
stretch holds wherever else its document has it. An anchor with very many
different stretches is dealt out again, window by window, by the hash of the whole window.

Null and empty texts, and those shorter than a window, lose nothing. Of documents with the same key the rows are
one document's only if the key is unique, which it must be."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stash
from .textkit import BASE, INVERSE, chunks, mixed, powers, windows_hash, word_hashes

#: Words of a window and of an anchor; words of a shard about; different stretches of an anchor before its windows are dealt out singly.
WINDOW, ANCHOR, SHARD_WORDS, CROWD = 50, 8, 400_000, 2_000
NONE = np.iinfo(np.int64).max


class WaveletTree:
    """Ranks of symbols in a sequence of numbers below 2**levels, from one bit vector with counts for each level."""

    def __init__(self, values: np.ndarray, levels: int):
        self.levels, self.size = levels, len(values)
        self.bits, self.counts, self.zeros = [], [], []
        now = values.astype(np.int64)
        for level in range(levels - 1, -1, -1):
            bit = (now >> level) & 1
            packed = np.zeros(len(now) // 64 + 1, np.uint64)
            raw = np.packbits(bit.astype(np.uint8), bitorder="little")
            packed.view(np.uint8)[: len(raw)] = raw
            self.bits.append(packed)
            self.counts.append(np.concatenate([[0], np.cumsum(np.bitwise_count(packed))]).astype(np.int32))
            self.zeros.append(int(len(now) - bit.sum()))
            now = np.concatenate([now[bit == 0], now[bit == 1]])  # stable, zeros first

    def _ones(self, level: int, at: np.ndarray) -> np.ndarray:
        block, rest = at >> 6, (at & 63).astype(np.uint64)
        return self.counts[level][block] + np.bitwise_count(self.bits[level][block] & ((np.uint64(1) << rest) - np.uint64(1)))

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How many of the first `at` values are `symbol`, element by element."""
        low, high = np.zeros(len(at), np.int64), at.astype(np.int64)
        for i in range(self.levels):
            bit = (symbol >> (self.levels - 1 - i)) & 1
            ones_low, ones_high = self._ones(i, low), self._ones(i, high)
            low = np.where(bit, self.zeros[i] + ones_low, low - ones_low)
            high = np.where(bit, self.zeros[i] + ones_high, high - ones_high)
        return high - low


class FmIndex:
    """Backward search over pieces of text whose suffixes are sorted by their first `depth` words.

    pieces: 64-bit words, one after another; lengths of the pieces; owners, a key for each piece."""

    def __init__(self, words: np.ndarray, lengths: np.ndarray, owners: np.ndarray, depth: int):
        self.alphabet, symbols = np.unique(words, return_inverse=True)
        # piece ends are symbol 0
        ends = np.cumsum(lengths + 1) - 1
        text = np.zeros(len(words) + len(lengths), np.int64)
        inside = np.ones(len(text), bool)
        inside[ends] = False
        text[inside] = symbols + 1
        owner = np.repeat(owners, lengths + 1)
        n, rank, width, ranks = len(text), text.copy(), 1, [text]
        while width < depth:  # ranks by twice as many words each time
            ahead = np.zeros(n, np.int64)
            ahead[: max(0, n - width)] = rank[width:] + 1
            _, rank = np.unique(rank * (n + 2) + ahead, return_inverse=True)
            width *= 2
            ranks.append(rank)
        # every class of equal first words may be in any order: it has one range
        self.suffixes = np.argsort(rank, kind="stable")
        last = text[self.suffixes - 1]
        last[self.suffixes == 0] = 0
        self.tree = WaveletTree(last, max(1, int(len(self.alphabet)).bit_length()))
        self.before = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=len(self.alphabet) + 1))])
        # words that each suffix has in common with the one before it, up to twice the depth
        a, b, same = np.append(self.suffixes[:-1], 0), np.append(self.suffixes[1:], 0), np.zeros(n, np.int64)
        for k in range(len(ranks) - 1, -1, -1):
            inside = (a + same < n) & (b + same < n)
            equal = inside & (ranks[k][np.where(inside, a + same, 0)] == ranks[k][np.where(inside, b + same, 0)])
            same += equal.astype(np.int64) << k
        common = np.zeros(n + 1, np.int16)
        common[1:n] = same[: n - 1]
        self.common = [common]  # and the least of runs of 2, 4, ... of them
        while 2 ** len(self.common) <= n + 1:
            half = 2 ** (len(self.common) - 1)
            self.common.append(np.minimum(self.common[-1][:-half], self.common[-1][half:]))
        owner = owner[self.suffixes]
        # least owner of any range of suffixes, from the least of all ranges whose length is a power of two
        self.least = [owner]
        while 2 ** len(self.least) <= n:
            half = 2 ** (len(self.least) - 1)
            self.least.append(np.minimum(self.least[-1][:-half], self.least[-1][half:]))

    def symbols(self, words: np.ndarray) -> np.ndarray:
        """Numbers of words; -1 for those the index has not."""
        at = np.minimum(np.searchsorted(self.alphabet, words), max(0, len(self.alphabet) - 1))
        return np.where(self.alphabet[at] == words, at + 1, -1) if len(self.alphabet) else np.full(len(words), -1)

    def extend(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranges of suffixes that start with the symbol and then what the given ranges start with; empty where there are none."""
        known = symbol > 0
        safe = np.where(known, symbol, 0)
        base = self.before[safe]
        down, up = base + self.tree.rank(safe, low), base + self.tree.rank(safe, high)
        return np.where(known, down, 0), np.where(known, up, 0)

    def wider(self, low: np.ndarray, high: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranges of all suffixes that have the first `length` words of the given ranges in common."""
        low, high = low.copy(), high.copy()
        for level in range(len(self.common) - 1, -1, -1):
            row, step = self.common[level], 2**level
            at = low - step + 1  # the least of common[at .. low]
            ok = at >= 1
            ok &= row[np.where(ok, at, 0)] >= length
            low = np.where(ok, low - step, low)
            ok = high + step <= self.tree.size
            ok &= row[np.where(ok, high, 0)] >= length
            high = np.where(ok, high + step, high)
        return low, high

    def least_owner(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        k = np.frexp((high - low).astype(float))[1] - 1
        out = np.zeros(len(low), self.least[0].dtype)
        for level in np.unique(k):
            here = k == level
            row = self.least[level]
            out[here] = np.minimum(row[low[here]], row[high[here] - 2**level])
        return out

    def first_owners(self, words: np.ndarray, lengths: np.ndarray, window: int) -> np.ndarray:
        """For each place in the pieces searched, the least owner of the window that starts there; the largest number if there is none.

        All pieces are searched in step, each from its last word to its first."""
        out = np.full(len(words), NONE)
        symbols, start = self.symbols(words), np.cumsum(lengths) - lengths
        end = start + lengths  # the match is words[at:end]
        at = end.copy()
        low, high = np.zeros(len(lengths), np.int64), np.full(len(lengths), self.tree.size)
        common = self.common[0]
        going = np.flatnonzero(lengths >= window)
        while len(going):
            a, e, lo, hi = at[going], end[going], low[going], high[going]
            more, less = self.extend(symbols[a - 1], lo, hi)
            grows = less > more
            none = ~grows & (e == a)
            a = a - (grows | none)
            # where it cannot grow it keeps as many words as its suffixes share with a neighbour
            keep = np.maximum(common[lo], common[hi])
            lo, hi = np.where(grows, more, lo), np.where(grows, less, hi)
            e = np.where(none, a, e)
            full = np.flatnonzero(e - a == window)
            out[a[full]] = self.least_owner(lo[full], hi[full])
            cut = ~grows & ~none
            length = np.where(cut, keep, e - a)
            length[full] = window - 1
            short = np.flatnonzero(cut | (e - a == window))
            lo[short], hi[short] = self.wider(lo[short], hi[short], length[short])
            e = np.where(none, e, a + length)
            at[going], end[going], low[going], high[going] = a, e, lo, hi
            going = going[(e - start[going] >= window) & (a > start[going])]
        return out


def stretches(words: np.ndarray, starts: np.ndarray, window: int, anchor: int) -> tuple[np.ndarray, ...]:
    """(text, first window, windows, anchor hash, content hash) of each stretch; starts: where each text's words begin, with the end added."""
    n = len(words) - window + 1
    if n <= 0:
        return tuple(np.zeros(0, np.int64) for _ in range(5))
    grams = windows_hash(words, anchor)
    width, least, step = window - anchor + 1, np.arange(len(grams)), 1
    while 2 * step <= width:  # leftmost place of the least hash in runs of twice as many
        right = least[step:]
        left = least[: len(right)]
        least = np.where(grams[left] <= grams[right], left, right)
        step *= 2
    left, right = least[:n], least[width - step : width - step + n]
    least = np.where(grams[left] <= grams[right], left, right)
    text = np.searchsorted(starts, np.arange(n), "right") - 1
    whole = np.arange(n) + window <= starts[np.minimum(text + 1, len(starts) - 1)]
    at = np.flatnonzero(whole)
    if not len(at):
        return tuple(np.zeros(0, np.int64) for _ in range(5))
    new = np.flatnonzero(np.concatenate([[True], (np.diff(at) > 1) | (np.diff(least[at]) != 0) | (np.diff(text[at]) != 0)]))
    first, count = at[new], np.diff(np.append(new, len(at)))
    last = first + count + window - 1
    up, down = powers(BASE, len(words)), powers(INVERSE, len(words))
    total = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(mixed(words) * up, out=total[1:])
    content = mixed((total[last] - total[first]) * down[first] + count.astype(np.uint64))
    return text[first], first - starts[text[first]], count, grams[least[first]].view(np.int64), content.view(np.int64)


def _intervals(repeats: np.ndarray, window: int) -> list[tuple[int, int]]:
    """Half-open runs of words covered by the marked windows."""
    at = np.flatnonzero(repeats)
    if not len(at):
        return []
    new = np.flatnonzero(np.concatenate([[True], np.diff(at) > window]))
    ends = np.append(new[1:] - 1, len(at) - 1)
    return list(zip(at[new].tolist(), (at[ends] + window).tolist(), strict=True))


def repeated(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, anchor: int = ANCHOR, shard_words: int = SHARD_WORDS, crowd: int = CROWD) -> DataFrame:
    """(key, first, last): half-open runs of words whose windows start in a document with a smaller key too."""
    texts = docs.select(F.col(key).cast("long").alias("key"), F.col(text).cast("string").cast("binary").alias("text"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(i, t) for i, t in zip(batch.column("key").to_pylist(), batch.column("text").to_pylist(), strict=True) if t and i is not None]
            for part in chunks(rows, lambda r: len(r[1])):
                words, starts = word_hashes([t for _, t in part])
                of, first, count, anchors, content = stretches(words, starts, window, anchor)
                keys = np.array([i for i, _ in part], np.int64)[of.astype(int)]
                yield pa.RecordBatch.from_arrays([pa.array(anchors, pa.int64()), pa.array(content, pa.int64()), pa.array(keys), pa.array(first.astype(np.int32)), pa.array(count.astype(np.int32))], ["anchor", "content", "key", "first", "count"])

    cuts = stash(texts.mapInArrow(cut, "anchor long, content long, key long, first int, count int"), "stretches")
    different = cuts.groupBy("anchor", "content").agg(F.min(F.struct("key", "first", "count")).alias("rep"), F.count("*").alias("n")).select("anchor", "content", "rep.*", "n")
    different = stash(different, "different")
    # a stretch that a smaller document has too, word for word
    several = different.where("n > 1").select("anchor", "content", F.col("key").alias("least"), F.col("first").alias("stretch"))
    met = cuts.join(several, ["anchor", "content"])
    same = met.where("key > least").select("key", "first", (F.col("first") + F.col("count") + (window - 1)).alias("last"))
    # or that its document has again, further on
    again = met.where("key = least and first > stretch").select("key", "stretch", (F.col("first") - F.col("stretch")).alias("shift"))
    # stretches whose anchor others have in other words
    shared = different.groupBy("anchor").agg(F.count("*").alias("kinds")).where("kinds > 1")
    unclear = stash(different.join(shared, "anchor").select("anchor", "key", "first", "count", (F.col("kinds") > crowd).alias("crowd")), "unclear")
    total = unclear.where("not crowd").agg(F.sum(F.col("count") + window)).first()[0] or 0
    shards = max(1, -(-total // shard_words))
    wanted = lambda rows: rows.groupBy("key").agg(F.collect_list(F.struct("anchor", "first", "count")).alias("wanted"))

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, t, runs in zip(batch.column("key").to_pylist(), batch.column("text").to_pylist(), batch.column("wanted").to_pylist(), strict=True):
                words, _ = word_hashes([t])
                first = [run["first"] for run in runs]
                held = [words[run["first"] : run["first"] + run["count"] + window - 1].tobytes() for run in runs]
                yield pa.RecordBatch.from_arrays([pa.array([run["anchor"] % shards for run in runs], pa.int64()), pa.array([i] * len(runs), pa.int64()), pa.array(first, pa.int32()), pa.array(held, pa.binary()), pa.array(first, pa.int32())], ["shard", "key", "first", "words", "stretch"])

    def single(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, t, runs in zip(batch.column("key").to_pylist(), batch.column("text").to_pylist(), batch.column("wanted").to_pylist(), strict=True):
                words, _ = word_hashes([t])
                other = mixed(words + np.uint64(7))
                for run in runs:
                    a, n = run["first"], run["count"]
                    h1, h2 = (windows_hash(x[a : a + n + window - 1], window).view(np.int64) for x in (words, other))
                    yield pa.RecordBatch.from_arrays([pa.array(h1), pa.array(h2), pa.array(np.full(n, i)), pa.array(np.arange(a, a + n, dtype=np.int32)), pa.array(np.full(n, a, np.int32))], ["h1", "h2", "key", "first", "stretch"])

    def search(shard: pd.DataFrame) -> pd.DataFrame:
        lengths = shard["words"].map(len).to_numpy() // 8
        words = np.frombuffer(b"".join(shard["words"]), np.uint64)
        keys, firsts = shard["key"].to_numpy(), shard["first"].to_numpy()
        owners = FmIndex(words, lengths, keys, window).first_owners(words, lengths, window)
        repeats = owners < np.repeat(keys, lengths)
        out, at = [], 0
        for i, a, n, s in zip(keys, firsts, lengths, shard["stretch"], strict=True):
            out.extend((i, a + x, a + y, s) for x, y in _intervals(repeats[at : at + n], window))
            at += n
        return pd.DataFrame(out, columns=["key", "first", "last", "stretch"])

    pieced = texts.join(wanted(unclear.where("not crowd")), "key").mapInArrow(pieces, "shard long, key long, first int, words binary, stretch int")
    searched = pieced.groupBy("shard").applyInPandas(search, "key long, first int, last int, stretch int")
    # windows of a crowded anchor are met by their hashes, so that a passage that all documents share needs no shard of its own
    crowded = texts.join(wanted(unclear.where("crowd")), "key").mapInArrow(single, "h1 long, h2 long, key long, first int, stretch int")
    crowded = stash(crowded, "windows")
    least = crowded.groupBy("h1", "h2").agg(F.min("key").alias("least"), F.max("key").alias("most")).where("least < most").select("h1", "h2", "least")
    after = crowded.join(least, ["h1", "h2"]).where("key > least").select("key", "first", (F.col("first") + window).alias("last"), "stretch")
    found = stash(searched.union(after), "found")
    moved = found.join(again, ["key", "stretch"]).select("key", F.col("first") + F.col("shift"), F.col("last") + F.col("shift"))
    return stash(same.union(found.select("key", "first", "last")).union(moved), "repeats").withColumnRenamed("key", key)


def _kept(docs: DataFrame, runs: DataFrame, key: str, text: str, finish, schema: str) -> DataFrame:
    names = [x.split(" ")[0] for x in schema.split(", ")]
    of = runs.groupBy(F.col(key).alias("key")).agg(F.collect_list(F.struct("first", "last")).alias("runs"))
    rows = docs.select(F.col(key).cast("long").alias("key"), F.col(text).cast("string").cast("binary").alias("text")).join(of, "key", "left")

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for t, gone in zip(batch.column("text").to_pylist(), batch.column("runs").to_pylist(), strict=True):
                words = (t or b"").split()
                n = len(words)
                if gone:
                    keep = np.ones(n, bool)
                    for run in gone:
                        keep[run["first"] : run["last"]] = False
                    words = [words[k] for k in np.flatnonzero(keep)]
                out.append(finish(n, words))
            if out:
                yield pa.RecordBatch.from_pydict({"key": batch.column("key")} | {c: pa.array(x) for c, x in zip(names, zip(*out, strict=True), strict=True)})

    return rows.mapInArrow(clean, f"key long, {schema}").withColumnRenamed("key", key)


def digests(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """(key, n_words, n_removed, kept_sha256) of each row."""
    finish = lambda n, words: (n, n - len(words), hashlib.sha256(b" ".join(words)).hexdigest())
    return _kept(docs, repeated(docs, key, text, **how), key, text, finish, "n_words long, n_removed long, kept_sha256 string")


def deduplicated(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """(key, text) of each row, the words that stay joined by one space."""
    return _kept(docs, repeated(docs, key, text, **how), key, text, lambda n, words: (b" ".join(words).decode("utf-8", "replace"),), "text string").withColumnRenamed("text", text)
