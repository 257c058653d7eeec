"""Byte-level BPE encoding and decoding through one shuffle of distinct words.

Texts are cut into pre-tokens; the distinct pre-tokens of all texts meet in one shuffle and each is
encoded once. A join of every occurrence with its word would put the occurrences of `the` into one task, so the most
frequent words, up to a fixed number (`resident_words`; none if 0), form a table that every task holds: a
join with a broadcast side of bounded size. The results are the same with any number. The occurrences of all others, with their document and their place, are joined with the rest of the table by
word, gathered per document and put where they belong. Decoding joins ids with the token-byte table,
whose size is the vocabulary's.

Nulls count as empty texts and encode to no ids. Repeated doc_ids are kept apart by a running number of
their rows. Any other column is passed through `encode` untouched under its own name."""

from __future__ import annotations

import base64
import hashlib
import re
from collections import Counter
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh, stash

#: Words that every task may hold; about 100 MB in a Python worker, whatever the input.
RESIDENT_WORDS = 400_000
#: Characters for which classes are spelt out; the number that stands for a word that is not resident.
_NEAR, _GAP = 0x250, 0xFFFFFF


def load_ranks(path: str) -> dict[bytes, int]:
    """The ranks of a rank file: a base64 token and its rank on each line."""
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, filter(None, map(bytes.strip, lines)))}


class Codec:
    """Cuts texts by a pattern, encodes single words and decodes ids; sent to the tasks as its rank table."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, pattern
        self.width = "<u2" if max(ranks.values(), default=0) < 0xFFFF else "<u4"

    def __getstate__(self):
        return self.ranks, self.pattern

    def __setstate__(self, state):
        self.__init__(*state)

    def cutter(self):
        """Splits a text into pre-tokens. Texts of the first letters of Unicode take a plainer engine, twice as fast, with the same classes spelt out."""
        # the pattern's \s means Unicode's White_Space to the reference tokenizer
        space = r"\p{White_Space}"
        whole = regex.compile(self.pattern.replace(r"[^\s", rf"[^{space}").replace(r"\s", space).replace(r"\S", r"\P{White_Space}")).findall
        s, letters, digits = (_spelt(x) for x in (space, r"\p{L}", r"\p{N}"))
        plain = self.pattern.replace(r"[^\s\p{L}\p{N}]", f"[^{s}{letters}{digits}]").replace(r"\p{L}", f"[{letters}]").replace(r"\p{N}", f"[{digits}]").replace(r"\s", f"[{s}]").replace(r"\S", f"[^{s}]")
        if re.search(r"\\(?!u)", plain):  # the pattern has more classes than these
            return whole
        near, far = re.compile(plain).findall, re.compile(f"[^\\u0000-\\u{_NEAR - 1:04x}]").search
        return lambda text: whole(text) if far(text) else near(text)

    def encoder(self):
        """The merges of a whole word: to a pattern that cuts nothing, a text is one word."""
        import tiktoken

        return tiktoken.Encoding("words", pat_str=r"(?s:.+)", mergeable_ranks=self.ranks, special_tokens={}).encode_ordinary

    def token_bytes(self) -> dict[int, bytes]:
        return {rank: token for token, rank in self.ranks.items()}


def _spelt(of: str) -> str:
    """The characters of a class among the first of Unicode, as ranges."""
    codes = [c for c in range(_NEAR) if regex.fullmatch(of, chr(c))]
    starts = [c for c in codes if c - 1 not in codes]
    ends = [c for c in codes if c + 1 not in codes]
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in zip(starts, ends, strict=True))


def _planes(numbers: np.ndarray) -> bytes:
    """Whole numbers below 2**24 as their lowest bytes, then the next, then the highest: packs better than number by number."""
    return numbers.astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3].T.tobytes()


def _numbers(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(raw, np.uint8).reshape(3, -1).astype(np.uint32)
    return planes[0] | planes[1] << 8 | planes[2] << 16


def _texts(batch: pa.RecordBatch, name: str) -> list[str]:
    return [x or "" for x in batch.column(name).to_pylist()]


def _column(values: tuple) -> pa.Array:
    """An Arrow column; arrays of whole numbers become lists without a Python object for each."""
    if isinstance(values[0], np.ndarray):
        return pa.ListArray.from_arrays(np.cumsum([0, *map(len, values)]).astype(np.int32), np.concatenate(values))
    return pa.array(values)


def _digest(blob: bytes, width: str, table: dict[int, bytes]) -> tuple[int, str, str]:
    ids = np.frombuffer(blob, width)
    return len(ids), hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest(), hashlib.sha256(b"".join(map(table.__getitem__, ids.tolist()))).hexdigest()


def word_table(docs: DataFrame, codec: Codec, text: str = "text") -> DataFrame:
    """(word, n, ids): each distinct pre-token of all texts, its occurrences and its ids, encoded once."""
    shared = docs.sparkSession.sparkContext.broadcast(codec)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut = shared.value.cutter()
        seen: Counter = Counter()

        def out():
            words = pa.RecordBatch.from_arrays([pa.array(seen.keys(), pa.string()), pa.array(seen.values(), pa.int64())], ["word", "n"])
            seen.clear()
            return words

        for batch in batches:
            for value in _texts(batch, text):
                seen.update(cut(value))
                if len(seen) > 500_000:
                    yield out()
        yield out()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        piece, width = shared.value.encoder(), shared.value.width
        for batch in batches:
            ids = [np.array(piece(w), width).tobytes() for w in batch.column("word").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("word"), batch.column("n"), pa.array(ids, pa.binary())], ["word", "n", "ids"])

    counted = docs.select(F.col(text).cast("string").alias(text)).mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return stash(counted.mapInArrow(encode, "word string, n long, ids binary"), "words")


def _frequent(words: DataFrame, most: int) -> int:
    """The least number of occurrences of a resident word: at most `most` words have as many."""
    held = 0
    for n, count in words.groupBy(F.least("n", F.lit(1 << 16)).alias("n")).count().orderBy(F.desc("n")).toLocalIterator():
        held += count
        if held > most:
            return n + 1
    return 1


def _packed(words: DataFrame) -> bytes:
    """Words and their ids, the most frequent first, as one piece of memory."""
    top = words.select("word", "ids", "n").toArrow().sort_by([("n", "descending"), ("word", "ascending")]).select(["word", "ids"])
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, top.schema) as out:
        out.write_table(top)
    return sink.getvalue().to_pybytes()


def _column_of(packed: bytes, name: str) -> list:
    return pa.ipc.open_stream(packed).read_all().column(name).to_pylist()


def _assembled(docs: DataFrame, codec: Codec, text: str, key: str, finish, schema: str, resident_words: int, carry: tuple[str, ...] = ()) -> DataFrame:
    """Rows of `finish(blob)` for each row of docs, with its key and a struct of the columns to carry; blob holds the row's ids in the
    codec's width. Rows that share a key must share their text."""
    spark = docs.sparkSession
    words = word_table(docs, codec, text)
    bar = _frequent(words, resident_words)
    shared = spark.sparkContext.broadcast((codec, _packed(words.where(F.col("n") >= bar))))
    other = F.struct(F.lit(0).alias("_"), *carry).alias("carry")
    texts = docs.select(F.col(key).alias("key"), F.col(text).cast("string").alias("text"), other)
    names = [x.split(" ")[0] for x in schema.split(", ")]

    def rare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, cut = frozenset(_column_of(shared.value[1], "word")), shared.value[0].cutter()
        for batch in batches:
            rows: tuple[list, list, list] = ([], [], [])
            for i, value in zip(batch.column("key").to_pylist(), _texts(batch, "text"), strict=True):
                others = [w for w in cut(value) if w not in held]
                rows[0].extend([i] * len(others))
                rows[1].extend(range(len(others)))
                rows[2].extend(others)
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], batch.column("key").type), pa.array(rows[1], pa.int32()), pa.array(rows[2], pa.string())], ["key", "place", "word"])

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        codec, keys = shared.value[0], _column_of(shared.value[1], "word")
        get, cut = dict(zip(keys, range(len(keys)), strict=True)).get, codec.cutter()
        pack = zstandard.ZstdCompressor(3).compress
        for batch in batches:
            blobs = []
            for value in _texts(batch, "text"):
                found = cut(value)
                blobs.append(pack(_planes(np.fromiter(map(get, found, repeat(_GAP)), np.uint32, len(found)))))
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(blobs, pa.binary()), batch.column("carry")], ["key", "blob", "carry"])

    def last(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        unpack = zstandard.ZstdDecompressor().decompress
        codec, table = shared.value[0], _column_of(shared.value[1], "ids")
        end = finish(codec)
        for batch in batches:
            rows = []
            for blob, filled in zip(batch.column("blob").to_pylist(), batch.column("filled").to_pylist(), strict=True):
                numbers = _numbers(unpack(blob))
                at = np.flatnonzero(numbers == _GAP)
                numbers[at] = 0
                parts = list(map(table.__getitem__, numbers.tolist())) if table else [b""] * len(numbers)
                for i, x in zip(at.tolist(), sorted(filled or (), key=lambda x: x["place"]), strict=True):
                    parts[i] = x["ids"]
                ids = b"".join(parts)
                rows.append(end(ids))
            if rows:
                yield pa.RecordBatch.from_pydict({"key": batch.column("key")} | {n: _column(c) for n, c in zip(names, zip(*rows, strict=True), strict=True)} | {"carry": batch.column("carry")})

    kind = docs.schema[key].dataType.simpleString()
    carried = texts.schema["carry"].dataType.simpleString()
    blobs = texts.mapInArrow(first, f"key {kind}, blob binary, carry {carried}")
    if bar > 1:
        found = texts.select("key", "text").mapInArrow(rare, f"key {kind}, place int, word string").join(words.where(F.col("n") < bar).select("word", "ids"), "word")
        filled = found.groupBy("key").agg(F.collect_set(F.struct("place", "ids")).alias("filled"))
        blobs = blobs.join(filled, "key", "left")
    else:
        blobs = blobs.withColumn("filled", F.lit(None).cast("array<struct<place:int,ids:binary>>"))
    return blobs.mapInArrow(last, f"key {kind}, {schema}, carry {carried}")


def digests(docs: DataFrame, codec: Codec, key: str = "doc_id", text: str = "text", resident_words: int = RESIDENT_WORDS) -> DataFrame:
    """(key, n_tokens, ids_sha256, decoded_sha256) of each row; the key must be unique and not null."""

    def finish(codec):
        table = codec.token_bytes()
        return lambda ids: _digest(ids, codec.width, table)

    return _assembled(docs, codec, text, key, finish, "n_tokens long, ids_sha256 string, decoded_sha256 string", resident_words).drop("carry").withColumnRenamed("key", key)


def encode(docs: DataFrame, codec: Codec, text: str = "text", to: str = "ids", resident_words: int = RESIDENT_WORDS, keep_text: bool = True) -> DataFrame:
    """docs with a column of ids, array<int>, instead of one of the same name; empty for null or empty texts. Without keep_text they stand in place of the texts."""
    row = fresh("row", docs)
    keyed = stash(docs.drop(to).withColumn(row, F.monotonically_increasing_id()), "rows")

    def finish(codec):
        return lambda ids: (np.frombuffer(ids, codec.width).astype(np.int32),)

    ids = _assembled(keyed, codec, text, row, finish, "ids array<int>", resident_words).select(F.col("key").alias(row), F.col("ids").alias(to))
    return (keyed if keep_text else keyed.drop(text)).join(ids, row).drop(row)


def encode_copies(docs: DataFrame, codec: Codec, key: str = "doc_id", text: str = "text", to: str = "ids", resident_words: int = RESIDENT_WORDS) -> DataFrame:
    """docs with ids in place of texts, where rows that share a key are copies of one text; keys are not null.

    Nothing is written between, and no row is joined with its text again."""
    others = tuple(c for c in docs.columns if c not in (key, text, to))

    def finish(codec):
        return lambda ids: (np.frombuffer(ids, codec.width).astype(np.int32),)

    rows = _assembled(docs, codec, text, key, finish, "ids array<int>", resident_words, others)
    return rows.select(F.col("key").alias(key), *[F.col("carry").getField(c).alias(c) for c in others], F.col("ids").alias(to))


def decode(rows: DataFrame, codec: Codec, ids: str = "ids", to: str = "text") -> DataFrame:
    """rows with the text of their ids, by the token-byte table; null ids give null, unknown ids raise KeyError."""
    shared = rows.sparkSession.sparkContext.broadcast(codec)

    def decoded(batches):
        table = shared.value.token_bytes()
        for batch in batches:
            texts = [None if x is None else b"".join(map(table.__getitem__, x)).decode("utf-8", "replace") for x in batch.column(ids).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(texts, pa.string())], [*kept, to])

    kept = [c for c in rows.columns if c != to]
    return rows.mapInArrow(decoded, T.StructType([rows.schema[c] for c in kept] + [T.StructField(to, T.StringType())]))
