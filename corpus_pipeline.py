"""Preparing a training corpus: toxic documents go, repeated lines go, one document of each near-duplicate group stays, sources are mixed to target sizes, and texts become token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilebalance.llm import bpe, fuzzylines, mixing, setjoin, toxicity
from tilebalance.llm.common import stash, table
from tilebalance.llm.queries import codec

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a score below one half, by models fitted on the labelled ones among them."""
    scorer = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs.select(*COLUMNS), scorer).where("score < 0.5").select(*COLUMNS)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without lines that an earlier document or line has alike."""
    done = fuzzylines.deduplicated(docs.select(*COLUMNS))
    return done.select("doc_id", "text", "lang", "source", F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")).alias("n_chars"))


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of each group of near-duplicates: those with a Jaccard similarity of 0.8 of their five-word shingles."""
    roots = setjoin.components(docs, n=5, percent=80).where("doc_id = component_id").select("doc_id")
    return docs.select(*COLUMNS).join(roots, "doc_id", "left_semi").select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it: not at all, once or twice."""
    copies = mixing.mixed(docs, mixing.words()).where("copies > 0").select("doc_id", "copies")
    rows = docs.select(*COLUMNS).join(copies, "doc_id")
    return rows.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*COLUMNS)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids in place of texts."""
    # tasks hold lists of ids besides, so fewer words
    ids = bpe.encode_copies(docs.select(*COLUMNS), codec(), resident_words=250_000)
    return ids.withColumn("n_tokens", F.size("ids").cast("long"))


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_repeated_lines),
    ("n-gram Jaccard join", keep_one_of_each_group),
    ("mixing sources to target weights", mix_sources),
    ("byte-level BPE encoding and decoding", tokenize),
]

#: No SQL expresses the toxicity models, the mix or the tokenizer.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = stash(docs, f"stage{i}")
    return docs
