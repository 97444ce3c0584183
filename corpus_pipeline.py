"""From raw documents to token ids: five stages, each written and read again.

Quality rules reject documents, shared lines go, one document of each group of
near copies stays, sources are mixed to their target weights, and texts are
encoded.  All stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow.llm import bpe, line_dedup, mixing, ngram_join, quality
from rankflow.llm.common import discard, documents, held, unpacked, written

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: Near copies here: five-word shingles, a similarity of 0.8 or more.
NEAR_WORDS, NEAR_THRESHOLD = 5, (80, 100)


def by_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_quality(docs)


def by_line(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(docs.select(F.struct("*").alias("row"), "doc_id", "text"))
    made = {"text": F.col("text"), "n_chars": F.char_length("text").cast("long")}
    return held(unpacked(out, docs.columns, {c: v for c, v in made.items() if c in docs.columns}), out)


def by_copy(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return ngram_join.keep_one(docs, NEAR_WORDS, NEAR_THRESHOLD)


def by_weight(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, in the mixed order: files by name, rows by place."""
    return mixing.in_order(mixing.mix(docs.select(F.struct("*").alias("row"), "doc_id", "source"))).select("row.*")


def to_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document; ``shard`` and ``place`` are its file and row there, which hold the order."""
    import public_tokenizers

    if docs.inputFiles():
        at = [F.col("_metadata.file_name").alias("shard"), F.col("_metadata.row_index").alias("place")]
    else:
        at = [F.lit(None).cast("string").alias("shard"), F.lit(None).cast("long").alias("place")]
    docs = docs.select("doc_id", "lang", "source", "text", *at)
    out = bpe.encode_documents(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)
    return out.select("doc_id", "lang", "source", "shard", "place", "n_tokens", "token_ids")


STAGES = [("quality", by_quality), ("line_dedup", by_line), ("ngram_join", by_copy), ("mixing", by_weight), ("bpe", to_tokens)]

#: The encoder is beyond SQL; tests compare the stages with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = documents(spark, sf_dir), None
    for name, stage in STAGES[:-1]:
        made = stage(spark, docs, sf_dir)
        docs = written(made, name)
        discard(made, last)
        last = docs
    return held(STAGES[-1][1](spark, docs, sf_dir), docs)
