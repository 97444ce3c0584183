"""The registered queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow.llm import bpe, fingerprint, language, line_dedup, mixing, ngram_join, pii, quality, secrets, sql, toxicity
from rankflow.llm.common import documents

#: A deployment passes its own; this one makes the query's result repeatable.
PII_KEY = "rankflow-demonstration-key"
VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with personal data replaced by format-preserving pseudonyms."""
    out = pii.pseudonymise(documents(spark, sf_dir).select("doc_id", "text"), PII_KEY)
    return out.select("doc_id", "text", F.size("pii_kinds").cast("long").alias("n_replaced"), F.array_join("pii_kinds", ",").alias("kinds"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality measures and verdict of each document."""
    out = quality.quality_report(documents(spark, sf_dir).select("doc_id", "text"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digest of each document after lines found in many documents are dropped."""
    out = line_dedup.dedup_lines(documents(spark, sf_dir).select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Place of each document in the mixed order."""
    out = mixing.mix(documents(spark, sf_dir).select("doc_id", "source"))
    return out.select("doc_id", "source", "mix_block", "mix_slot", "mix_position")


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in each document: those of the base patterns, and what the field adds."""
    docs = documents(spark, sf_dir).select("doc_id", "text")
    out = secrets.find_secrets(docs, secrets.learn(docs))
    base = F.filter("secret_spans", lambda x: x["kind"] != "crf")
    count = [F.size(F.filter("secret_spans", _of_kind(k))).cast("long").alias(f"n_{k}") for k in secrets.KINDS]
    return out.select("doc_id", *count, F.sha2(secrets.listed(base), 256).alias("base_sha256"), secrets.listed(F.col("secret_spans")).alias("spans"))


def _of_kind(kind: str) -> Callable[[Column], Column]:
    return lambda x: x["kind"] == kind


def _remainder(m: int) -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % m, F.lit(0))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of each document, learned from the labels of those not held out."""
    docs = documents(spark, sf_dir).select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(_remainder(4) != 2)
    out = toxicity.score_documents(docs, toxicity.learn(docs, labels))
    return out.select("doc_id", (_remainder(4) == 2).alias("held_out"), "score", (F.col("score") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op7_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of each document and of an edit of it."""
    return fingerprint.compare_with_next(documents(spark, sf_dir))


def op8_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of each document, by profiles of those not held out."""
    docs = documents(spark, sf_dir).select("doc_id", "text", "lang")
    profiles = language.learn(docs.where(_remainder(3) != 1))
    out = language.identify(docs.select("doc_id", "text"), profiles)
    return out.select("doc_id", (_remainder(3) == 1).alias("held_out"), "lang_pred", "score")


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of each document's token ids and of what they decode to."""
    import public_tokenizers

    docs = documents(spark, sf_dir).select("doc_id", "text")
    out = bpe.encode_documents(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN, decode=True)
    return out.select("doc_id", "n_tokens", F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op10_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number of shingles and component of near copies of each document."""
    return ngram_join.linked_components(documents(spark, sf_dir).select("doc_id", "text"))


def op10_ngram_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As ``op10_ngram_join``, with the number of links of each document: no link is left untested."""
    return ngram_join.link_counts(documents(spark, sf_dir).select("doc_id", "text"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_pii, op2_quality, op3_line_dedup, op4_mixing, op5_secrets, op6_toxicity, op7_fingerprint, op8_language, op9_bpe, op10_ngram_join, op10_ngram_links)}


def oracle_sql() -> dict[str, str]:
    """SQL for what SQL can express on whole tables; the tests hold the others against brute force."""
    return {"op2_quality": sql.quality_sql(), "op3_line_dedup": sql.line_dedup_sql(), "op10_ngram_join": sql.ngram_join_sql()}
