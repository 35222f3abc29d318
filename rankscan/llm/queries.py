"""The queries op1 to op10 over the synthetic tables, each a thin digest of its operator's results."""

from __future__ import annotations

from fractions import Fraction

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bitslice, decontaminate, mixture, ngramjoin, oracles, quality, tokenfile, toxicity, transcripts, urlrules, warcaudit
from .common import cut, held_out, table

TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.drop("items", "text_key")


def op2_source_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.mix(table(spark, sf_dir, "documents")).drop("text_key")


def op3_bit_sliced_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bitslice.top_k(table(spark, sf_dir, "embeddings"))


def op4_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = ngramjoin.jaccard_join(table(spark, sf_dir, "documents"), k=3, threshold=Fraction(9, 10))
    return out.select("doc_id", "n_shingles", "component_id", "n_links")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.size("sentences").alias("n_offending"))


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.encode_and_check(table(spark, sf_dir, "documents"), TOKENIZER)


def op7_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlrules.judge(table(spark, sf_dir, "pages"), urlrules.rules_frame(spark, urlrules.RULES))


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = transcripts.transcript_lines(table(spark, sf_dir, "conversations"))
    known = lines.where(~held_out(F.col("conv_id")))
    return transcripts.render(transcripts.decode(lines, transcripts.train(known)))


def op9_warc_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    leaves, replica = (cut(warcaudit.records(x)) for x in (pages, warcaudit.corrupted(pages)))
    differ = warcaudit.audit(leaves, replica).withColumn("corrupt", F.lit(True))
    out = leaves.join(differ, ["file", "pos"], "left")
    return out.select("page_id", "file", "pos", "offset", "length", "digest", "copies", F.coalesce("corrupt", F.lit(False)).alias("corrupt"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = quality.score(docs, quality.train(docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


_ALL = (
    op1_decontamination, op2_source_mixture, op3_bit_sliced_top_k, op4_ngram_jaccard_join, op5_toxicity, op6_token_files,
    op7_url_rules, op8_chat_format, op9_warc_fixity, op10_quality,
)
QUERIES = {f.__name__: f for f in _ALL}
ORACLE_SQL: dict[str, str] = oracles.SQL
