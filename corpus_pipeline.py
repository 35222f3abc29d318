"""A corpus pipeline of five operators: toxicity, n-gram join, decontamination, mixing, token files.

Each stage takes the documents that its predecessor kept and applies its operator to all of them. Null, empty and very
long texts, repeated rows and empty tables are handled as each operator states.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession

from rankscan.llm import decontaminate, mixture, ngramjoin, queries, tokenfile, toxicity
from rankscan.llm.common import cut, lighten, shared_path, table, tidy, without

#: The near-duplicate stage's rule: words of a shingle, least Jaccard similarity of two documents' sets.
NEAR_WORDS, NEAR_SHARE = 5, Fraction(4, 5)


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score is at least 0.5 go."""
    lighten(spark)
    scored = toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))
    return without(docs, scored.where("score >= 0.5"))


def ngram_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of the n-gram join stays, that of the least id; of equal rows one stays.

    Near copies share at least 4/5 of their five-word shingles; op4's three words and 9/10 bind that query alone.
    """
    lighten(spark)
    joined = cut(ngramjoin.jaccard_join(docs, k=NEAR_WORDS, threshold=NEAR_SHARE))  # read three times below
    tidy(spark)
    repeated = joined.groupBy("doc_id", "text_key").count().where("count > 1")
    kept = docs if repeated.isEmpty() else docs.dropDuplicates(["doc_id", "text"])
    return without(kept, ngramjoin.one_of_each(joined))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents contaminated by benchmark items go."""
    tidy(spark)
    judged = decontaminate.contamination(docs, table(spark, sf_dir, "benchmark"))
    return without(docs, judged.where("contaminated"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix to target weights has them, with a budget of the tokens there are."""
    tidy(spark)
    return mixture.mixed_documents(docs, mixture.mix(docs))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Writes token files and returns what is read back from them, a row per document."""
    lighten(spark)
    return tokenfile.encode_and_check(docs, queries.TOKENIZER)


STAGES = [
    ("toxicity", toxicity_stage),
    ("ngram_jaccard_join", ngram_stage),
    ("decontamination", decontamination_stage),
    ("source_mixture", mixing_stage),
    ("token_files", token_stage),
]
#: SQL has no learned scores and no tokenizer; tests/llm holds the near-duplicate and decontamination stages against
#: brute-force versions and the other stages' operators against theirs.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each result but the last is written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = shared_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
