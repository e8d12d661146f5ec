"""A corpus pipeline of five stages: toxicity, near duplicates, secrets, mixing, encoding.

STAGES is a list of (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame.  Each
result is written as Parquet and read back as the next stage's docs.  All but the last keep the columns of
documents.  Labels of the labelled table train the models; no stage reads a document's own label."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlab.llm import mixing, partenum, secrets, toxicity, unigram
from pairlab.llm.scratch import materialize

#: SQL expresses neither the trained models nor the encoder; the operators behind the stages are tested, the stages themselves only by a test that is skipped.
ORACLE_SQL = None


def _labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score 0.5 or more go; rows without an id are judged by their text as all others."""
    model = toxicity.train(docs, _labels(spark, sf_dir))
    return toxicity.keep(docs, model, 0.5)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest id stays; documents without words all stay."""
    return partenum.keep_one(docs)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each span of a secret becomes a mask; the documents stay."""
    out = secrets.redact(docs)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeat by their rate; the budget lets no domain shrink."""
    return mixing.resample(docs, _labels(spark, sf_dir), mixing.Mixture(weights={"q1t0": 0.88, "q0t0": 0.12}, whole=()))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id and the tokens of each text."""
    return unigram.encode_documents(docs)


STAGES = [("toxicity", drop_toxic), ("near_duplicates", one_of_each_group), ("secrets", mask_secrets), ("mixing", mix_sources), ("encoding", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
