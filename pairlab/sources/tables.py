"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


#: A session setting of Spark that may change at any time: remove an execution's shuffle files when it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, or some of its columns (the scan then reads no others)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_chats(spark: SparkSession, path: str) -> DataFrame:
    """JSON lines with fixed schema; a line that does not parse is kept in _corrupt."""
    schema = "conv_id long, messages array<struct<role:string,content:string>>, _corrupt string"
    return spark.read.schema(schema).option("columnNameOfCorruptRecord", "_corrupt").json(path)


def write_chats(chats: DataFrame, path: str) -> None:
    chats.write.mode("overwrite").json(path)


def write_by(df: DataFrame, path: str, *keys: str) -> None:
    """Parquet by keys; a rerun replaces only the partitions it writes."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*keys).parquet(path)


def shared_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the session's shared folder, or under its warehouse if none is set."""
    import uuid

    root = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    return f"{root.rstrip('/')}/pairlab-{name}-{uuid.uuid4().hex}"


def saved(df: DataFrame, name: str) -> DataFrame:
    """df written once and read back; cuts its lineage, and removes the shuffles behind it as soon as it is written."""
    spark = df.sparkSession
    path = shared_path(spark, name)
    before = spark.conf.get(CLEANUP)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def words(text: Column) -> Column:
    """Whitespace-separated words of a text column."""
    return F.filter(F.split(text, "\\s+"), lambda w: w != "")


def shingles(text: Column, n: int) -> Column:
    """Runs of n words, joined by spaces; null for fewer words. The words are bound once, so that no rewrite of the
    plan splits the text again for every run."""
    runs = lambda w: F.when(F.size(w) >= n, F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - (n - 1), F.lit(1))), lambda i: F.array_join(F.slice(w, i, F.lit(n)), " ")))
    return F.element_at(F.transform(F.array(words(text)), runs), 1)
