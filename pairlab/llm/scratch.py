"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: dict[str, str] = {}
#: A session setting of Spark that may change at any time: remove an execution's shuffle files when it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Another: bytes of rows that a task gathers before Python gets them. Spark's 64 MB are held in the JVM (twice, while a buffer grows) and in Python.
BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def shared_dir(spark: SparkSession) -> str:
    """The cluster's spark.checkpoint.dir; a folder of this process only where none is set (tests)."""
    known = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if known:
        return known.rstrip("/")
    return _own.setdefault("dir", tempfile.mkdtemp(prefix="pairlab-"))


def materialize(df: DataFrame, name: str, partition_by: tuple[str, ...] = (), codec: str = "snappy") -> DataFrame:
    """Write df once as Parquet under a fresh name and read it back; cuts the lineage.

    A lost executor costs only its running tasks, since the files are in shared storage.  The shuffles behind the table are
    removed as soon as it is written: nothing reads them again.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/pairlab-llm/{name}-{uuid.uuid4().hex}"
    before = {k: spark.conf.get(k) for k in (CLEANUP, BATCH)}
    spark.conf.set(CLEANUP, "true")
    spark.conf.set(BATCH, "5000000b")
    try:
        df.write.partitionBy(*partition_by).option("compression", codec).parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables of materialize that nothing reads again; what was made of them has to be written already."""
    for df in tables:
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df.scratch_path)
        path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return df.select(*columns) if columns else df
