"""Shared-folder tables: where multi-step operators cut their lineage so that a lost executor costs little."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


#: Rows that one Arrow batch hands to Python: texts may be long, and several workers share an executor's memory.
BATCH_ROWS = 1000


def small_batches(spark: SparkSession) -> None:
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def workspace(spark: SparkSession, name: str) -> str:
    """A fresh folder under spark.checkpoint.dir; where that is unset, a temporary one of this machine, which only a session on this machine alone may use."""
    small_batches(spark)
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        root = "file://" + tempfile.mkdtemp(prefix="patcard-")
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


def keep(df: DataFrame, path: str) -> DataFrame:
    """Write a result to the shared folder and read it back: later steps start from files, not from lineage."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop(spark: SparkSession, *paths: str) -> None:
    """Delete finished intermediate tables."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    for path in paths:
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(conf).delete(p, True)


def release(spark: SparkSession) -> None:
    """Let the context cleaner remove the shuffle files of steps whose results are already written."""
    gc.collect()
    spark._jvm.System.gc()


def fresh(df: DataFrame, name: str) -> str:
    """The name, with underscores before it until no column of df has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def holdout(doc_id_column: str, modulus: int, remainder: int) -> str:
    """SQL for 'crc32 of the id as text has this remainder': such rows are never learned from."""
    return f"crc32(cast({doc_id_column} as string)) % {modulus} = {remainder}"
