"""Tables that cut lineage: written once to the folder all executors share, then read back."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softdep.shared import shared_dir


def bounded_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Arrow batches of whole texts hold at most so many rows from now on: Spark's own limit of rows lets a batch grow to
    many MB in both the JVM and Python. A lower limit of the session stays."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= rows:
        spark.conf.set(name, str(rows))


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder. The result's plan is a scan: a lost executor costs a re-read only."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def collapsed(docs: DataFrame, key: str, text: str) -> DataFrame:
    """(key, text, times): rows of equal key and text as one, a null text as an empty one. Where no row repeats, which hashes
    tell, no text moves; where some do, equal rows are counted before the exchange, so that none is a task's burden."""
    slim = docs.select(F.col(key).alias("key"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    if slim.groupBy("key", F.xxhash64("text")).agg(F.count("*").alias("c")).where("c > 1").isEmpty():
        return slim.withColumn("times", F.lit(1).cast("long"))
    return slim.groupBy("key", "text").agg(F.count("*").alias("times"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
