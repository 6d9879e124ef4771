"""Writing result lists and reports."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.plans.report import RunReport


def write_topk(topk: DataFrame, path: str, relation: str, format: str = "parquet", mode: str = "append") -> None:
    """A result list under its relation's partition. Text formats get the left side comma-joined."""
    df = topk.withColumn("relation", F.lit(relation))
    df = df.withColumn("lhs", F.array_join("lhs", ",")) if format in ("csv", "text") else df
    if format == "table":
        df.write.mode(mode).partitionBy("relation").saveAsTable(path)
    else:
        df.write.mode(mode).partitionBy("relation").format(format).save(path)


def write_report(report: RunReport, spark, path: str) -> None:
    spark.createDataFrame([(report.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(path)
