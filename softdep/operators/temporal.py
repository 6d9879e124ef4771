"""Columns from earlier rows: as-of and interval joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def micros(c):
    """Microseconds of a time with or without zone."""
    return F.unix_micros(F.col(c).cast("timestamp"))


def previous_value(df: DataFrame, key: str, ts: str, value: str, alias: str, bucket_seconds: int = 86400) -> DataFrame:
    """df with the value of the key's latest strictly earlier row; among equal times the greatest value. Null without one.
    Dealt by key and time bucket, as in asof_join."""
    earlier = df.select(F.col(key), F.col(ts).alias("__earlier"), F.col(value).alias(alias))
    return asof_join(df, earlier, key, ts, "__earlier", [alias], bucket_seconds, strict=True)


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, right_ts: str, columns: list[str], bucket_seconds: int = 86400, strict: bool = False) -> DataFrame:
    """left with the columns of right's latest row of the key at or before ts (before ts if strict). The key's rows are dealt
    by time bucket, and the last row of earlier buckets is carried over, so that a key with many rows is no single task's."""
    slot = lambda c: F.floor(micros(c) / (bucket_seconds * 1_000_000))
    r = right.select(F.col(key), slot(right_ts).alias("__slot"), micros(right_ts).alias("__t"), F.struct(micros(right_ts).alias("t"), *columns).alias("__row"))
    li = left.withColumn("__slot", slot(ts)).withColumn("__t", micros(ts)).withColumn("__row", F.lit(None).cast(r.schema["__row"].dataType))
    slots = li.select(key, "__slot").union(r.select(key, "__slot")).distinct().join(r.groupBy(key, "__slot").agg(F.max("__row").alias("__last")), [key, "__slot"], "left")
    carried = slots.withColumn("__carried", F.last("__last", ignorenulls=True).over(Window.partitionBy(key).orderBy("__slot").rowsBetween(Window.unboundedPreceding, -1))).select(key, "__slot", "__carried")
    both = li.withColumn("__left", F.lit(True)).unionByName(r, allowMissingColumns=True)
    inside = Window.partitionBy(key, "__slot").orderBy("__t").rangeBetween(Window.unboundedPreceding, -1 if strict else 0)
    near = both.withColumn("__near", F.max("__row").over(inside)).where("__left")
    out = near.join(carried, [key, "__slot"], "left").withColumn("__found", F.coalesce("__near", "__carried"))
    return out.select(*left.columns, *(F.col(f"__found.{c}").alias(c) for c in columns))


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, right_ts: str, before_seconds: int) -> DataFrame:
    """Pairs of equal key with right_ts in [ts - before_seconds, ts). Time buckets of the interval's length are part of the
    join key, so that a row meets two buckets of its key and not all its rows."""
    length = before_seconds * 1_000_000
    a = left.withColumn("__t", micros(ts)).withColumn("__b", F.explode(F.array(F.floor(F.col("__t") / length), F.floor(F.col("__t") / length) - 1)))
    b = right.withColumn("__u", micros(right_ts)).withColumn("__b", F.floor(F.col("__u") / length))
    return a.join(b, [key, "__b"]).where((F.col("__u") < F.col("__t")) & (F.col("__u") >= F.col("__t") - length)).drop("__t", "__u", "__b")
