"""Sources mixed to target weights by Poisson replication (built-in functions only).

With weights w, a total size T = epochs * (size of all sources) and a source's own size S, its documents repeat
r = w / sum(w) * T / S times in the mean. Each document's number of copies is the Poisson(r) quantile of a uniform number
made from a hash of the seed and its id: repeatable, independent of partitions and of other documents, and with the mean
exact for fractional rates. Copies go to partitions by a hash of seed, id and copy number and are sorted by it inside:
a global shuffle with one exchange and no range sampling.

Only sums by source are aggregated. The table of rates is broadcast while it has at most max_broadcast_sources rows
(counted first) and joined otherwise.

Edge cases. A null source is the source null, weighed by default_weight as every source without a weight. A source of
weight 0 (or below, or null) goes. A source whose texts are all empty has no size to fill and goes too, unless sizes count
documents. Repeated rows of one id are copied alike, and equal shuffle keys stay in any order. A null id hashes as the empty
string. Very long texts move whole, a copy at a time. Empty tables stay empty. Columns named copies, copy or shuffle_key are
replaced, others go along.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Stands for a null source in joins.
NO_SOURCE = "\x00"


def uniform(seed: int, *parts: Column) -> Column:
    """A number in (0, 1) from the first 52 bits of the MD5 of seed and parts."""
    text = F.concat_ws(":", F.lit(str(seed)), *(F.coalesce(p.cast("string"), F.lit("")) for p in parts))
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") + 0.5) / F.lit(float(2**52))


def source_of(docs: DataFrame, source: str = "source") -> Column:
    return F.coalesce(F.col(source).cast("string"), F.lit(NO_SOURCE))


def rates(docs: DataFrame, weights: dict[str, float], epochs: float = 1.0, size: Column | None = None, source: str = "source", default_weight: float = 1.0) -> DataFrame:
    """(source_key, size, weight, rate) of every source of docs; size is the characters of its texts unless given."""
    size = F.length(F.coalesce(F.col("text").cast("string"), F.lit(""))) if size is None else size
    own = docs.select(source_of(docs, source).alias("source_key"), size.cast("long").alias("n")).groupBy("source_key").agg(F.sum("n").alias("size"))
    w = F.lit(float(default_weight))
    for name, value in sorted(weights.items()):
        w = F.when(F.col("source_key") == name, float(value or 0.0)).otherwise(w)
    own = own.withColumn("weight", F.greatest(w, F.lit(0.0)))
    total = own.where("size > 0").agg(F.sum("weight").alias("all_weight"), F.sum("size").alias("all_size")).withColumn("one", F.lit(1))
    rate = F.when((F.col("size") > 0) & (F.col("weight") > 0), F.col("weight") / F.col("all_weight") * F.lit(float(epochs)) * F.col("all_size") / F.col("size")).otherwise(0.0)
    return own.withColumn("one", F.lit(1)).join(F.broadcast(total), "one").select("source_key", "size", "weight", rate.alias("rate"))


def quantiles(rate: Column) -> Column:
    """P(X <= k) for k = 0, 1, ... as far as a double can tell from 1, with terms taken in logarithms."""
    last = F.ceil(rate + 10 * F.sqrt(rate) + 40).cast("int")
    step = F.aggregate(
        F.sequence(F.lit(1), last),
        F.struct((-rate).alias("log"), F.exp(-rate).alias("sum"), F.array(F.exp(-rate)).alias("cdf")),
        lambda a, k: F.struct((a["log"] + F.log(rate) - F.log(k.cast("double"))).alias("log"), (a["sum"] + F.exp(a["log"] + F.log(rate) - F.log(k.cast("double")))).alias("sum"), F.concat(a["cdf"], F.array(a["sum"] + F.exp(a["log"] + F.log(rate) - F.log(k.cast("double"))))).alias("cdf")),
        lambda a: a["cdf"],
    )
    return F.when(rate > 0, step).otherwise(F.array(F.lit(1.0)))


def replicated(docs: DataFrame, rate_table: DataFrame, seed: int = 0, key: str = "doc_id", source: str = "source", partitions: int | None = None, max_broadcast_sources: int = 10_000) -> DataFrame:
    """docs with copies (how many), copy (1, 2, ...) and shuffle_key, in shuffled order."""
    table = rate_table.select("source_key", quantiles(F.col("rate")).alias("__cdf"))
    few = rate_table.count() <= max_broadcast_sources
    base = docs.drop("copies", "copy", "shuffle_key").withColumn("source_key", source_of(docs, source))
    joined = base.join(F.broadcast(table) if few else table, "source_key")
    u = uniform(seed, F.col(key))
    counted = joined.withColumn("__u", u).withColumn("copies", F.size(F.filter("__cdf", lambda c: c < F.col("__u")))).drop("__cdf", "__u", "source_key").where("copies > 0")
    many = counted.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    shuffled = many.withColumn("shuffle_key", uniform(seed + 1, F.col(key), F.col("copy")))
    dealt = shuffled.repartition(partitions, "shuffle_key") if partitions else shuffled.repartition("shuffle_key")
    return dealt.sortWithinPartitions("shuffle_key")
