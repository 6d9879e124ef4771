"""Connected components of an edge table, by alternating large-star and small-star steps on written tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.llm._store import written


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every id in edges(a, b); component is the smallest id reachable. Ids must not be null.

    Each step sends every id's neighbours to its smallest one, as aggregates and joins: no component is ever one task's
    group. The number of steps grows with the logarithm of the number of ids.
    """
    current = written(edges.where("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    while True:
        # Large star: the larger neighbours of each id go to its smallest neighbour (or itself).
        both = current.union(current.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = written(large.where("u != v").distinct(), "large")
        # Small star: the smaller neighbours of each id, and the id, go to the smallest.
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").union(down).distinct()
        step = written(small, "small")
        before, after = (t.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first() for t in (current, step))
        current = step
        if tuple(before) == tuple(after):
            break
    return current.select(F.col("u").alias("id"), F.col("v").alias("component")).union(current.select("v", "v").distinct())
