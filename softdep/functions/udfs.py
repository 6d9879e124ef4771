"""Functions for SQL users that are no expressions: an aggregate over Arrow batches and a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def agreement_agg(left: pd.Series, right: pd.Series) -> float:
    """Agreement of right given left over a group's rows, which must fit one task."""
    d = pd.DataFrame({"x": left, "a": right}).dropna()
    f = d.groupby(["x", "a"]).size()
    return float((f**2).groupby(level=0).sum().div(f.groupby(level=0).sum()).sum() / len(d)) if len(d) else float("nan")


@F.udtf(returnType=T.StructType([T.StructField("subset", T.LongType()), T.StructField("size", T.IntegerType())]))
class SubsetsOf:
    """The non-empty subsets of a bit mask."""

    def eval(self, mask: int) -> Iterator[tuple[int, int]]:
        sub = mask
        while sub:
            yield sub, bin(sub).count("1")
            sub = (sub - 1) & mask


def register(spark: SparkSession) -> None:
    spark.udf.register("agreement_agg", agreement_agg)
    spark.udtf.register("subsets_of", SubsetsOf)


def packed_bits(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """mapInPandas body: the signs of an embedding column as one integer of up to 63 bits."""
    for b in batches:
        v = np.stack(b["embedding"].to_numpy()) if len(b) else np.zeros((0, 1))
        yield pd.DataFrame({"vec_id": b["vec_id"], "bits": ((v[:, :63] > 0) @ (1 << np.arange(min(63, v.shape[1]), dtype=np.int64))).astype(np.int64)})
