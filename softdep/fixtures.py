"""Small literal relations with known values."""

from __future__ import annotations

from pyspark.sql import SparkSession

from softdep.relation import Relation

SIX = [("a", 1), ("a", 1), ("a", 2), ("b", 3), ("b", 3), ("c", 1)]

NULLBREAK = {
    "c": "0 1 1 0 0 0 0 1 1 0 1 0 1 0 1 1 1 1 0 1 0 1 1 1 1 1",
    "d": "0 1 1 0 0 0 0 0 1 0 0 0 1 0 0 1 1 1 0 1 0 1 1 1 1 0",
    "x": "10 11 12 13 14 15 16 17 18 19 20 21 22 23 24 25 26 27 0 1 0 1 0 1 0 1",
    "b": ". . . . . . . . . . . . . . . . . . 0 0 1 1 0 0 1 1",
    "a": "0 0 0 0 0 0 0 0 0 0 0 0 0 0 0 0 0 0 0 1 1 0 0 1 1 1",
}


def nullbreak_rows() -> list[tuple]:
    cols = [[None if v == "." else int(v) for v in s.split()] for s in NULLBREAK.values()]
    return list(zip(*cols, strict=True))


def six(spark: SparkSession) -> Relation:
    return Relation.of(spark.createDataFrame(SIX, "x string, a int"), name="six")


def nullbreak(spark: SparkSession) -> Relation:
    return Relation.of(spark.createDataFrame(nullbreak_rows(), ", ".join(f"{c} int" for c in NULLBREAK)), name="nullbreak")
