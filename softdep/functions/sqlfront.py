"""A sentence for a search: DISCOVER [TOP 20] DEPENDENCIES FROM t [MAX LHS 3] [FOR rhs] [WITH VARIANT V4] [ABOVE 0.8].

With ABOVE, all dependencies of that score or more; with TOP too, the best of these. Every part holds with every other."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softdep.plans import search
from softdep.relation import Relation

_SENTENCE = re.compile(
    r"\s*discover\s+(?:top\s+(?P<k>\d+)\s+)?dependencies\s+from\s+(?P<table>[\w.`]+)(?:\s+max\s+lhs\s+(?P<l>\d+))?(?:\s+for\s+(?P<rhs>\w+))?(?:\s+with\s+variant\s+(?P<v>v[0-4]))?(?:\s+above\s+(?P<theta>[\d.]+))?\s*;?\s*",
    re.I,
)


def sql(spark: SparkSession, sentence: str) -> DataFrame:
    m = _SENTENCE.fullmatch(sentence)
    if not m:
        return spark.sql(sentence)
    rel = Relation.of(spark.table(m["table"]), name=m["table"])
    variant, rhs = (m["v"] or "V4").upper(), (m["rhs"],) if m["rhs"] else None
    if not m["theta"]:
        return search.top_k(rel, int(m["k"] or 20), int(m["l"] or 5), variant, rhs=rhs)
    above = search.threshold_discovery(rel, float(m["theta"]), int(m["l"] or 5), variant=variant, rhs=rhs)
    return above.orderBy(F.desc("score"), F.size("lhs"), "lhs", "rhs").limit(int(m["k"])) if m["k"] else above
