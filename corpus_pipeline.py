"""From documents to a training mix: STAGES in order, each written and read again between.

Edge cases of all stages: null and empty texts fail the quality rules, so that the later stages see none; very long texts
are read whole; of tied documents in a group the smallest id stays, then the least hash of the text; repeated rows are each
judged, and are one document from the join stage on; empty tables give empty ones. Extra columns go through unchanged until
mixing, whose own (copies, copy, shuffle_key) replace columns of these names.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softdep.llm import decontaminate, jaccard, mixing, quality, toxicity
from softdep.llm._store import table, written
from softdep.llm.queries import MIX_WEIGHTS

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored under 0.5. Null and empty texts stay."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return docs.where(toxicity.scored(model, F.col("text")) < 0.5)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and every certified cutoff; texts without words fail."""
    slim = docs.select("doc_id", "text", "lang")
    feats = written(quality.measured(slim).drop("text", "lang"), "measured")
    cutoffs = written(quality.certified(feats, table(spark, sf_dir, "labels")), "cutoffs")
    # The counts are made again beside the whole rows: cheaper in memory and disk than to write every text once more.
    held = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("__doc"), "doc_id", "text", "lang")
    return quality.judged(quality.measured(held), cutoffs).where("kept").select("__doc.*")


def jaccard_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one of the smallest id, and of its texts then the one of the least hash. Rows
    equal in id and text are one document. Documents of one id but unlike texts are each other's equals: none stands for
    another. Rows without an id stay, as none can stand for another."""
    found = jaccard.members(docs).where("key is not null")
    first = found.where("component is not null").groupBy("component").agg(F.min(F.struct("key", "mark")).alias("f")).select("f.key", "f.mark")
    kept = first.unionByName(found.where("component is null").select("key", "mark")).select(F.col("key").alias("doc_id"), F.col("mark").alias("__mark"))
    marked = docs.withColumn("__mark", F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    one = marked.join(kept, ["doc_id", "__mark"], "left_semi").dropDuplicates(["doc_id", "__mark"]).drop("__mark")
    return one.unionByName(docs.where("doc_id is null"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak no benchmark item."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Copies of the documents in shuffled order, with copies, copy and shuffle_key."""
    return mixing.replicated(docs, mixing.rates(docs, MIX_WEIGHTS), seed=11)


STAGES: list[tuple[str, Stage]] = [
    ("toxicity", toxicity_stage),
    ("quality_rules", quality_stage),
    ("ngram_jaccard_join", jaccard_stage),
    ("benchmark_decontamination", decontamination_stage),
    ("mixing", mixing_stage),
]

#: Learnt scores and shingle links are beyond SQL; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs, name)
    return docs
