"""The tuples that violate a dependency, and what to change."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.operators.joint import non_null
from softdep.relation import Relation


def _groups(rel: Relation, lhs: list[str], rhs: str) -> DataFrame:
    """(lhs..., group_size, distinct_rhs, majority, majority_count); ties for the majority go to the smallest value.
    Joint counts first, so that no group of tuples meets in one task."""
    whole = rel.df.select(*lhs, rhs).where(non_null([*lhs, rhs]))
    joint = whole.groupBy(*lhs, rhs).agg(F.count("*").alias("f"))
    best = F.min(F.struct((-F.col("f")).alias("nf"), F.col(f"`{rhs}`").alias("v")))
    return joint.groupBy(*lhs).agg(F.sum("f").alias("group_size"), F.count("*").alias("distinct_rhs"), best.alias("best")).select(*lhs, "group_size", "distinct_rhs", F.col("best.v").alias("majority"), (-F.col("best.nf")).alias("majority_count"))


def violations(rel: Relation, lhs: list[str], rhs: str, keep_all: bool = False, max_broadcast_rows: int = 100_000, salts: int = 32) -> DataFrame:
    """S-VIOLATION: the tuples of groups with more than one right value (keep_all: every complete tuple), with group_size,
    rhs_count, majority and is_violation, true where the tuple's value is not the group's majority.

    What is known of each left group and right value is broadcast while it has at most max_broadcast_rows rows (counted
    first); else each of its rows goes to salts places and a tuple to one of these, so that no group is a task's burden."""
    whole = rel.df.where(non_null([*lhs, rhs]))
    groups = _groups(rel, lhs, rhs)
    groups = groups if keep_all else groups.where("distinct_rhs > 1")
    joint = whole.groupBy(*lhs, rhs).agg(F.count("*").alias("rhs_count"))
    known = joint.join(groups.drop("distinct_rhs", "majority_count"), lhs)
    if known.limit(max_broadcast_rows + 1).count() <= max_broadcast_rows:
        out = whole.join(F.broadcast(known), [*lhs, rhs])
    else:
        salted = whole.withColumn("__salt", F.pmod(F.xxhash64(*rel.columns), F.lit(salts)).cast("int"))
        out = salted.join(known.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))), [*lhs, rhs, "__salt"])
    return out.select(*rel.columns, "group_size", "rhs_count", "majority", (F.col(f"`{rhs}`") != F.col("majority")).alias("is_violation"))


def suggest_repairs(rel: Relation, lhs: list[str], rhs: str) -> DataFrame:
    """(lhs..., found, suggested, n_rows, support): for each minority value of a group its majority; support is the
    majority's share of the group."""
    groups = _groups(rel, lhs, rhs).where("distinct_rhs > 1")
    joint = rel.df.select(*lhs, rhs).where(non_null([*lhs, rhs])).groupBy(*lhs, rhs).agg(F.count("*").alias("n_rows"))
    return joint.join(groups, lhs).where(F.col(f"`{rhs}`") != F.col("majority")).select(*lhs, F.col(f"`{rhs}`").alias("found"), F.col("majority").alias("suggested"), "n_rows", (F.col("majority_count") / F.col("group_size")).alias("support"))
