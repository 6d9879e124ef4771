"""Counts and scores of many candidates X -> A at once."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.functions import measures
from softdep.operators.blocks import block_counts
from softdep.operators.joint import Z, chunk_tables, chunks
from softdep.relation import Relation

Candidate = tuple[Z, int]
COUNTS = "cid int, n long, d_lhs long, d_joint long, max_sum long, d_rhs long, disagree_lhs double, disagree_rhs double"


def _folded(rows: DataFrame) -> DataFrame:
    """Statistics of each cid from rows (cid, side, k1, k2, f): side 0 has a row for each joint group keyed by its left
    group, side 1 keyed by its right value. 1 - agreement is summed as s - q/s, to which pure groups add exactly 0."""
    groups = rows.groupBy("cid", "side", "k1", "k2").agg(F.sum("f").alias("s"), F.sum(F.col("f").cast("double") * F.col("f")).alias("q"), F.count(F.lit(1)).alias("k"), F.max("f").alias("top"))
    left, right = F.col("side") == 0, F.col("side") == 1
    total = groups.groupBy("cid").agg(
        F.sum(F.when(left, F.col("s"))).alias("n"),
        F.sum(F.when(left, F.lit(1))).cast("long").alias("d_lhs"),
        F.sum(F.when(left, F.col("k"))).alias("d_joint"),
        F.sum(F.when(left, F.col("top"))).alias("max_sum"),
        F.sum(F.when(right, F.lit(1))).cast("long").alias("d_rhs"),
        F.sum(F.when(left & (F.col("k") > 1), F.col("s") - F.col("q") / F.col("s"))).alias("dis"),
        F.sum(F.when(right, F.col("s").cast("double") * F.col("s"))).alias("sq"),
    )
    n = F.col("n").cast("double")
    return total.select("cid", "n", "d_lhs", "d_joint", "max_sum", "d_rhs", (F.coalesce("dis", F.lit(0.0)) / n).alias("disagree_lhs"), F.when(F.col("d_rhs") == 1, 0.0).otherwise(1 - F.col("sq") / (n * n)).alias("disagree_rhs"))


def joint_counts(rel: Relation, cands: list[tuple[int, Candidate]], chunk_size: int = 16) -> DataFrame:
    """One aggregation for each joint set serves all its candidates, and a scan serves a chunk of sets."""
    wanted: dict[Z, list[tuple[int, int]]] = {}
    for cid, (lhs, rhs) in cands:
        wanted.setdefault(tuple(sorted((*lhs, rhs))), []).append((cid, rhs))
    spark = rel.df.sparkSession
    parts = []
    for sets in chunks(list(wanted), chunk_size):
        table, gid, attributes = chunk_tables(rel, sets)
        place = {a: i for i, a in enumerate(attributes)}
        rows = [(gid[z], cid, place[rhs]) for z in sets for cid, rhs in wanted[z]]
        listed = F.broadcast(spark.createDataFrame(rows, "gid long, cid int, a int"))  # a row for each candidate of the chunk
        coded = table.select("gid", "f", F.array(*(F.struct(F.col(rel.physical(i)[0]).alias("x"), F.col(rel.physical(i)[-1]).alias("y")) for i in attributes)).alias("v"))
        others = F.transform("v", lambda v, i: F.when(i != F.col("a"), v))
        own = F.element_at("v", F.col("a") + 1)
        left = F.struct(F.lit(0).alias("side"), F.xxhash64(others).alias("k1"), F.xxhash64(F.lit(1), others).alias("k2"))
        right = F.struct(F.lit(1).alias("side"), own["x"].alias("k1"), own["y"].alias("k2"))
        # Without NULLs the right side's counts are those of the whole relation: they are taken once, not for each candidate.
        sides = F.array(left) if rel.null_free else F.array(left, right)
        parts.append(coded.join(listed, "gid").select("cid", "f", F.explode(sides).alias("e")).select("cid", "e.*", "f"))
    folded = _folded(reduce(DataFrame.union, parts))
    if not rel.null_free:
        return folded
    known = spark.createDataFrame([(cid, rel.marginals[rhs].values, rel.marginals[rhs].disagreement) for cid, (_, rhs) in cands if rhs in rel.marginals], "cid int, d_rhs long, disagree_rhs double")
    return folded.drop("d_rhs", "disagree_rhs").join(known, "cid").select("cid", "n", "d_lhs", "d_joint", "max_sum", "d_rhs", "disagree_lhs", "disagree_rhs")


def _shared_counts(rel: Relation, cands: list[tuple[int, Candidate]]) -> DataFrame:
    """The left side is keyed once and all right sides are counted beside it, a scan for each left side."""
    by: dict[Z, list[tuple[int, int]]] = {}
    for cid, (lhs, rhs) in cands:
        by.setdefault(lhs, []).append((cid, rhs))
    parts = []
    for lhs, rights in by.items():
        keys = [F.col(p) for i in lhs for p in rel.physical(i)]
        whole = reduce(lambda a, b: a & b, [k.isNotNull() for k in keys])
        each = F.array(*(F.struct(F.lit(cid).alias("cid"), F.col(rel.physical(a)[0]).alias("x"), F.col(rel.physical(a)[-1]).alias("y")) for cid, a in rights))
        slim = rel.codes.where(whole).select(F.xxhash64(*keys).alias("k1"), F.xxhash64(F.lit(1), *keys).alias("k2"), "w", F.explode(each).alias("e")).where("e.x is not null")
        joint = slim.groupBy("e.cid", "k1", "k2", "e.x", "e.y").agg(F.sum("w").alias("f"))
        left = F.struct(F.lit(0).alias("side"), "k1", "k2")
        right = F.struct(F.lit(1).alias("side"), F.col("x").alias("k1"), F.col("y").alias("k2"))
        parts.append(joint.select("cid", "f", F.explode(F.array(left, right)).alias("s")).select("cid", "s.*", "f"))
    return _folded(reduce(DataFrame.union, parts))


def counts(rel: Relation, cands: list[tuple[int, Candidate]], kernel: str = "blocks", chunk_size: int = 16) -> DataFrame:
    """(cid, n, d_lhs, d_joint, max_sum, d_rhs, disagree_lhs, disagree_rhs); a candidate without a tuple has no row.

    Kernels: 'blocks' (default: refined partitions, NumPy on blocks of rows), 'blocks_each', which shares nothing between
    candidates and drops no row; and by SQL aggregates alone 'joint' (joint tables by GROUPING SETS), 'lhs_shared', and
    'candidate', an aggregation of its own for each candidate.
    """
    if not cands:
        return rel.df.sparkSession.createDataFrame([], COUNTS)
    if kernel in ("blocks", "blocks_each"):
        return block_counts(rel, cands, kernel == "blocks")
    if kernel == "joint":
        return joint_counts(rel, cands, chunk_size)
    if kernel == "lhs_shared":
        return _shared_counts(rel, cands)
    return reduce(DataFrame.union, [_shared_counts(rel, [c]) for c in cands])


def measured(counted: DataFrame, complete_rows: int | None = None) -> DataFrame:
    """counted (as counts gives it, other columns kept) with rho, mu_plus, is_exact, bound, sound_bound, g3_error, gain, lift
    instead of max_sum; null for candidates of one tuple or none."""
    n, d, x, a = F.col("n"), F.col("d_lhs"), F.col("disagree_lhs"), F.col("disagree_rhs")
    some = n > 1
    own = [c for c in counted.columns if c not in ("n", "max_sum", "d_lhs", "d_joint", "d_rhs", "disagree_lhs", "disagree_rhs")]
    return counted.withColumn("n", F.coalesce("n", F.lit(0))).select(
        *own,
        "n",
        "d_lhs",
        "d_joint",
        "d_rhs",
        "disagree_lhs",
        "disagree_rhs",
        F.when(some, measures.rho(n, d, x, a)).alias("rho"),
        F.when(some, measures.mu_plus(n, d, x, a)).alias("mu_plus"),
        F.when(some, F.col("d_joint") == d).alias("is_exact"),
        F.when(some, measures.optimistic_bound(n, d, a)).alias("bound"),
        (F.when(some, measures.sound_bound(n, d, a, F.col("d_rhs"), complete_rows)) if complete_rows is not None else F.lit(None).cast("double")).alias("sound_bound"),
        F.when(some, 1 - F.col("max_sum") / n).alias("g3_error"),
        F.when(some, F.when(a > 0, 1 - x / a).otherwise(1.0)).alias("gain"),
        F.when(some, (1 - x) / (1 - a)).alias("lift"),
    )


def statistics(rel: Relation, cands: list[Candidate], kernel: str = "blocks", complete_rows: int | None = None) -> DataFrame:
    """S-STATS: cid, lhs and rhs positions, counts and measures of every candidate. Those of one tuple or none have n of 0 or 1
    and null scores."""
    numbered = list(enumerate(cands))
    listed = rel.df.sparkSession.createDataFrame([(i, list(x), a) for i, (x, a) in numbered] or [], "cid int, lhs array<int>, rhs int")
    return measured(listed.join(counts(rel, numbered, kernel), "cid", "left"), complete_rows)


def named(rel: Relation, stats: DataFrame) -> DataFrame:
    """stats with lhs as comma-joined column names and rhs as a name."""
    names = F.array(*map(F.lit, rel.columns))
    return stats.withColumn("lhs", F.array_join(F.transform("lhs", lambda i: F.element_at(names, i + 1)), ",")).withColumn("rhs", F.element_at(names, F.col("rhs") + 1))


def agreement(rel: Relation, lhs: list[str], rhs: str) -> float:
    """Probability that two tuples drawn with replacement inside a left group agree on rhs, over all tuples."""
    r = statistics(rel, [(tuple(map(rel.position, lhs)), rel.position(rhs))]).first()
    return 1 - r["disagree_lhs"]


def mu_plus(rel: Relation, lhs: list[str], rhs: str) -> float:
    return statistics(rel, [(tuple(map(rel.position, lhs)), rel.position(rhs))]).first()["mu_plus"]


def holds_exactly(rel: Relation, lhs: list[str], rhs: str) -> bool:
    """By integers only: as many joint groups as left groups."""
    return bool(statistics(rel, [(tuple(map(rel.position, lhs)), rel.position(rhs))]).first()["is_exact"])


def marginal_agreement(rel: Relation) -> DataFrame:
    """(attribute, n, d, agreement): chance agreement of each attribute over its non-NULL tuples, in one pass."""
    parts = []
    for at in range(0, rel.m, 24):  # a grouping id has 64 bits
        sets = [(i,) for i in range(at, min(at + 24, rel.m))]
        table, gid, _ = chunk_tables(rel, sets)
        names = rel.df.sparkSession.createDataFrame([(gid[z], rel.columns[z[0]]) for z in sets], "gid long, attribute string")
        sums = table.groupBy("gid").agg(F.sum("f").alias("n"), F.count("*").alias("d"), F.sum(F.col("f").cast("double") * F.col("f")).alias("q"))
        parts.append(sums.join(F.broadcast(names), "gid").select("attribute", "n", "d", (F.col("q") / F.col("n").cast("double") / F.col("n")).alias("agreement")))
    return reduce(DataFrame.union, parts)
