"""Joint tables: how often each combination of values of a set of attributes occurs."""

from __future__ import annotations

from functools import reduce
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.relation import Relation

Z = tuple[int, ...]


def non_null(columns: list[str]):
    """Conjunction of IS NOT NULL, which reaches the Parquet scan."""
    return reduce(lambda a, b: a & b, [F.col(f"`{c}`").isNotNull() for c in columns])


def joint_table(rel: Relation, columns: list[str]) -> DataFrame:
    """(columns..., f) over the tuples without NULL in columns."""
    df = rel.df.select(*columns)
    return (df.where(non_null(columns)) if rel.null_policy == "ignore" else df).groupBy(*columns).agg(F.count("*").alias("f"))


def chunks(sets: list[Z], size: int = 16, most: int = 30) -> list[list[Z]]:
    """The sets in lexicographic order, cut into runs: neighbours share most of their columns. A run has at most most
    attributes, two columns each, as a grouping id has 64 bits."""
    out: list[list[Z]] = []
    held: set[int] = set()
    for z in sorted(sets):
        if out and len(out[-1]) < size and len(held | set(z)) <= most:
            out[-1].append(z)
            held |= set(z)
        else:
            out.append([z])
            held = set(z)
    return out


def chunk_tables(rel: Relation, sets: list[Z]) -> tuple[DataFrame, dict[Z, int], list[int]]:
    """The joint tables of all sets by one scan: (code columns, f, gid), the sets' gid, and the attributes in the columns.

    Rows with a NULL among their set's columns are dropped after the aggregation, as the sets differ in what they need.
    """
    attributes = sorted({i for z in sets for i in z})
    names = [p for i in attributes for p in rel.physical(i)]
    width = len(names)
    gid = {z: sum(1 << (width - 1 - names.index(p)) for i in attributes if i not in z for p in rel.physical(i)) for z in sets}
    base = rel.codes.select(*names, "w")
    if len(sets) > 1 and rel.null_free:
        most = prod(rel.marginals[i].values for i in attributes if i in rel.marginals)
        if 4 * most <= rel.size:
            # The chunk's columns have few combinations: count these once and roll the sets up from them.
            base = base.groupBy(*names).agg(F.sum("w").alias("w"))
    grouped = base.groupingSets([[F.col(p) for i in z for p in rel.physical(i)] for z in sets], *names)
    table = grouped.agg(F.sum("w").alias("f"), F.grouping_id().alias("gid"))
    nulls = reduce(lambda a, b: a + b, [F.col(n).isNull().cast("int") for n in names])
    return table.where(nulls == F.bit_count("gid")), gid, attributes


#: Attributes to a word of a pattern, as in the right-side masks of the lattice.
WORD = 62


def null_patterns(rel: Relation) -> DataFrame:
    """(null_mask array<long>, n): bit i % 62 of word i // 62 is set where attribute i is NULL."""
    words = []
    for at in range(0, rel.m, WORD):
        bits = [F.when(F.col(f"`{c}`").isNull(), F.lit(1 << k)).otherwise(F.lit(0)).cast("long") for k, c in enumerate(rel.columns[at : at + WORD])]
        words.append(reduce(lambda a, b: a.bitwiseOR(b), bits))
    return rel.df.groupBy(F.array(*words).alias("null_mask")).agg(F.count("*").alias("n"))
