"""The level-wise search space: left sides as sorted position tuples, right sides as bit masks."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Level = dict[tuple[int, ...], int]


def candidate_count(m: int, max_lhs: int) -> int:
    """Number of candidates of m attributes with at most max_lhs on the left."""
    return sum(comb(m, k) * (m - k) for k in range(1, min(max_lhs, m - 1) + 1))


def enumerate_candidates(m: int, max_lhs: int) -> Iterator[tuple[tuple[int, ...], int]]:
    """All candidates by level, left side and right side."""
    for k in range(1, min(max_lhs, m - 1) + 1):
        for lhs in combinations(range(m), k):
            yield from ((lhs, a) for a in range(m) if a not in lhs)


def bits(mask: int) -> list[int]:
    return [i for i in range(mask.bit_length()) if mask >> i & 1]


def full_level(m: int, size: int, lhs: int, rhs: int) -> Level:
    """Every left side of that size, without regard to pruning."""
    return {x: rhs & ~sum(1 << i for i in x) for x in combinations(bits(lhs & ((1 << m) - 1)), size)}


def next_level(level: Level, all_subsets: bool = False) -> Level:
    """Left sides one larger, from pairs that share all but their last attribute; a right side survives where both, or all
    subsets if asked, still have it. Left sides without right sides go."""
    families: dict[tuple[int, ...], list[int]] = {}
    for x in sorted(level):
        families.setdefault(x[:-1], []).append(x[-1])
    out: Level = {}
    for prefix, lasts in families.items():
        for a, b in combinations(lasts, 2):
            x = (*prefix, a, b)
            mask = level[(*prefix, a)] & level[(*prefix, b)] & ~(1 << a) & ~(1 << b)
            if all_subsets and mask:
                for i in range(len(prefix)):
                    mask &= level.get(x[:i] + x[i + 1 :], 0)
            if mask:
                out[x] = mask
    return out


def level_frame(spark, level: Level, m: int) -> DataFrame:
    """S-LEVEL: (lhs, prefix, last, s_mask), 62 attributes to a word of the mask."""
    words = -(-m // 62)
    rows = [(list(x), list(x[:-1]), x[-1], [mask >> (62 * w) & ((1 << 62) - 1) for w in range(words)]) for x, mask in sorted(level.items())]
    return spark.createDataFrame(rows, "lhs array<int>, prefix array<int>, last int, s_mask array<long>")


def next_level_df(level: DataFrame, all_subsets: bool = False) -> DataFrame:
    """next_level as an equi-join on the prefix, for levels too large for the driver."""
    a, b = level.alias("a"), level.alias("b")
    both = F.zip_with("a.s_mask", "b.s_mask", lambda x, y: x.bitwiseAND(y))
    joined = a.join(b, (F.col("a.prefix") == F.col("b.prefix")) & (F.col("a.last") < F.col("b.last")))
    out = joined.select(F.concat("a.lhs", F.array("b.last")).alias("lhs"), F.col("a.lhs").alias("prefix"), F.col("b.last").alias("last"), both.alias("both"))
    # The new members leave the mask.
    out = out.select("lhs", "prefix", "last", unset("both", F.col("lhs")).alias("s_mask"))
    if all_subsets:
        one = out.withColumn("i", F.explode(F.sequence(F.lit(1), F.size("lhs"))))
        subset = F.concat(F.slice("lhs", F.lit(1), F.col("i") - 1), F.slice("lhs", F.col("i") + 1, F.size("lhs")))
        parts = one.withColumn("sub", subset).join(level.select(F.col("lhs").alias("sub"), F.col("s_mask").alias("m")), "sub")
        agg = parts.groupBy("lhs", "prefix", "last", "s_mask").agg(F.collect_list("m").alias("ms"), F.count("*").alias("k")).where(F.col("k") == F.size("lhs"))
        out = agg.select("lhs", "prefix", "last", F.aggregate("ms", F.col("s_mask"), lambda acc, m: F.zip_with(acc, m, lambda x, y: x.bitwiseAND(y))).alias("s_mask"))
    return out.where(F.exists("s_mask", lambda x: x != 0))


def unset(mask: str, members: Column) -> Column:
    """mask without the bits of members."""
    zero = F.lit(0).cast("long")
    own = lambda word: F.aggregate(members, zero, lambda acc, i: acc.bitwiseOR(F.when(F.floor(i / 62) == word, F.pow(F.lit(2.0), F.pmod(i, F.lit(62))).cast("long")).otherwise(zero)))
    return F.transform(mask, lambda x, w: x.bitwiseAND(F.bitwise_not(own(w))))


def held(mask: str, m: int) -> Column:
    """The attributes whose bits are set, as an array."""
    return F.filter(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.getbit(F.element_at(mask, F.floor(i / 62).cast("int") + 1), F.pmod(i, F.lit(62))) == 1)
