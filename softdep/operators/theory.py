"""What a result set can and cannot have: minimality, the true k best, exactly k rows."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: All functions take scores as (lhs array<int>, rhs int, rho double, mu_plus double) of the non-exact dependencies.


def order() -> list[Column]:
    """The engine's total order: rho, at most 1, to 12 digits; size and positions of the left side; the right side."""
    digits = F.when(F.col("rho") > 0, F.floor(F.log10(F.least("rho", F.lit(1.0))))).otherwise(0)
    scale = F.pow(F.lit(10.0), 11 - digits)
    return [F.round(F.least("rho", F.lit(1.0)) * scale, 0) / scale, F.size("lhs"), F.col("lhs"), F.col("rhs")]


def ranked(scores: DataFrame, k: int | None = None) -> DataFrame:
    """scores in the engine's total order, the first k of them; a top-k node, no full sort."""
    out = scores.orderBy(*order())
    return out if k is None else out.limit(k)


def _contained(small: str, large: str):
    """Whether small is a proper subset of large, both arrays."""
    return (F.size(small) < F.size(large)) & (F.size(F.array_except(small, large)) == 0)


def subset_pairs(scores: DataFrame, larger: DataFrame | None = None) -> DataFrame:
    """(rhs, small, large, low, high) of dependencies on the same right side, one left side inside the other; the large ones
    from larger if given. The join is on the right side and the smaller side's first column, so that only pairs sharing a
    column meet."""
    a = scores.select("rhs", F.col("lhs").alias("small"), F.col("mu_plus").alias("low"), F.col("lhs")[0].alias("k"))
    b = (scores if larger is None else larger).select("rhs", F.col("lhs").alias("large"), F.col("mu_plus").alias("high"), F.explode("lhs").alias("k"))
    return a.join(b, ["rhs", "k"]).where(_contained("small", "large")).select("rhs", "small", "large", "low", "high")


def growth_chains(scores: DataFrame, epsilon: float = 1e-9) -> DataFrame:
    """Pairs whose score rises as the left side grows."""
    return subset_pairs(scores).where(F.col("high") > F.col("low") + epsilon)


def minimal_only(scores: DataFrame, mode: str = "scored", theta: float = 0.0) -> DataFrame:
    """Dependencies without a smaller one in the set: 'literal' counts every non-exact one, 'scored' those of theta or more."""
    base = scores if mode == "literal" else scores.where(F.col("mu_plus") >= theta)
    worse = subset_pairs(base).select(F.col("large").alias("lhs"), "rhs").distinct()
    return base.join(worse, ["lhs", "rhs"], "left_anti")


@dataclass(frozen=True)
class Properties:
    minimal: bool
    top_k: bool
    exactly_k: bool


def _not_minimal(part: DataFrame, scores: DataFrame) -> DataFrame:
    """(lhs, rhs) of the members of part whose left side contains that of any non-exact dependency on the same right side."""
    return subset_pairs(scores, part).select(F.col("large").alias("lhs"), "rhs").distinct()


def check_properties(result: DataFrame, scores: DataFrame, k: int, epsilon: float = 1e-9) -> Properties:
    """minimal: no member's left side contains that of another dependency in scores on the same right side, in the result or
    not. top_k: nothing outside scores higher than the lowest member. exactly_k: min(k, all) members."""
    n, low = result.agg(F.count("*"), F.min("mu_plus")).first()
    outside = scores.join(result.select("lhs", "rhs"), ["lhs", "rhs"], "left_anti").agg(F.max("mu_plus")).first()[0]
    return Properties(
        minimal=_not_minimal(result, scores).isEmpty(),
        top_k=outside is None or low is None or outside <= low + epsilon,
        exactly_k=n == min(k, scores.count()),
    )


def enforce(scores: DataFrame, k: int, keep: str) -> DataFrame:
    """A result with two of the three properties. P2P3: the k best. P1P3: the k best of the minimal ones. P1P2: of the k best
    those before the first that is not minimal, which may be none: to leave one out and go on would not be the top."""
    if keep == "P2P3":
        return ranked(scores, k)
    if keep == "P1P3":
        return ranked(scores.join(_not_minimal(scores, scores), ["lhs", "rhs"], "left_anti"), k)
    if keep == "P1P2":
        top = ranked(scores, k)
        place = top.withColumn("place", F.row_number().over(Window.orderBy(*order())))  # k rows
        first = place.join(_not_minimal(top, scores), ["lhs", "rhs"], "left_semi").agg(F.coalesce(F.min("place"), F.lit(k + 1)).alias("first"))
        return place.join(F.broadcast(first), F.col("place") < F.col("first")).select(*scores.columns)
    raise ValueError(keep)


def incompatibility_witness(scores: DataFrame) -> DataFrame:
    """(rhs, small, large, low, high, other_lhs, other_rhs, other): a minimal dependency, one on more columns that scores
    higher (the best such, then its best minimal subset), and the best minimal one of a lower positive score on columns apart.

    Among these three and for k = 2 the best two are large and small, of which large is not minimal; the minimal two leave
    out large. Without such a third, its columns are null; without a rising pair there is no row. Scores are compared to 12
    decimals: what columns that determine each other score alike differs in the last digits by the order of the rows, and
    such ties go to size and positions."""
    least = scores.join(_not_minimal(scores, scores), ["lhs", "rhs"], "left_anti")
    rising = subset_pairs(least, scores).where(F.col("high") > F.col("low") + 1e-9)
    tied = lambda s: F.round(s, 12)
    by = lambda c, s: [F.desc(tied(s)), F.size(c), F.col(c), F.col("rhs")]
    chain = rising.orderBy(*by("large", "high"), *by("small", "low")).limit(1)
    apart = least.select(F.col("lhs").alias("other_lhs"), F.col("rhs").alias("other_rhs"), F.col("mu_plus").alias("other"))
    used = F.concat("large", F.array("rhs"))
    free = (F.col("other") > 0) & (tied("other") < tied("low")) & ~F.arrays_overlap(F.concat("other_lhs", F.array("other_rhs")), used)
    both = F.broadcast(chain).join(apart, free, "right").where("rhs is not null")  # chain is a row
    third = both.orderBy(F.desc(tied("other")), F.size("other_lhs"), "other_lhs", "other_rhs").limit(1).select("other_lhs", "other_rhs", "other", F.lit(1).alias("one"))
    return chain.withColumn("one", F.lit(1)).join(third, "one", "left").drop("one")
