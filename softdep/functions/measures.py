"""Scores and bounds as column expressions over counts, and as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def rho(n: Column, d_lhs: Column, disagree_lhs: Column, disagree_rhs: Column) -> Column:
    """Disagreement given the left side over disagreement by chance, corrected for the number of left groups.
    0 for exact dependencies, also in the degenerate cases of key left sides and constant right sides."""
    exact = (disagree_lhs <= 0) | (n == d_lhs) | (disagree_rhs <= 0)
    return F.when(exact, F.lit(0.0)).otherwise(disagree_lhs / disagree_rhs * (n - 1) / (n - d_lhs))


def mu_plus(n: Column, d_lhs: Column, disagree_lhs: Column, disagree_rhs: Column) -> Column:
    return F.greatest(F.lit(0.0), 1 - rho(n, d_lhs, disagree_lhs, disagree_rhs))


def optimistic_bound(n: Column, d_lhs: Column, disagree_rhs: Column) -> Column:
    """No non-exact descendant scores higher on a relation without NULLs; null where the denominator is zero."""
    return F.when((n > d_lhs) & (disagree_rhs > 0), 1 - (n - 1) / (n * disagree_rhs * (n - d_lhs)))


def sound_bound(n: Column, d_lhs: Column, disagree_rhs: Column, d_rhs: Column, complete_rows: int) -> Column:
    """As optimistic_bound, and valid with NULLs: descendants keep at least complete_rows tuples; the pairs that disagree on
    the right side can only become fewer, and so can n - d."""
    nu = F.least(n, F.lit(max(2, complete_rows))).cast("double")
    q = F.least(1 - 1 / d_rhs, (n / nu) * (n / nu) * disagree_rhs)
    return F.when((n > d_lhs) & (disagree_rhs > 0) & (q > 0), 1 - (nu - 1) / (nu * q * (n - d_lhs)))


def significant(x: Column, digits: int = 12) -> Column:
    """x rounded to so many significant digits."""
    scale = F.pow(F.lit(10.0), F.lit(digits - 1) - F.floor(F.log10(x)))
    return F.when(x > 0, F.round(x * scale, 0) / scale).otherwise(F.lit(0.0))


#: Bodies of the SQL functions; Catalyst inlines them.
SQL_FUNCTIONS = {
    "mu_plus_of": (
        "n DOUBLE, d DOUBLE, dis_x DOUBLE, dis_a DOUBLE",
        "CASE WHEN dis_x <= 0 OR n = d OR dis_a <= 0 THEN 1.0D ELSE greatest(0.0D, 1 - dis_x / dis_a * (n - 1) / (n - d)) END",
    ),
    "optimistic_bound_of": ("n DOUBLE, d DOUBLE, dis_a DOUBLE", "CASE WHEN n > d AND dis_a > 0 THEN 1 - (n - 1) / (n * dis_a * (n - d)) END"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions mu_plus_of and optimistic_bound_of."""
    for name, (arguments, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS DOUBLE RETURN {body}")
