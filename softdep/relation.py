"""A relation: a DataFrame whose column order is semantic, with its codes and NULL pattern."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


class Profile(NamedTuple):
    """Tuples, those without any NULL, NULLs by attribute, and about how many tuples differ."""

    rows: int
    complete: int
    nulls: tuple[int, ...]
    distinct: int


class Marginal(NamedTuple):
    """Of an attribute over its non-NULL tuples: values, chance disagreement, tuples of the most frequent value."""

    values: int
    disagreement: float
    largest: int


@dataclass(eq=False)
class Relation:
    """df restricted to columns, in order. Positions in columns identify attributes everywhere else.

    wide keys strings and nested values by 128 hash bits instead of 64; integral and floating-point values are keyed exactly.
    null_policy 'ignore' leaves tuples with a NULL among a candidate's columns out of that candidate; 'as_value' takes NULL
    as one more value. collapse keeps equal tuples as one with a weight; None does so where a sketch says that at most half
    of them differ.
    """

    df: DataFrame
    columns: list[str]
    name: str = "r"
    wide: bool = True
    null_policy: str = "ignore"
    collapse: bool | None = None
    _codes: DataFrame | None = field(default=None, repr=False)
    _marginals: dict[int, Marginal] | None = field(default=None, repr=False)
    _profile: Profile | None = field(default=None, repr=False)
    _size: int | None = field(default=None, repr=False)

    @staticmethod
    def of(df: DataFrame, include: list[str] | None = None, exclude: tuple[str, ...] = (), name: str = "r", **options: object) -> Relation:
        columns = [c for c in (include or df.columns) if c not in exclude]
        return Relation(df.select(*columns), columns, name, **options)

    @property
    def m(self) -> int:
        return len(self.columns)

    def position(self, column: str) -> int:
        return self.columns.index(column)

    def physical(self, i: int) -> list[str]:
        """Names of the code columns of attribute i."""
        return [f"c{i}", f"c{i}w"] if self.wide and not _is_exact(self.df.schema[self.columns[i]].dataType) else [f"c{i}"]

    @property
    def coded(self) -> DataFrame:
        """The code columns of each tuple."""
        out = []
        for i, name in enumerate(self.columns):
            kind = self.df.schema[name].dataType
            for k, alias in enumerate(self.physical(i)):
                code = _code(F.col(f"`{name}`"), kind, k)
                out.append((F.coalesce(code, F.lit(-(2**62) - k)) if self.null_policy == "as_value" else code).alias(alias))
        return self.df.select(*out)

    @property
    def profile(self) -> Profile:
        """One pass over the tuples; a number for each attribute reaches the driver, whatever patterns the NULLs form."""
        if self._profile is None:
            coded = self.coded
            firsts = [self.physical(i)[0] for i in range(self.m)]
            whole = reduce(lambda a, b: a + b, [F.col(c).isNull().cast("int") for c in firsts]) == 0
            r = coded.agg(F.count(F.lit(1)), F.count_if(whole), F.approx_count_distinct(F.xxhash64(*coded.columns)), *(F.count(c) for c in firsts)).first()
            self._profile = Profile(r[0], r[1], tuple(r[0] - x for x in r[3:]), r[2])
        return self._profile

    def profiles(self, i: int) -> dict[int, Profile]:
        """Of the tuples with each value of an exactly keyed attribute, by one pass. How many differ is told from those whose hash
        ends in six zeros, which equal tuples do together; where there are none, all count as different."""
        coded = self.coded
        firsts = [self.physical(j)[0] for j in range(self.m)]
        whole = reduce(lambda a, b: a + b, [F.col(c).isNull().cast("int") for c in firsts]) == 0
        h = F.xxhash64(*coded.columns)
        own = coded.groupBy(F.col(firsts[i]).alias("x"), F.when(h.bitwiseAND(63) == 0, h).alias("h")).agg(F.count(F.lit(1)).alias("n"), F.count_if(whole).alias("u"), *(F.count(c).alias(f"n{j}") for j, c in enumerate(firsts)))
        by = own.groupBy("x").agg(F.sum("n"), F.sum("u"), F.count("h"), F.sum(F.when(F.col("h").isNotNull(), F.col("n"))), *(F.sum(f"n{j}") for j in range(self.m)))
        return {x: Profile(n, u, tuple(n - k for k in each), n * d // of if of else n) for x, n, u, d, of, *each in by.toDF(*(f"x{j}" for j in range(self.m + 5))).collect()}

    @property
    def weighted(self) -> bool:
        """Whether equal tuples are kept once."""
        return 2 * self.profile.distinct <= self.profile.rows if self.collapse is None else self.collapse

    @property
    def codes(self) -> DataFrame:
        """One or two long columns for each attribute, equal for equal values, and a weight w. Persisted on first use."""
        if self._codes is None:
            coded = self.coded
            self._codes = (coded.groupBy(*coded.columns).agg(F.count(F.lit(1)).alias("w")) if self.weighted else coded.withColumn("w", F.lit(1).cast("long"))).persist()
        return self._codes

    @property
    def size(self) -> int:
        """Number of rows of codes."""
        if self._size is None:
            self._size = self.codes.count() if self.weighted else self.profile.rows
        return self._size

    @property
    def null_free(self) -> bool:
        """Whether no tuple is left out of any candidate."""
        return not any(self.profile.nulls)

    @property
    def marginals(self) -> dict[int, Marginal]:
        """Of each attribute with a value, by one aggregation for every 24 attributes."""
        if self._marginals is None:
            self._marginals = {}
            for at in range(0, self.m, 24):
                some = range(at, min(at + 24, self.m))
                names = [p for i in some for p in self.physical(i)]
                gid = {sum(1 << (len(names) - 1 - k) for k, p in enumerate(names) if p not in self.physical(i)): i for i in some}
                grouped = self.codes.groupingSets([[F.col(p) for p in self.physical(i)] for i in some], *names).agg(F.sum("w").alias("s"), F.grouping_id().alias("gid"))
                held = grouped.where(F.coalesce(*(F.col(self.physical(i)[0]) for i in some)).isNotNull())
                sums = held.groupBy("gid").agg(F.count(F.lit(1)).alias("d"), F.sum("s").alias("n"), F.sum(F.col("s").cast("double") * F.col("s")).alias("q"), F.max("s").alias("top"))
                self._marginals |= {gid[r["gid"]]: Marginal(r["d"], 0.0 if r["d"] == 1 else 1 - r["q"] / r["n"] / r["n"], r["top"]) for r in sums.collect()}
        return self._marginals

    def release(self) -> None:
        if self._codes is not None:
            self._codes.unpersist()
        self._codes = self._marginals = self._profile = self._size = None


def _is_exact(kind: T.DataType) -> bool:
    """Whether one long tells values apart: as itself, or as a hash, which is one to one on 64 bits."""
    return isinstance(kind, (T.IntegralType, T.BooleanType, T.DateType, T.TimestampType, T.FloatType, T.DoubleType))


def _code(c: Column, kind: T.DataType, salt: int) -> Column:
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c)
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("long")
    if isinstance(kind, (T.IntegralType, T.BooleanType)):
        return c.cast("long")
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        c = c.cast("double") + F.lit(0.0)  # -0.0 and 0.0 are one value, as in groupBy
    if isinstance(kind, T.MapType):
        c = F.array_sort(F.map_entries(c))
    return F.when(c.isNotNull(), F.xxhash64(F.lit(salt), c))
