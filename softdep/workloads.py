"""The experiments, on the given tables: python -m softdep.workloads SF_DIR [NAME...]."""

from __future__ import annotations

import sys
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softdep import fixtures
from softdep.plans.report import described
from softdep.plans.search import Found, Options, counted_all, counted_parts, search, threshold_discovery
from softdep.relation import Relation
from softdep.sources.tables import load, relation, sign_bits

#: Depth for each relation.
DEPTH = {"lineitem": 3, "orders": 5, "customer": 4, "part": 5, "events": 5, "doc": 5, "dirty": 5, "conv": 5, "page": 5, "bits": 3, "wide": 2}
ABLATION = {"orders": 5, "dirty": 5, "events": 5, "bits": 2}
SWEEP = {"events": 6, "doc": 6, "dirty": 6, "lineitem": 3}
ROW = "name string, variant string, k int, max_lhs int, n long, m int, ecn long, pruning_ratio double, exact long, tau double, seconds double, n_results int"


def _row(name: str, f: Found, variant: str | None = None) -> tuple:
    r = f.report
    return (name, variant or r.variant, r.k, r.max_lhs, r.n, r.m, r.ecn, r.pruning_ratio, r.exact_count, float(r.tau_by_level[-1]) if r.levels else -1.0, r.seconds, len(f.entries))


def _frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, ROW)


# With shared, the searches of a relation evaluate candidates from counts taken once: all columns but seconds are the same.
def overall(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(DEPTH), k: int = 20, shared: bool = False) -> DataFrame:
    """Exhaustive against pruned search on every relation."""
    rows = []
    for n in names:
        rel = relation(spark, sf_dir, n)
        ledger = counted_all(rel, DEPTH[n]) if shared else None
        rows += [_row(n, search(rel, Options(k, DEPTH[n], v, keep_scored=False, ledger=ledger))) for v in ("V0", "V4")]
        rel.release()
    return _frame(spark, rows)


def depth(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(SWEEP), k: int = 20, shared: bool = False) -> DataFrame:
    """(name, max_lhs, tau, seconds, overlap): overlap is the share of the list that the next depth keeps, in per cent."""
    rows = []
    for n in names:
        rel = relation(spark, sf_dir, n)
        ledger = counted_all(rel, SWEEP[n]) if shared else None
        found = [search(rel, Options(k, d, keep_scored=False, ledger=ledger)) for d in range(1, min(SWEEP[n], rel.m - 1) + 1)]
        lists = [{(x, a) for _, x, a, _ in f.entries} for f in found]
        for d, f in enumerate(found):
            rows.append((n, d + 1, float(f.report.tau_by_level[-1]), f.report.seconds, 100.0 * len(lists[d] & lists[d + 1]) / k if d + 1 < len(found) else None))
        rel.release()
    return spark.createDataFrame(rows, "name string, max_lhs int, tau double, seconds double, overlap double")


def scale_rows(spark: SparkSession, sf_dir: str, max_lhs: int = 2, k: int = 20, shared: bool = False) -> DataFrame:
    """Fractions of lineitem by a hash of its keys, all columns."""
    li = load(spark, sf_dir, "lineitem").withColumn("bucket", (F.col("l_orderkey") * 31 + F.col("l_linenumber")) % 10)
    shares = (1, 2, 4, 6, 8, 10)
    rels = [Relation.of(li.where(F.col("bucket") < t).drop("bucket")) for t in shares]
    first = F.coalesce(*(F.when(F.col("bucket") < t, i) for i, t in enumerate(shares)))
    ledgers = counted_parts(li, first, rels, max_lhs) if shared else [None] * len(shares)
    rows = []
    for t, rel, ledger in zip(shares, rels, ledgers, strict=True):
        rows += [_row(f"lineitem {10 * t} %", search(rel, Options(k, max_lhs, v, keep_scored=False, ledger=ledger))) for v in ("V0", "V4")]
        rel.release()
    return _frame(spark, rows)


def scale_columns(spark: SparkSession, sf_dir: str, bits: tuple[int, ...] = (8, 12, 16, 20, 32, 64), max_lhs: int = 2, k: int = 20) -> DataFrame:
    """More and more sign bits of the embeddings; no dependency is exact and nothing is pruned."""
    e = load(spark, sf_dir, "embeddings")
    return _frame(spark, [_row(f"bits {b}", search(rel, Options(k, max_lhs, v, keep_scored=False))) for b in bits for rel in [Relation.of(sign_bits(e, b))] for v in ("V0", "V4")])


def scale_columns_wide(spark: SparkSession, sf_dir: str, prefixes: tuple[int, ...] = (4, 8, 11, 14), max_lhs: int = 2, k: int = 20, shared: bool = False) -> DataFrame:
    """The first columns of the joined tables: many are exact dependencies of others."""
    df = relation(spark, sf_dir, "wide").df
    ledger = None
    if shared:
        rel = Relation.of(df.select(*df.columns[: max(prefixes)]))
        ledger = counted_all(rel, max_lhs)
        rel.release()
    rows = []
    for m in prefixes:
        rel = Relation.of(df.select(*df.columns[:m]))
        rows += [_row(f"wide {m}", search(rel, Options(k, max_lhs, v, keep_scored=False, ledger=ledger))) for v in ("V0", "V4")]
        rel.release()
    return _frame(spark, rows)


def scale_k(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("dirty", "doc"), max_lhs: int = 3) -> DataFrame:
    return _frame(spark, [_row(n, search(rel, Options(k, max_lhs, "V4"))) for n in names for rel in [relation(spark, sf_dir, n)] for k in (5, 10, 20, 50, 100)])


def ablation(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(ABLATION), k: int = 20) -> DataFrame:
    """V0 to V4 with one kernel, which counts each candidate anew before left sides are shared. All lists must be equal."""
    rows = []
    for n in names:
        rel = relation(spark, sf_dir, n)
        rel.codes.count()
        base = None
        for v in ("V0", "V1", "V2", "V3", "V4"):
            f = search(rel, Options(k, ABLATION[n], v, keep_scored=False))
            key = [(r, x, a, round(s, 9)) for r, x, a, s in f.entries]
            base = base or key
            if key != base:
                raise AssertionError(f"{n}: {v} differs from V0")
            rows.append(_row(n, f))
        rel.release()
    return _frame(spark, rows)


def null_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bound with NULLs: heuristic, sound and off, on natural NULLs, injected ones and the counterexample."""
    rows = []
    for name, rel, k, d in (("doc", relation(spark, sf_dir, "doc"), 20, 3), ("dirty", relation(spark, sf_dir, "dirty"), 20, 3), ("nullbreak", fixtures.nullbreak(spark), 1, 2)):
        rows += [_row(name, search(rel, Options(k, d, bound_mode=m)), m) for m in ("off", "heuristic", "sound")]
    return _frame(spark, rows)


def paradigms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(paradigm, n_results, best) of thresholds, a fixed right side and the global list."""
    rel = relation(spark, sf_dir, "dirty")
    rows = []
    for t in (0.5, 0.8, 0.9, 0.95):
        n, best = threshold_discovery(rel, t, 3).agg(F.count("*"), F.max("score")).first()
        rows.append((f"threshold {t}", n, best))
    for name, f in (("fixed market", search(rel, Options(10, 3, rhs=("market",)))), ("global", search(rel, Options(20, 3)))):
        rows.append((name, len(f.entries), max((s for *_, s in f.entries), default=None)))
    return spark.createDataFrame(rows, "paradigm string, n_results long, best double")


def case_study(spark: SparkSession, sf_dir: str, name: str = "dirty", max_lhs: int = 3, k: int = 20) -> DataFrame:
    """The list with how many tuples violate each entry, and the right sides met so far."""
    return described(search(relation(spark, sf_dir, name), Options(k, max_lhs)))


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (overall, depth, scale_rows, scale_columns, scale_columns_wide, scale_k, ablation, null_bound, paradigms, case_study)}


def main(arguments: list[str]) -> None:
    spark = SparkSession.builder.getOrCreate()
    for name in arguments[1:] or WORKLOADS:
        print(name)
        WORKLOADS[name](spark, arguments[0]).show(200, False)


if __name__ == "__main__":
    main(sys.argv[1:])
