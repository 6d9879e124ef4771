"""Searches for the k best non-exact dependencies over all left and right sides.

A level's candidates are counted by Spark in batches; the driver then replays them in lexicographic order, so that the
threshold, and with it the pruning of the next level, moves as in a sequential search. Only a row of counts for each
candidate reaches the driver. Levels of more than lattice_rows left sides are tables instead: their candidates are counted
batch by batch into a written table, pruned there with the level's last threshold, and joined to the next level.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import islice

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softdep.operators import nested, score, theory
from softdep.operators.blocks import BLOCK_ROWS
from softdep.plans.lattice import Level, bits, enumerate_candidates, full_level, held, level_frame, next_level, next_level_df, unset
from softdep.plans.report import LevelReport, RunReport, Watch
from softdep.plans.topk import BoundedTopK
from softdep.relation import Relation
from softdep.shared import shared_dir

#: Counts (score.COUNTS without cid) by the names of the left side's columns and the right side; None without a tuple.
Ledger = dict[tuple[tuple[str, ...], str], tuple | None]

COMPONENTS = {
    "V0": frozenset(),
    "V1": frozenset({"prefix"}),
    "V2": frozenset({"prefix", "reuse"}),
    "V3": frozenset({"prefix", "reuse", "exact"}),
    "V4": frozenset({"prefix", "reuse", "exact", "bound"}),
}


@dataclass(frozen=True)
class Options:
    """k and max_lhs as given; the rest refines the variant.

    bound_mode: strict (only without NULLs), heuristic, sound, off, or auto (strict without NULLs, sound with).
    tau_policy: replay, or level_end, which tests once more with the level's last threshold.
    propagation: parents, or all_subsets. kernel: as in score.counts; blocks shares a left side's groups between its
    candidates only in variants with the component reuse.
    rhs, lhs_columns: names that the sides are restricted to. min_redundancy: least n - d of a candidate, 0 for none.
    min_rows: least number of tuples. theta: prune below this score instead of a list's threshold (threshold discovery).
    inherit: copy the scores of X + B from X where X -> B is exact and B has no NULL.
    time_limit_s: stop after the batch that exceeds it; the report is then marked incomplete. batch: candidates to a batch.
    keep_scored: keep every level's statistics in the result, not only the last one's.
    lattice_rows: left sides of a level that the driver holds at most; larger levels are tables, 0 for all.
    ledger: counts as counted_all gives them, for searches whose times are not compared; candidates in it are evaluated
    from them, not counted again, and others are added to it. Levels that are tables do not use it.
    """

    k: int = 20
    max_lhs: int = 5
    variant: str = "V4"
    components: frozenset[str] | None = None
    bound_mode: str = "auto"
    tau_policy: str = "replay"
    propagation: str = "parents"
    kernel: str = "blocks"
    rhs: tuple[str, ...] | None = None
    lhs_columns: tuple[str, ...] | None = None
    min_redundancy: int = 0
    min_rows: int = 2
    theta: float | None = None
    inherit: bool = False
    time_limit_s: float | None = None
    batch: int = 20_000
    keep_scored: bool = True
    lattice_rows: int = 500_000
    ledger: Ledger | None = None

    @property
    def parts(self) -> frozenset[str]:
        return COMPONENTS[self.variant] if self.components is None else self.components


@dataclass
class Found:
    """entries: (rank, lhs, rhs, mu_plus); scored: the evaluated candidates' statistics, without those of levels that were
    tables; report: costs."""

    rel: Relation
    entries: list[tuple[int, tuple[int, ...], int, float]]
    scored: dict[tuple[tuple[int, ...], int], dict]
    report: RunReport

    def frame(self) -> DataFrame:
        """S-TOPK: (rank, lhs array, rhs, mu_plus)."""
        c = self.rel.columns
        rows = [(r, [c[i] for i in x], c[a], s) for r, x, a, s in self.entries]
        return self.rel.df.sparkSession.createDataFrame(rows, "rank int, lhs array<string>, rhs string, mu_plus double")


def _mask(rel: Relation, names: tuple[str, ...] | None) -> int:
    return sum(1 << rel.position(c) for c in names) if names is not None else (1 << rel.m) - 1


def search(rel: Relation, options: Options = Options()) -> Found:  # noqa: B008
    """The best dependencies of rel; see Options."""
    o, parts = options, options.parts
    profile = rel.profile
    nullable = sum(1 << i for i, n in enumerate(profile.nulls) if n)
    mode = o.bound_mode if o.bound_mode != "auto" else ("sound" if nullable else "strict")
    if mode == "strict" and nullable:
        raise ValueError("the strict bound needs a relation without NULLs; use sound, heuristic or off")
    best = BoundedTopK(o.k)
    report = RunReport(o.variant, o.k, min(o.max_lhs, rel.m - 1), rel.m, profile.rows)
    run = _Run(rel, o, mode, best, report, time.monotonic())
    scored: dict[tuple[tuple[int, ...], int], dict] = {}
    lhs, rhs = _mask(rel, o.lhs_columns), _mask(rel, o.rhs)
    level: Level = full_level(rel.m, 1, lhs, rhs)
    for size in range(1, report.max_lhs + 1):
        if "prefix" in parts and (not o.lattice_rows or _pairs(level) > o.lattice_rows) and size > 1:
            run.tables(level_frame(rel.df.sparkSession, level, rel.m), size)
            break
        at = LevelReport(size)
        t = time.monotonic()
        with Watch(rel.df.sparkSession, at):
            if size > 1:
                level = next_level(level, o.propagation == "all_subsets") if "prefix" in parts else full_level(rel.m, size, lhs, rhs)
            level = {x: s for x, s in level.items() if s}
            if not level:
                break
            cands = [(x, a) for x in sorted(level) for a in bits(level[x])]
            derived = _inherited(cands, scored, nullable) if o.inherit else {}
            todo = [c for c in cands if c not in derived]
            got = dict(derived)
            for some in run.batches(iter(todo)):
                got |= run.collected(some)
            at.ecn, at.derived, at.driver_rows = len(got) - len(derived), len(derived), len(got) - len(derived)
            at.joint_sets = len({tuple(sorted((*x, a))) for x, a in todo})
            cands = [c for c in cands if c in got]
            scored = (scored if o.keep_scored else {}) | got
        run.replay(at, level, cands, got)
        at.tau, at.seconds = best.threshold, time.monotonic() - t
        report.levels.append(at)
        if run.late and (size < report.max_lhs or at.ecn < len(todo)):
            report.complete = False
            break
    return Found(rel, best.result(), scored, report)


def _key(rel: Relation, c: tuple[tuple[int, ...], int]) -> tuple[tuple[str, ...], str]:
    return tuple(rel.columns[i] for i in c[0]), rel.columns[c[1]]


def entered(rel: Relation, cands: list, ledger: Ledger) -> None:
    """Counts those of the candidates that the ledger lacks."""
    todo = [c for c in cands if _key(rel, c) not in ledger]
    if not todo:
        return
    table = score.counts(rel, list(enumerate(todo))).toArrow()
    ledger |= dict.fromkeys((_key(rel, c) for c in todo), None)
    names = [x.split()[0] for x in score.COUNTS.split(", ")]
    for cid, *values in zip(*(table[c].to_pylist() for c in names), strict=True):
        ledger[_key(rel, todo[cid])] = tuple(values)


def counted_all(rel: Relation, max_lhs: int, batch: int = 20_000) -> Ledger:
    """The counts of all candidates of all levels, so that a pivot's exchange and a prefix's groups serve every level. They hold
    for any relation of the same rows that has the candidates' columns."""
    ledger: Ledger = {}
    cands = enumerate_candidates(rel.m, max_lhs)
    while some := list(islice(cands, batch)):
        entered(rel, some, ledger)
    return ledger


def counted_parts(df: DataFrame, layer: Column, parts: list[Relation], max_lhs: int, batch: int = 20_000, block_rows: int = BLOCK_ROWS) -> list[Ledger]:
    """The counts of all candidates of all levels on relations that each hold the ones before. layer is the number of the first
    that holds a row of df, null for none. The relations get their profiles."""
    columns = parts[-1].columns
    name = next(n for i in range(len(columns) + 1) if (n := f"layer{i}") not in columns)
    rel = Relation.of(df.select(*columns, layer.alias(name)).where(F.col(name).isNotNull()))
    every = nested.Nested(rel, len(parts), block_rows)
    ledgers: list[Ledger] = [{} for _ in parts]
    cands = enumerate_candidates(every.m, max_lhs)
    while some := list(islice(cands, batch)):
        for ledger, counts in zip(ledgers, every.counts(list(enumerate(some))), strict=True):
            ledger |= {_key(rel, c): counts.get(cid) for cid, c in enumerate(some)}
    rel.release()
    for part, profile in zip(parts, every.profiles, strict=True):
        part._profile = profile
    return ledgers


def _pairs(level: Level) -> int:
    """How many left sides the next level may have."""
    families: dict[tuple[int, ...], int] = {}
    for x in level:
        families[x[:-1]] = families.get(x[:-1], 0) + 1
    return sum(n * (n - 1) // 2 for n in families.values())


@dataclass
class _Run:
    """What the levels of a search share."""

    rel: Relation
    o: Options
    mode: str
    best: BoundedTopK
    report: RunReport
    began: float

    @property
    def late(self) -> bool:
        return self.o.time_limit_s is not None and time.monotonic() - self.began > self.o.time_limit_s

    def batches(self, cands: Iterator) -> Iterator[list]:
        """At least one batch of a level is counted, then as many as the time allows."""
        while some := list(islice(cands, self.o.batch)):
            yield some
            if self.late:
                return

    @property
    def kernel(self) -> str:
        alone = {"blocks": "blocks_each", "lhs_shared": "candidate"}
        return self.o.kernel if "reuse" in self.o.parts else alone.get(self.o.kernel, self.o.kernel)

    def statistics(self, cands: list) -> DataFrame:
        return score.statistics(self.rel, cands, self.kernel, max(self.rel.profile.complete, 1))

    def collected(self, cands: list) -> dict:
        """The statistics of a batch by candidate; candidates without a tuple have n of 0."""
        if self.o.ledger is None:
            counted = score.counts(self.rel, list(enumerate(cands)), self.kernel)
        else:
            entered(self.rel, cands, self.o.ledger)
            known = [self.o.ledger[_key(self.rel, c)] for c in cands]
            counted = self.rel.df.sparkSession.createDataFrame([(i, *r) for i, r in enumerate(known) if r is not None], score.COUNTS)
        table = score.measured(counted, max(self.rel.profile.complete, 1)).toArrow().to_pydict()
        out = {c: {"n": 0, "lhs": list(c[0]), "rhs": c[1]} for c in cands}
        names = [c for c in table if c != "cid"]
        for cid, *values in zip(table["cid"], *(table[c] for c in names), strict=True):
            out[cands[cid]] |= zip(names, values, strict=True)
        return out

    def replay(self, at: LevelReport, level: Level, cands: list, got: dict) -> None:
        """Offers in order, and what each prunes of its left side's further right sides."""
        o, parts = self.o, self.o.parts
        kept: list[tuple[tuple[int, ...], int, dict]] = []
        for x, a in cands:
            r = got[(x, a)]
            if r["n"] < max(2, o.min_rows) or (o.min_redundancy and r["n"] - r["d_lhs"] < o.min_redundancy):
                at.skipped += 1
                level[x] &= ~(1 << a)
            elif r["is_exact"]:
                at.exact += 1
                if "exact" in parts:
                    level[x] &= ~(1 << a)
            else:
                self.best.offer(r["rho"], x, a)
                if "bound" in parts and _hopeless(r, self.mode, self.best.threshold, o.theta):
                    level[x] &= ~(1 << a)
                    at.bound_pruned += 1
                else:
                    kept.append((x, a, r))
        if o.tau_policy == "level_end" and "bound" in parts:
            for x, a, r in kept:
                if _hopeless(r, self.mode, self.best.threshold, o.theta):
                    level[x] &= ~(1 << a)
                    at.bound_pruned += 1

    def tables(self, level: DataFrame, size: int) -> None:
        """The levels from size on as tables; level is that of the left sides one smaller. Right sides are pruned with the
        threshold that a level ends with. Only k rows of each batch, and a batch's candidates, are in the driver."""
        o, parts, spark = self.o, self.o.parts, self.rel.df.sparkSession
        base = f"{shared_dir(spark)}/lattice-{uuid.uuid4().hex}"

        def put(df: DataFrame, name: str) -> DataFrame:
            df.write.mode("append").parquet(f"{base}/{name}")
            return spark.read.schema(df.schema).parquet(f"{base}/{name}")

        for size_ in range(size, self.report.max_lhs + 1):
            at = LevelReport(size_)
            t = time.monotonic()
            with Watch(spark, at):
                level = put(next_level_df(level, o.propagation == "all_subsets"), f"level-{size_}")
                cands = level.select("lhs", F.explode(held("s_mask", self.rel.m)).alias("rhs")).sort("lhs", "rhs")
                stats = None
                for some in self.batches((tuple(r["lhs"]), r["rhs"]) for r in cands.toLocalIterator()):
                    batch = self.statistics(some).withColumn("few", (F.col("n") < max(2, o.min_rows)) | F.lit(bool(o.min_redundancy)) & (F.col("n") - F.col("d_lhs") < o.min_redundancy))
                    stats = put(batch.drop("cid"), f"stats-{size_}")
                    at.ecn += len(some)
            if stats is None:
                break
            spark.catalog.refreshByPath(f"{base}/stats-{size_}")
            stats = spark.read.schema(stats.schema).parquet(f"{base}/stats-{size_}")
            open_ = stats.where("not few and not is_exact")
            at.skipped, at.exact = stats.agg(F.count_if("few"), F.count_if(F.expr("not few and is_exact"))).first()
            for r in open_.select("rho", "lhs", "rhs").orderBy(*theory.order()).limit(o.k).collect():
                self.best.offer(r["rho"], tuple(r["lhs"]), r["rhs"])
                at.driver_rows += 1
            gone = F.col("few")
            if "exact" in parts:
                gone = gone | F.col("is_exact")
            if "bound" in parts and self.mode != "off":
                bound = F.col("sound_bound" if self.mode == "sound" else "bound")
                tau = self.best.threshold
                weak = bound < o.theta if o.theta is not None else F.lit(tau >= 0) & (F.greatest(bound, F.lit(0.0)) <= tau)
                weak = F.coalesce(weak, F.lit(False)) & ~F.col("few") & ~F.col("is_exact")
                gone = gone | weak
                at.bound_pruned = stats.where(weak).count()
            pruned = stats.where(gone).groupBy("lhs").agg(F.collect_list("rhs").alias("gone"))
            level = level.join(pruned, "lhs", "left").withColumn("s_mask", unset("s_mask", F.coalesce("gone", F.array().cast("array<int>")))).drop("gone")
            level = put(level.where(F.exists("s_mask", lambda w: w != 0)), f"pruned-{size_}")
            at.tau, at.seconds = self.best.threshold, time.monotonic() - t
            self.report.levels.append(at)
            if self.late and size_ < self.report.max_lhs:
                self.report.complete = False
                break


def _hopeless(r: dict, mode: str, tau: float, theta: float | None) -> bool:
    """Whether no non-exact descendant can enter. A bound equal to the threshold loses its ties, being longer."""
    if mode == "off":
        return False
    bound = r["sound_bound"] if mode == "sound" else r["bound"]
    if bound is None:
        return False
    return bound < theta if theta is not None else tau >= 0 and max(bound, 0.0) <= tau


def _inherited(cands: list, scored: dict, nullable: int) -> dict:
    """X + B has the groups of X where X -> B is exact and B is never NULL: its statistics are those of X."""
    out = {}
    for x, a in cands:
        for i, b in enumerate(x):
            rest = x[:i] + x[i + 1 :]
            fd = scored.get((rest, b))
            if rest and fd and fd["is_exact"] and not nullable >> b & 1 and (rest, a) in scored:
                out[(x, a)] = scored[(rest, a)] | {"lhs": list(x)}
                break
    return out


def top_k(rel: Relation, k: int = 20, max_lhs: int = 5, variant: str = "V4", **options: object) -> DataFrame:
    return search(rel, Options(k=k, max_lhs=max_lhs, variant=variant, keep_scored=False, **options)).frame()


def threshold_discovery(rel: Relation, theta: float, max_lhs: int = 5, measure: str = "mu_plus", prune: bool = True, variant: str = "V4", rhs: tuple[str, ...] | None = None) -> DataFrame:
    """(lhs, rhs, score) of all non-exact dependencies of at least theta; the number of rows is not bounded.

    measure is mu_plus, gain, lift or agreement_error (1 - g3); only mu_plus can prune by its bound."""
    if variant == "V4" and not (prune and measure == "mu_plus"):
        variant = "V3"
    found = search(rel, Options(k=1, max_lhs=max_lhs, variant=variant, theta=theta, rhs=rhs, lattice_rows=1 << 62))
    value = {"mu_plus": lambda r: r["mu_plus"], "gain": lambda r: r["gain"], "lift": lambda r: r["lift"], "agreement_error": lambda r: 1 - r["g3_error"]}[measure]
    c = rel.columns
    rows = [([c[i] for i in x], c[a], value(r)) for (x, a), r in found.scored.items() if r["n"] > 1 and not r["is_exact"] and value(r) >= theta]
    return rel.df.sparkSession.createDataFrame(rows, "lhs array<string>, rhs string, score double")


def exact_dependencies(rel: Relation, max_lhs: int = 2, minimal: bool = True, kernel: str = "blocks") -> DataFrame:
    """(lhs, rhs) of the exact dependencies; minimal ones have no exact dependency on fewer of their columns."""
    found = search(rel, Options(k=1, max_lhs=max_lhs, variant="V0", kernel=kernel))
    exact = {(x, a) for (x, a), r in found.scored.items() if r["n"] > 1 and r["is_exact"]}
    if minimal:
        exact = {(x, a) for x, a in exact if not any((x[:i] + x[i + 1 :], a) in exact for i in range(len(x)) if len(x) > 1)}
    c = rel.columns
    return rel.df.sparkSession.createDataFrame([([c[i] for i in x], c[a]) for x, a in sorted(exact)], "lhs array<string>, rhs string")
