"""What a search cost, and comparisons between searches."""

from __future__ import annotations

import json
import uuid
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame, SparkSession

from softdep.plans.lattice import candidate_count


@dataclass
class LevelReport:
    level: int
    ecn: int = 0
    derived: int = 0
    exact: int = 0
    skipped: int = 0
    bound_pruned: int = 0
    tau: float = -1.0
    seconds: float = 0.0
    jobs: int = 0
    tasks: int = 0
    shuffle_bytes: int = 0
    joint_sets: int = 0
    driver_rows: int = 0


class Watch:
    """Counts the jobs, tasks and bytes written for exchanges that Spark runs inside a with block, into a level's report."""

    def __init__(self, spark: SparkSession, into: LevelReport):
        self.context, self.into = spark.sparkContext, into

    def __enter__(self) -> Watch:
        self.group = f"softdep-{uuid.uuid4().hex}"
        self.before = {k: self.context.getLocalProperty(k) for k in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel")}
        self.context.setJobGroup(self.group, "counts of a level")
        return self

    def __exit__(self, *_: object) -> None:
        for k, v in self.before.items():
            self.context.setLocalProperty(k, v)
        core = self.context._jsc.sc()
        core.listenerBus().waitUntilEmpty()
        tracker, store, seen = self.context.statusTracker(), core.statusStore(), set()
        jobs = tracker.getJobIdsForGroup(self.group)
        self.into.jobs += len(jobs)
        for j in jobs:
            info = tracker.getJobInfo(j)
            seen |= set(info.stageIds if info else ())
        for k in seen:
            try:
                stage = store.lastStageAttempt(k)
            except Exception:  # noqa: BLE001, S112 -- a stage that never ran, or that the store has let go
                continue
            self.into.tasks += stage.numCompleteTasks()
            self.into.shuffle_bytes += stage.shuffleWriteBytes()


@dataclass
class RunReport:
    variant: str
    k: int
    max_lhs: int
    m: int
    n: int
    levels: list[LevelReport] = field(default_factory=list)
    complete: bool = True

    def total(self, what: str) -> float:
        return sum(getattr(x, what) for x in self.levels)

    @property
    def ecn(self) -> int:
        return int(self.total("ecn"))

    @property
    def seconds(self) -> float:
        return self.total("seconds")

    @property
    def exact_count(self) -> int:
        return int(self.total("exact"))

    @property
    def pruning_ratio(self) -> float:
        """Share of the candidates of an exhaustive search that were not evaluated."""
        return 1 - self.ecn / max(1, candidate_count(self.m, self.max_lhs))

    @property
    def tau_by_level(self) -> list[float]:
        return [x.tau for x in self.levels]

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(self.variant, self.k, self.max_lhs, x.level, x.ecn, x.derived, x.exact, x.bound_pruned, float(x.tau), self.pruning_ratio, x.seconds, x.jobs, x.tasks, x.shuffle_bytes, x.joint_sets, x.driver_rows) for x in self.levels]
        return spark.createDataFrame(rows, "variant string, k int, max_lhs int, level int, ecn long, derived long, exact long, bound_pruned long, tau double, pruning_ratio double, seconds double, jobs int, tasks int, shuffle_bytes long, joint_sets int, driver_rows int")

    def to_json(self) -> str:
        return json.dumps(asdict(self) | {"ecn": self.ecn, "pruning_ratio": self.pruning_ratio, "seconds": self.seconds})


def speedup(base: RunReport, other: RunReport) -> list[float]:
    """Of the whole run, then of each level."""
    ratio = lambda a, b: a / b if b else float("inf")
    return [ratio(base.seconds, other.seconds), *(ratio(a.seconds, b.seconds) for a, b in zip(base.levels, other.levels, strict=False))]


def explain_pruning(report: RunReport) -> str:
    return "\n".join(f"level {x.level}: {x.ecn} evaluated, {x.exact} exact, {x.bound_pruned} pruned by the bound, threshold {x.tau:.6f}" for x in report.levels)


def overlap(a: DataFrame, b: DataFrame, k: int) -> float:
    """Per cent of k that two result lists share."""
    return 100 * a.select("lhs", "rhs").intersect(b.select("lhs", "rhs")).count() / k


def same_result(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def cost_model(m: int, n: int, max_lhs: int, variant: str = "V0", evaluated: dict[int, tuple[int, int]] | None = None) -> dict[str, int]:
    """Counts of row visits, left-key evaluations, heap offers and mask words; evaluated gives (left sides, candidates) of
    each level where pruning left fewer than all."""
    from math import comb

    rows = keys = heap = words = 0
    for size in range(1, min(max_lhs, m - 1) + 1):
        lefts, cands = (evaluated or {}).get(size, (comb(m, size), comb(m, size) * (m - size)))
        reuse = variant in ("V2", "V3", "V4")
        rows += cands * n
        keys += (lefts if reuse else cands) * n * size
        heap += cands
        words += lefts * -(-m // 64) if variant != "V0" else 0
    return {"row_scans": rows, "lhs_key_evaluations": keys, "heap_operations": heap, "mask_words": words}


def described(found) -> DataFrame:
    """(rank, lhs, rhs, mu_plus, n_violations, distinct_rhs, rhs_per_rank) of a search's list: the tuples that differ from
    their group's majority, the right sides up to the rank, and their share of the rank."""
    c, seen, rows = found.rel.columns, set(), []
    for r, x, a, s in found.entries:
        seen.add(a)
        stats = found.scored[(x, a)]
        rows.append((r, ",".join(c[i] for i in x), c[a], s, round(stats["g3_error"] * stats["n"]), len(seen), len(seen) / r))
    return found.rel.df.sparkSession.createDataFrame(rows, "rank int, lhs string, rhs string, mu_plus double, n_violations long, distinct_rhs int, rhs_per_rank double")
