"""Searches: variants agree, counts match arithmetic, the NULL counterexample, the measured regressions."""

import os
import time

import pytest

from pyspark.sql import functions as F

from softdep import fixtures, workloads
from softdep.functions.sqlfront import sql
from softdep.operators import blocks
from softdep.plans import lattice, report
from softdep.plans.search import Options, counted_all, counted_parts, exact_dependencies, search, threshold_discovery
from softdep.plans.topk import BoundedTopK
from softdep.relation import Relation
from softdep.sources.sinks import write_report, write_topk
from softdep.sources.tables import load, relation

#: relation, depth, ECN of V0, V3, V4, and of V4 with the late test and all-subset propagation, exact dependencies of V0.
MEASURED = [
    ("orders", 5, 186, 83, 78, 68, 116),
    ("customer", 4, 75, 29, 29, 29, 60),
    ("part", 5, 186, 110, 110, 104, 95),
    ("events", 5, 186, 177, 175, 168, 20),
]


def test_candidate_counts():
    assert lattice.candidate_count(9, 5) == 1962 and lattice.candidate_count(109, 5) == 12757176117
    assert lattice.candidate_count(5, 3) == len(list(lattice.enumerate_candidates(5, 3)))


def test_list_holds_k_before_it_prunes():
    b = BoundedTopK(2)
    assert b.threshold == -1
    b.offer(0.5, (0,), 1)
    b.offer(1.7, (0,), 2)
    assert b.threshold == 0 and b.offer(0.9, (1,), 2) and b.threshold == pytest.approx(0.1)
    assert not b.offer(0.9, (1, 3), 2)  # ties go to the shorter side
    assert [e[1:3] for e in b.result()] == [((0,), 1), ((1,), 2)]


def test_next_level_on_driver_and_in_spark(spark):
    level = lattice.full_level(6, 1, 63, 63)
    level[(1,)] &= ~4
    two = lattice.next_level(level)
    three = lattice.next_level(two)
    strict = lattice.next_level(two, all_subsets=True)
    one_df = lattice.level_frame(spark, level, 6)
    two_df = lattice.next_level_df(one_df)
    as_dict = lambda df: {tuple(r["lhs"]): r["s_mask"][0] for r in df.collect()}
    assert as_dict(two_df) == two and as_dict(lattice.next_level_df(two_df)) == three
    assert as_dict(lattice.next_level_df(two_df, all_subsets=True)) == strict
    assert all(strict[x] & ~three[x] == 0 for x in strict)


@pytest.mark.parametrize(("name", "depth", "v0", "v3", "v4", "late", "exact"), MEASURED)
def test_variants_agree_and_count_as_measured(spark, sf, name, depth, v0, v3, v4, late, exact):
    rel = relation(spark, sf, name)
    found = {v: search(rel, Options(20, depth, v, bound_mode="heuristic" if v == "V4" else "auto")) for v in ("V0", "V1", "V3", "V4")}
    base = found["V0"]
    assert base.report.ecn == v0 == lattice.candidate_count(rel.m, depth) == found["V1"].report.ecn
    assert base.report.exact_count == exact
    assert (found["V3"].report.ecn, found["V4"].report.ecn) == (v3, v4)
    key = lambda f: [(r, x, a, round(s, 9)) for r, x, a, s in f.entries]
    assert all(key(f) == key(base) for f in found.values())
    more = search(rel, Options(20, depth, tau_policy="level_end", propagation="all_subsets"))
    assert more.report.ecn == late and key(more) == key(base)
    inherited = search(rel, Options(20, depth, "V0", inherit=True))
    assert key(inherited) == key(base) and inherited.report.total("derived") > 0
    assert len(base.entries) == min(20, sum(not r["is_exact"] for r in base.scored.values() if r["n"] > 1))
    rel.release()


def test_null_counterexample(spark):
    rel = fixtures.nullbreak(spark)
    best = lambda **o: [(x, a, round(s, 6)) for _, x, a, s in search(rel, Options(1, 2, **o)).entries]
    truth = [((2, 3), 4, 0.533333)]
    assert best(variant="V0") == truth and best(bound_mode="sound") == truth and best(bound_mode="off") == truth
    assert best(bound_mode="heuristic") == [((0,), 1, 0.516369)]
    assert search(rel, Options(1, 2, bound_mode="heuristic")).report.ecn == 47
    assert search(rel, Options(1, 2, bound_mode="sound")).report.ecn == 50
    with pytest.raises(ValueError):
        search(rel, Options(1, 2, bound_mode="strict"))


def test_natural_nulls_modes_agree(spark, sf):
    rel = relation(spark, sf, "doc")
    lists = [search(rel, Options(20, 2, bound_mode=m)).entries for m in ("sound", "heuristic", "off")]
    assert lists[0] == lists[1] == lists[2]


def test_k_and_depth_move_costs_as_expected(spark, sf):
    rel = relation(spark, sf, "dirty")
    ecn = [search(rel, Options(k, 3, bound_mode="heuristic")).report.ecn for k in (5, 10, 20, 50, 100)]
    assert ecn == sorted(ecn) == [146, 146, 146, 169, 169]
    taus = [search(rel, Options(20, d)).report.tau_by_level[-1] for d in (1, 2, 3)]
    assert taus == sorted(taus)


def test_restrictions_and_limits(spark, sf):
    rel = relation(spark, sf, "dirty")
    f = search(rel, Options(10, 3, rhs=("market",), lhs_columns=("c_mktsegment", "r_name", "rep")))
    assert {a for _, _, a, _ in f.entries} == {rel.position("market")}
    assert max(s for *_, s in search(rel, Options(10, 3, rhs=("market",))).entries) == pytest.approx(0.906374, abs=1e-6)
    stopped = search(rel, Options(10, 5, time_limit_s=0.0))
    assert not stopped.report.complete and len(stopped.report.levels) == 1
    thin = search(rel, Options(20, 2, "V0", min_redundancy=1400))
    assert all(r["n"] - r["d_lhs"] >= 1400 for (x, a), r in thin.scored.items() if (x, a) in {(x, a) for _, x, a, _ in thin.entries})


def test_threshold_paradigm_sizes(spark, sf):
    rel = relation(spark, sf, "dirty")
    assert [threshold_discovery(rel, t, 3).count() for t in (0.5, 0.8, 0.9, 0.95)] == [44, 26, 26, 2]
    assert threshold_discovery(rel, 0.9, 2).count() == threshold_discovery(rel, 0.9, 2, prune=False).count()


def test_exact_dependencies(spark):
    rel = Relation.of(spark.createDataFrame([(1, 1, 5), (2, 1, 5), (3, 2, 6), (4, 2, 6)], "a int, b int, c int"))
    got = {(tuple(r["lhs"]), r["rhs"]) for r in exact_dependencies(rel, 2).collect()}
    assert got == {(("a",), "b"), (("a",), "c"), (("b",), "c"), (("c",), "b")}


def test_all_exact_gives_an_empty_list(spark):
    rel = Relation.of(spark.createDataFrame([(1, 1), (2, 2)], "a int, b int"))
    f = search(rel, Options(3, 5))
    assert f.entries == [] and f.frame().count() == 0


def test_reports(spark, sf, tmp_path):
    rel = relation(spark, sf, "orders")
    a, b = search(rel, Options(20, 2, "V0")), search(rel, Options(20, 2, "V4"))
    assert report.same_result(a.frame(), b.frame()) and report.overlap(a.frame(), b.frame(), 20) == 100
    assert a.report.pruning_ratio == 0 < b.report.pruning_ratio and len(report.speedup(a.report, b.report)) == 3
    assert report.explain_pruning(b.report).count("level") == 2 and a.report.frame(spark).count() == 2
    assert report.cost_model(6, 10, 2, "V2")["lhs_key_evaluations"] < report.cost_model(6, 10, 2, "V1")["lhs_key_evaluations"]
    write_topk(a.frame(), str(tmp_path / "t"), "orders")
    write_topk(a.frame(), str(tmp_path / "c"), "orders", "csv")
    write_report(a.report, spark, str(tmp_path / "r"))
    assert spark.read.parquet(str(tmp_path / "t")).where("relation = 'orders'").count() == 20


def test_level_tables_give_the_same_search(spark, sf):
    """Levels as tables, in small batches, against the driver's with the same late test."""
    rel = relation(spark, sf, "dirty")
    a, b = search(rel, Options(20, 3, tau_policy="level_end")), search(rel, Options(20, 3, lattice_rows=0, batch=30))
    assert a.entries == b.entries and [(x.ecn, x.exact, x.bound_pruned) for x in a.report.levels] == [(x.ecn, x.exact, x.bound_pruned) for x in b.report.levels]
    every = [search(rel, Options(20, 3, propagation="all_subsets", **o)) for o in ({"tau_policy": "level_end"}, {"lattice_rows": 0})]
    assert every[0].entries == every[1].entries and every[0].report.ecn == every[1].report.ecn


def test_time_limit_inside_a_level(spark, sf):
    f = search(relation(spark, sf, "part"), Options(5, 1, time_limit_s=0.0, batch=7))
    assert f.report.ecn == 7 and not f.report.complete and len(f.scored) == 7


def test_spark_costs_are_counted(spark, sf):
    at = search(relation(spark, sf, "part"), Options(5, 1)).report.levels[0]
    assert at.jobs >= 1 and at.tasks >= at.jobs and at.shuffle_bytes > 0 and at.driver_rows == at.ecn


def test_sentence(spark, sf):
    load(spark, sf, "part").createOrReplaceTempView("part")
    assert sql(spark, "DISCOVER TOP 3 DEPENDENCIES FROM part MAX LHS 2 FOR p_brand").count() == 3
    assert sql(spark, "discover dependencies from part max lhs 1 above 0.9").count() == 0
    above = sql(spark, "discover top 2 dependencies from part max lhs 2 for p_brand with variant v3 above 0.0").collect()
    assert len(above) == 2 and {r["rhs"] for r in above} == {"p_brand"} and above[0]["score"] >= above[1]["score"]
    every = sql(spark, "discover dependencies from part max lhs 2 for p_brand above 0.0").collect()
    assert max(r["score"] for r in every) == above[0]["score"]
    assert sql(spark, "select 1 as x").first()["x"] == 1


def test_searches_share_counts(spark, sf):
    """A search from counts taken once gives the list and costs of one that counts for itself, and counts nothing more."""
    rel = relation(spark, sf, "dirty")
    ledger = counted_all(rel, 3)
    assert len(ledger) == lattice.candidate_count(rel.m, 3)
    for v in ("V0", "V4"):
        alone, shared = search(rel, Options(20, 3, v)), search(rel, Options(20, 3, v, ledger=ledger))
        what = lambda f: ([e[:3] for e in f.entries], f.report.ecn, f.report.exact_count, [x.bound_pruned for x in f.report.levels])
        assert what(alone) == what(shared)
    assert len(ledger) == lattice.candidate_count(rel.m, 3)


def test_pivots_leave_no_exchange_files(spark, sf):
    """Counts of many blocks: the relation's exchanges are gone when they are known."""
    rel = relation(spark, sf, "orders")
    rel.codes.count()
    rel.marginals  # noqa: B018 -- its exchange is not in question
    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    shuffles = lambda: {f for f in disk.getAllFiles().mkString("\n").split("\n") if f.endswith(".data")}
    before = shuffles()
    blocks.block_counts(rel, [(i, ((0,), i)) for i in range(1, rel.m)], block_rows=2000).toArrow()
    time.sleep(1)
    assert sum(map(os.path.getsize, shuffles() - before)) < 50_000  # a small join of counts


@pytest.mark.parametrize(("twice", "block_rows"), [(False, 1_000_000), (False, 300), (True, 100)])
def test_parts_count_as_each_alone(spark, sf, twice, block_rows):
    """Parts that each hold the ones before, counted at once, in one block and in many, with NULLs and equal tuples; some tuples
    are in none."""
    df = relation(spark, sf, "doc").df.select("doc_id", "lang", "quality", "size_band")
    if twice:
        df = df.drop("doc_id").union(df.drop("doc_id"))
    number = F.pmod(F.xxhash64(*df.columns), F.lit(10))
    shares = (1, 9)
    parts = [Relation.of(df.where(number < t)) for t in shares]
    layer = F.coalesce(*(F.when(number < t, i) for i, t in enumerate(shares)))
    for part, ledger in zip(parts, counted_parts(df, layer, parts, 2, block_rows=block_rows), strict=True):
        given = part.profile
        part.release()
        alone = counted_all(part, 2)
        assert ledger.keys() == alone.keys() and given[:3] == part.profile[:3]
        for c, counts in alone.items():
            assert ledger[c] == (counts and pytest.approx(counts, abs=1e-12)), c


def test_parts_share_their_exchanges(spark, sf, monkeypatch):
    """scale_rows exchanges lineitem for all its parts at once: the bytes are those of one search of all rows, not of six."""
    monkeypatch.setattr(blocks, "BLOCK_ROWS", 20_000)
    for f in (blocks.block_counts, blocks.whole, counted_parts):
        monkeypatch.setattr(f, "__defaults__", tuple(20_000 if x == 1_000_000 else x for x in f.__defaults__))
    one, all_ = report.LevelReport(1), report.LevelReport(1)
    rel = Relation.of(load(spark, sf, "lineitem"))
    with report.Watch(spark, one):
        counted_all(rel, 1)
    rel.release()
    with report.Watch(spark, all_):
        rows = workloads.scale_rows(spark, sf, max_lhs=1, shared=True).collect()
    assert [r["n"] for r in rows[::2]] == sorted(r["n"] for r in rows[::2]) and rows[-1]["n"] == load(spark, sf, "lineitem").count()
    assert all_.shuffle_bytes < 1.5 * one.shuffle_bytes
