"""Hand values, brute force on pairs of rows, and invariants of the scores."""

import itertools
import math
import random
from collections import Counter
from fractions import Fraction

import numpy as np
import pytest

from softdep import fixtures
from softdep.functions import measures, udfs
from softdep.operators import blocks, reliable, score
from softdep.operators.joint import joint_table, null_patterns
from softdep.plans.lattice import enumerate_candidates
from softdep.plans.search import Options, search
from softdep.relation import Relation


def stats(rel, cands, **options):
    return {(tuple(r["lhs"]), r["rhs"]): r for r in score.statistics(rel, cands, **options).collect()}


def brute(rows, lhs, rhs):
    """Counts and mu+ from pairs of rows."""
    rows = [r for r in rows if all(r[i] is not None for i in (*lhs, rhs))]
    n = len(rows)
    if n <= 1:
        return n, None, None
    key = lambda r: tuple(r[i] for i in lhs)
    groups = {}
    for r in rows:
        groups.setdefault(key(r), []).append(r[rhs])
    agree = sum(Fraction(sum(a == b for a in g for b in g), len(g)) for g in groups.values()) / n
    chance = Fraction(sum(a[rhs] == b[rhs] for a in rows for b in rows), n * n)
    exact = all(len(set(g)) == 1 for g in groups.values())
    if exact:
        return n, 1.0, True
    rho = (1 - agree) / (1 - chance) * Fraction(n - 1, n - len(groups))
    return n, max(0.0, float(1 - rho)), False


def test_six_rows(spark):
    r = stats(fixtures.six(spark), [((0,), 1)])[((0,), 1)]
    assert (r["n"], r["d_lhs"], r["d_joint"]) == (6, 3, 4)
    assert r["disagree_lhs"] == pytest.approx(2 / 9) and r["disagree_rhs"] == pytest.approx(11 / 18)
    assert r["rho"] == pytest.approx(20 / 33) and r["mu_plus"] == pytest.approx(13 / 33) and r["bound"] == pytest.approx(6 / 11)


@pytest.mark.parametrize("kernel", ["blocks", "blocks_each", "joint", "lhs_shared", "candidate"])
def test_random_relations_against_pairs(spark, kernel):
    rng = random.Random(5)
    for nulls in (0.0, 0.25):
        rows = [tuple(None if rng.random() < nulls else rng.randrange(k) for k in (2, 3, 4)) for _ in range(24)]
        rel = Relation.of(spark.createDataFrame(rows, "a int, b int, c int"))
        cands = list(enumerate_candidates(3, 2))
        got = stats(rel, cands, kernel=kernel)
        for x, a in cands:
            n, mu, exact = brute(rows, x, a)
            assert got[(x, a)]["n"] == n
            if n > 1:
                assert got[(x, a)]["mu_plus"] == pytest.approx(mu) and got[(x, a)]["is_exact"] == exact


def test_edges(spark):
    nan = float("nan")
    rows = [(1, 1, None, nan, 0.0, "s"), (1, 2, None, nan, -0.0, "s"), (1, 3, None, 1.0, 0.0, "t"), (1, 3, None, 1.0, 0.0, "t")]
    rel = Relation.of(spark.createDataFrame(rows, "const int, near int, nothing int, f double, z double, s string"))
    got = stats(rel, list(enumerate_candidates(6, 1)))
    assert got[((1,), 0)]["is_exact"] and got[((1,), 0)]["mu_plus"] == 1  # constant right side
    assert got[((2,), 0)]["n"] == 0 and got[((2,), 0)]["mu_plus"] is None  # all NULL
    assert got[((3,), 5)]["is_exact"] and got[((5,), 3)]["is_exact"]  # NaN equals NaN
    assert got[((0,), 4)]["is_exact"]  # 0.0 equals -0.0
    one = Relation.of(spark.createDataFrame([(1, 2)], "a int, b int"))
    assert stats(one, [((0,), 1)])[((0,), 1)]["mu_plus"] is None
    value = Relation.of(spark.createDataFrame(rows, "const int, near int, nothing int, f double, z double, s string"), null_policy="as_value")
    assert stats(value, [((2,), 0)])[((2,), 0)]["n"] == 4


def test_recoding_and_row_order_change_nothing(spark):
    rows = [(i % 3, (i * 7) % 5, i % 2) for i in range(30)]
    a = stats(Relation.of(spark.createDataFrame(rows, "a int, b int, c int")), list(enumerate_candidates(3, 2)))
    shuffled = rows[:]
    random.Random(1).shuffle(shuffled)
    b = stats(Relation.of(spark.createDataFrame([(f"v{x}", -y, float(z)) for x, y, z in shuffled], "a string, b int, c double").repartition(3)), list(enumerate_candidates(3, 2)))
    assert all(a[k]["mu_plus"] == pytest.approx(b[k]["mu_plus"]) and a[k]["is_exact"] == b[k]["is_exact"] for k in a)


def test_correction_is_chance_neutral(spark):
    """The unclamped score of a shuffled right side is 0 in the mean."""
    rng = random.Random(3)
    right = [rng.randrange(3) for _ in range(40)]
    total = []
    for _ in range(30):
        rng.shuffle(right)
        rel = Relation.of(spark.createDataFrame([(i % 8, v) for i, v in enumerate(right)], "x int, a int"))
        total.append(1 - stats(rel, [((0,), 1)])[((0,), 1)]["rho"])
    assert abs(sum(total) / len(total)) < 0.1


def test_one_candidate_helpers_and_sql_functions(spark):
    rel = fixtures.six(spark)
    assert score.agreement(rel, ["x"], "a") == pytest.approx(7 / 9)
    assert score.mu_plus(rel, ["x"], "a") == pytest.approx(13 / 33)
    assert not score.holds_exactly(rel, ["x"], "a")
    measures.register(spark)
    r = spark.sql("SELECT mu_plus_of(6, 3, 2 / 9D, 11 / 18D) AS m, optimistic_bound_of(6, 3, 11 / 18D) AS b").first()
    assert r["m"] == pytest.approx(13 / 33) and r["b"] == pytest.approx(6 / 11)
    udfs.register(spark)
    rel.df.createOrReplaceTempView("six")
    assert spark.sql("SELECT agreement_agg(x, a) AS g FROM six").first()["g"] == pytest.approx(7 / 9)
    assert {(r["subset"], r["size"]) for r in spark.sql("SELECT * FROM subsets_of(5)").collect()} == {(5, 2), (4, 1), (1, 1)}


def test_information_measures(spark):
    rel = fixtures.six(spark)
    f = reliable.fraction_of_information(rel, ["x"], "a")
    assert 0 < f < 1
    got = reliable.rfi_frame(rel, [((0,), 1), ((1,), 0)]).collect()
    assert {tuple(r["lhs"]) for r in got} == {(0,), (1,)} and all(0 <= r["rfi"] <= f for r in got if r["rhs"] == 1)
    assert reliable.rfi_prime_plus(rel, ["x"], "a") == pytest.approx(next(r["rfi"] for r in got if r["rhs"] == 1))


def test_permutation_mean_against_all_permutations():
    """Of six tuples, every permutation of the right side; and Stirling's series against sums of logarithms."""
    left, right = [0, 0, 0, 1, 1, 2], [0, 0, 1, 1, 1, 2]
    entropy = lambda x: -sum(c / 6 * math.log2(c / 6) for c in Counter(x).values())
    gains = [entropy(left) + entropy(p) - entropy(zip(left, p, strict=True)) for p in itertools.permutations(right)]
    sizes = lambda x: np.array(sorted(Counter(x).values()))
    assert reliable.expected_information(sizes(left), sizes(right)) == pytest.approx(sum(gains) / len(gains))
    assert reliable.log_factorial(np.array([0, 1, 5, 15, 16, 17, 400])) == pytest.approx([math.lgamma(x + 1) for x in (0, 1, 5, 15, 16, 17, 400)])


@pytest.mark.parametrize("collapse", [False, True])
def test_many_blocks_count_as_one(spark, collapse):
    """Fine and coarse columns, with NULLs and a hot value, in blocks of any size."""
    rng = random.Random(7)
    rows = [(rng.randrange(40), "hot" if rng.random() < 0.4 else f"v{rng.randrange(30)}", rng.randrange(2), None if rng.random() < 0.2 else rng.randrange(25), rng.random() < 0.5) for _ in range(150)]
    rel = Relation.of(spark.createDataFrame(rows, "a int, b string, c int, d int, e boolean"), collapse=collapse)
    cands = list(enumerate(enumerate_candidates(5, 2)))
    key = lambda df: {r["cid"]: [round(x, 9) for x in r[1:]] for r in df.collect()}
    want = key(score.joint_counts(rel, cands))
    assert key(blocks.block_counts(rel, cands)) == want
    for size in (20, 70):
        assert key(blocks.block_counts(rel, cands, block_rows=size)) == want


@pytest.mark.parametrize("m", [64, 65, 109])
def test_wide_tables(spark, m):
    rows = [tuple(None if (i + k) % 11 == 0 else (i * (k + 3)) % 5 for k in range(m)) for i in range(30)]
    rel = Relation.of(spark.createDataFrame(rows, ", ".join(f"c{k} int" for k in range(m))))
    f = search(rel, Options(20, 1))
    assert f.report.ecn == m * (m - 1) and len(f.entries) == 20
    for x, a in [((0,), m - 1), ((m - 1,), 3)]:
        n, mu, exact = brute(rows, x, a)
        assert f.scored[(x, a)]["n"] == n and f.scored[(x, a)]["is_exact"] == exact and f.scored[(x, a)]["mu_plus"] == pytest.approx(mu)
    words = {tuple(r["null_mask"]): r["n"] for r in null_patterns(rel).collect()}
    seen = Counter(tuple(sum(1 << (k % 62) for k in range(62 * w, min(62 * w + 62, m)) if r[k] is None) for w in range(-(-m // 62))) for r in rows)
    assert words == dict(seen)
    assert score.marginal_agreement(rel).count() == m


def test_joint_table_and_patterns(spark):
    rel = Relation.of(spark.createDataFrame([(1, None), (1, 2), (1, 2)], "a int, b int"))
    assert [tuple(r) for r in joint_table(rel, ["a", "b"]).collect()] == [(1, 2, 2)]
    assert {tuple(r["null_mask"]): r["n"] for r in null_patterns(rel).collect()} == {(0,): 2, (2,): 1}


def test_bound_holds_for_descendants_without_nulls(spark):
    rng = random.Random(11)
    for _ in range(3):
        rows = [tuple(rng.randrange(3) for _ in range(4)) for _ in range(20)]
        rel = Relation.of(spark.createDataFrame(rows, "a int, b int, c int, d int"))
        got = stats(rel, list(enumerate_candidates(4, 3)), complete_rows=20)
        for (x, a), (y, b) in itertools.product(got, got):
            if a == b and set(x) < set(y) and not got[(x, a)]["is_exact"] and not got[(y, b)]["is_exact"]:
                for bound in ("bound", "sound_bound"):
                    assert got[(y, b)]["mu_plus"] <= max(0.0, got[(x, a)][bound]) + 1e-9
