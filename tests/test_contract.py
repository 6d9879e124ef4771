"""Queries against their SQL, as the driver compares them."""

import math
import os

import duckdb
import pyarrow.parquet as pq
import pytest

from softdep import oracles, queries
from softdep.operators import score
from softdep.plans import lattice
from softdep.relation import Relation
from softdep.sources.tables import load, present_bits

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def compared(spark, sf, run, sql):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = run(spark, sf)
    columns = sorted(df.columns)
    norm = lambda v: (None if math.isnan(v) else round(v, 6) + 0.0) if isinstance(v, float) else v
    rows = lambda names, data: sorted(repr([norm(dict(zip(names, r, strict=True))[c]) for c in columns]) for r in data)
    want = con.sql(sql)
    assert sorted(want.columns) == columns
    assert rows(df.columns, df.collect()) == rows(list(want.columns), want.fetchall())


@pytest.mark.parametrize("name", sorted(oracles.ORACLES))
def test_query_matches_sql(spark, sf, name):
    compared(spark, sf, queries.QUERIES[name], oracles.ORACLES[name])


def test_every_query_without_sql_gives_rows(spark, sf):
    for name in sorted(set(queries.QUERIES) - set(oracles.ORACLES)):
        assert not queries.QUERIES[name](spark, sf).isEmpty(), name


@pytest.mark.parametrize("name", ["nullbreak_exhaustive", "nullbreak_sound", "six_row_example"])
def test_queries_of_small_examples_read_a_given_table(spark, sf, name):
    assert queries.QUERIES[name](spark, sf).first()["lhs"].split(",")[0] in oracles.columns("doc")


def with_own(sf, folder, name, df):
    """A folder of the given tables but one, which is df."""
    for t in TABLES:
        if t != name:
            os.symlink(f"{sf}/{t}.parquet", f"{folder}/{t}.parquet")
    pq.write_table(df.toArrow(), f"{folder}/{name}.parquet")
    return str(folder)


def test_candidate_counts_are_of_a_given_table(spark, sf):
    """The tuples of each width and depth are those of all its candidates, counted one by one."""
    got = {(r["m"], r["max_lhs"]): r for r in queries.QUERIES["candidate_counts"](spark, sf).collect()}
    bits = present_bits(load(spark, sf, "embeddings"))
    for m, k in ((2, 1), (5, 3)):
        rel = Relation.of(bits.select(*bits.columns[:m]))
        n = [r["n"] or 0 for r in score.statistics(rel, list(lattice.enumerate_candidates(m, k))).select("n").collect()]
        assert (got[m, k]["candidates"], got[m, k]["tuples"]) == (len(n), sum(n))
    assert len(got) == 633 and got[109, 6]["tuples"] > got[109, 6]["candidates"]


@pytest.mark.parametrize("vectors", [[], [None, [1.0] * 64, [1.0] * 64, [-1.0] * 64, [0.125] * 64, [0.5, -0.25, float("nan")], [None] * 64]])
def test_candidate_counts_of_odd_vectors(spark, sf, tmp_path, vectors):
    own = spark.createDataFrame([(i, v, 0) for i, v in enumerate(vectors)], "vec_id long, embedding array<float>, label int")
    compared(spark, with_own(sf, tmp_path, "embeddings", own), queries.QUERIES["candidate_counts"], oracles.ORACLES["candidate_counts"])


#: Of part: names decide brands; brands and types decide prices, but neither does alone.
PLANTED = [(i, f"n{i % 8}", f"b{i % 8 // 2}", f"t{i % 3}", i % 5, float(7 * (i % 8 // 2) + 3 * (i % 3) ** 2)) for i in range(240)]


@pytest.mark.parametrize("rows", [PLANTED, PLANTED[:1], [], [(None, "n", None, "t", 1, 2.0), (1, "n", "b", None, 1, 2.0), (2, "m", "b", "t", 1, None)]])
def test_next_levels_start_from_what_is_exact_on_the_table(spark, sf, tmp_path, rows):
    own = spark.createDataFrame(rows, load(spark, sf, "part").schema)
    folder = with_own(sf, tmp_path, "part", own)
    compared(spark, folder, queries.QUERIES["next_level_demo"], oracles.ORACLES["next_level_demo"])
    if rows is PLANTED:
        mask = {r["lhs"]: r["mask"] for r in queries.QUERIES["next_level_demo"](spark, folder).collect()}
        assert not any(x.startswith("0") for x in mask)  # the key decides everything
        assert not mask["1,3"] & 1 << 2
        assert mask["2,3"] & mask["2,4"] & 1 << 5 and not mask["2,3,4"] & 1 << 5


@pytest.mark.parametrize("vectors", [[], [None, None, [1.0] * 64, [-1.0] * 64, [0.0] * 64], [[(-1.0) ** (i >> b & 1) for b in range(64)] for i in range(40)]])
def test_cost_model_is_of_a_given_table(spark, sf, tmp_path, vectors):
    own = spark.createDataFrame([(i, v, 0) for i, v in enumerate(vectors)], "vec_id long, embedding array<float>, label int")
    folder = with_own(sf, tmp_path, "embeddings", own)
    compared(spark, folder, queries.QUERIES["cost_model_table"], oracles.ORACLES["cost_model_table"])
    n = {r["m"]: r["n"] for r in queries.QUERIES["cost_model_table"](spark, folder).collect()}
    assert len(vectors) != 40 or n == {5: 32, 10: 40, 20: 40}


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 5
    assert set(e.oracle_sql()) <= set(e.queries())
