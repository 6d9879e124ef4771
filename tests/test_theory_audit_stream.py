"""The three properties, violating rows, time joins and streams."""

from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from softdep.operators import audit, score, temporal, theory
from softdep.plans.lattice import enumerate_candidates
from softdep.sources import tables
from softdep.sources.tables import load, relation
from softdep.streaming import audit as stream_audit


@pytest.fixture(scope="module")
def dirty(spark, sf):
    return relation(spark, sf, "dirty")


@pytest.fixture(scope="module")
def scores(dirty):
    return score.statistics(dirty, list(enumerate_candidates(dirty.m, 2))).where("n > 1 and not is_exact").select("lhs", "rhs", "rho", "mu_plus").persist()


def test_the_three_cannot_hold_together(scores):
    got = {k: theory.check_properties(theory.enforce(scores, 2, k), scores, 2) for k in ("P2P3", "P1P3", "P1P2")}
    assert got["P2P3"] == theory.Properties(False, True, True)
    assert (got["P1P3"].minimal, got["P1P3"].top_k, got["P1P3"].exactly_k) == (True, False, True)
    assert got["P1P2"].minimal and not got["P1P2"].exactly_k


def test_properties_count_dependencies_outside_the_result(spark):
    """Two on one right side, the larger better, and one apart: the result without the smaller is still not minimal."""
    scores = spark.createDataFrame([([0], 2, 0.5, 0.5), ([0, 1], 2, 0.1, 0.9), ([3], 4, 0.2, 0.8)], "lhs array<int>, rhs int, rho double, mu_plus double")
    key = lambda df: [(tuple(r["lhs"]), r["rhs"]) for r in theory.ranked(df).collect()]
    got = {k: theory.enforce(scores, 2, k) for k in ("P2P3", "P1P3", "P1P2")}
    assert {k: key(v) for k, v in got.items()} == {"P2P3": [((0, 1), 2), ((3,), 4)], "P1P3": [((3,), 4), ((0,), 2)], "P1P2": []}
    assert {k: theory.check_properties(v, scores, 2) for k, v in got.items()} == {"P2P3": theory.Properties(False, True, True), "P1P3": theory.Properties(True, False, True), "P1P2": theory.Properties(True, True, False)}
    w = theory.incompatibility_witness(scores).first()
    assert (w["small"], w["large"], w["rhs"], w["low"], w["high"], w["other_lhs"]) == ([0], [0, 1], 2, 0.5, 0.9, None)
    lower = scores.union(spark.createDataFrame([([5], 6, 0.7, 0.3)], scores.schema))
    assert theory.incompatibility_witness(lower).first()["other_lhs"] == [5]


def test_witness(scores):
    """Among the three, for k = 2: the best two are not minimal, the minimal two are not the best, and no two are both."""
    w = theory.incompatibility_witness(scores).first()
    assert set(w["small"]) < set(w["large"]) and w["high"] > w["low"] > w["other"] > 0
    assert not {*w["other_lhs"], w["other_rhs"]} & {*w["large"], w["rhs"]}
    three = scores.sparkSession.createDataFrame([(w["small"], w["rhs"], 1 - w["low"], w["low"]), (w["large"], w["rhs"], 1 - w["high"], w["high"]), (w["other_lhs"], w["other_rhs"], 1 - w["other"], w["other"])], scores.schema)
    for keep, lost in (("P2P3", "minimal"), ("P1P3", "top_k"), ("P1P2", "exactly_k")):
        p = theory.check_properties(theory.enforce(three, 2, keep), three, 2)
        assert [k for k, v in vars(p).items() if not v] == [lost]


def test_witness_ties_go_to_positions(spark):
    """Equal scores that differ in the last digit by the order in which rows were summed."""
    less, more = 0.5, 0.5 + 1e-15
    rows = [([0], 9, 0.4, 0.6), ([0, 1], 9, 0.1, 0.9 - 1e-15), ([0, 2], 9, 0.1, 0.9), ([4], 5, less, 1 - more), ([6], 5, less, 1 - less)]
    w = theory.incompatibility_witness(spark.createDataFrame(rows, "lhs array<int>, rhs int, rho double, mu_plus double")).first()
    assert (w["large"], w["other_lhs"]) == ([0, 1], [4])


def test_scores_move_both_ways(scores):
    assert not theory.growth_chains(scores).isEmpty()
    assert not theory.subset_pairs(scores).where("high < low - 1e-9").isEmpty()


def test_violations_are_the_planted_flips(spark, sf, dirty):
    flips = load(spark, sf, "customer").where((F.col("c_custkey") * 7919) % 101 < 4).count()
    v = audit.violations(dirty, ["r_name"], "market")
    assert v.where("is_violation").count() == flips and v.where("is_violation and market != 'OTHER'").isEmpty()
    r = audit.suggest_repairs(dirty, ["r_name"], "market").collect()
    assert all(x["found"] == "OTHER" and x["suggested"] == x["r_name"] for x in r) and sum(x["n_rows"] for x in r) == flips
    assert audit.violations(dirty, ["r_name"], "market", keep_all=True).count() == dirty.df.where("market is not null").count()


def test_salted_violations_are_the_broadcast_ones(dirty):
    key = lambda df: sorted(map(repr, df.collect()))
    assert key(audit.violations(dirty, ["c_nationkey"], "market")) == key(audit.violations(dirty, ["c_nationkey"], "market", max_broadcast_rows=0))


def test_violation_ties_and_nulls(spark):
    from softdep.relation import Relation

    rel = Relation.of(spark.createDataFrame([(1, "b"), (1, "a"), (1, None), (None, "a"), (2, "c")], "x int, a string"))
    assert sorted((r["a"], r["is_violation"], r["majority"]) for r in audit.violations(rel, ["x"], "a").collect()) == [("a", False, "a"), ("b", True, "a")]


def test_time_joins_against_loops(spark):
    rows = [(i, (i * 7) % 3, (i * 13) % 50) for i in range(40)]
    df = spark.createDataFrame(rows, "id int, u int, s int").withColumn("ts", F.timestamp_seconds(F.col("s") * 1000))
    prev = {r["id"]: r["p"] for r in temporal.previous_value(df, "u", "ts", "id", "p").collect()}
    asof = {r["id"]: r["rid"] for r in temporal.asof_join(df, df.select("u", F.col("ts").alias("rts"), F.col("id").alias("rid")), "u", "ts", "rts", ["rid"], bucket_seconds=3600).select("id", "rid").collect()}
    pairs = {(r["id"], r["rid"]) for r in temporal.interval_join(df.select("id", "u", "ts"), df.select(F.col("id").alias("rid"), "u", F.col("ts").alias("rts")), "u", "ts", "rts", 5000).collect()}
    for i, u, s in rows:
        before = [(t, j) for j, v, t in rows if v == u and t < s]
        assert prev[i] == (max(before)[1] if before else None)
        assert asof[i] == max((t, j) for j, v, t in rows if v == u and t <= s)[1]
        assert {j for a, j in pairs if a == i} == {j for t, j in before if t >= s - 5}


@pytest.fixture
def event_files(spark, sf, tmp_path):
    """The events in ten files in time order, then one with rows far behind."""
    e = load(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type", F.from_json("props", "k int")["k"].alias("k")).orderBy("ts").toPandas()
    step = len(e) // 10
    for i in range(10):
        e.iloc[i * step : (i + 1) * step if i < 9 else len(e)].to_parquet(tmp_path / f"{i:02d}.parquet", coerce_timestamps="us", index=False)
    e.iloc[:50].to_parquet(tmp_path / "10.parquet", coerce_timestamps="us", index=False)
    return str(tmp_path)


def test_stream_counts_are_the_batch_counts(spark, event_files, tmp_path_factory):
    ad = (("event_type",), "k")
    batch = spark.read.parquet(event_files)
    stream = spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 3).parquet(event_files)
    out = str(tmp_path_factory.mktemp("s"))
    stream_audit.stream_counts(stream, ad, f"{out}/t", f"{out}/c").awaitTermination()
    key = lambda df: sorted(map(tuple, df.collect()))
    merged = stream_audit.merged_counts(spark, f"{out}/t")
    assert key(merged) == key(stream_audit.joint_counts(batch, ad))
    a, b = (stream_audit.scored(x, []).first() for x in (merged, stream_audit.joint_counts(batch, ad)))
    assert a["n"] == b["n"] and a["mu_plus"] == pytest.approx(b["mu_plus"])


def test_late_rows_are_dropped_and_counted(spark, event_files, tmp_path_factory):
    stream = spark.readStream.schema(spark.read.parquet(event_files).schema).option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(event_files)
    out = str(tmp_path_factory.mktemp("w"))
    q = stream_audit.stream_counts(stream, (("event_type",), "k"), f"{out}/t", f"{out}/c", watermark="1 day", window="1 day")
    q.awaitTermination()
    assert stream_audit.dropped_by_watermark(q) > 0
    assert spark.read.parquet(f"{out}/t").agg(F.sum("f")).first()[0] <= 10000


def test_dedup_and_alerts(spark, event_files, tmp_path_factory):
    stream = spark.readStream.schema(spark.read.parquet(event_files).schema).parquet(event_files)
    out = str(tmp_path_factory.mktemp("d"))
    q = stream_audit.deduplicated(stream, watermark="365 days").writeStream.format("parquet").option("path", f"{out}/t").option("checkpointLocation", f"{out}/c").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.read.parquet(f"{out}/t").count() == 10000
    alerts = stream_audit.violation_alerts(stream, "event_type", "k").writeStream.format("memory").queryName("alerts").outputMode("append").trigger(availableNow=True).start()
    alerts.awaitTermination()
    n = spark.table("alerts").count()
    seen = Counter(r["lhs"] for r in spark.table("alerts").collect())
    assert 0 < n <= 10050 and len(seen) == 5


def test_windows_partition_the_rows(spark, sf):
    e = load(spark, sf, "events").select("ts", "event_type", F.from_json("props", "k int")["k"].alias("k"))
    day = stream_audit.windowed_scores(e, (("event_type",), "k")).collect()
    assert sum(r["n"] for r in day) == e.count()
    by = defaultdict(int)
    for r in stream_audit.windowed_scores(e, (("event_type",), "k"), window="2 days", slide="1 day").collect():
        by[r["end"] - r["start"]] += r["n"]
    assert list(by.values()) == [2 * e.count()]


def test_sources(spark, sf, tmp_path):
    part = tables.read_any(spark, f"{sf}/part.parquet", columns=["p_name", "p_size"])
    assert part.columns == ["p_name", "p_size"]
    part.write.csv(str(tmp_path / "c"), header=True)
    assert tables.read_any(spark, str(tmp_path / "c"), "csv", "p_name string, p_size int", header="true").count() == part.count()
    flat = tables.flattened(spark.sql("select struct(1 as a, struct(2 as b) as c) as s, 3 as t"))
    assert flat.columns == ["s_a", "s_c_b", "t"]
    some, more = (tables.hash_sample(part, F.col("p_name"), p) for p in (20, 60))
    assert some.exceptAll(more).isEmpty() and some.count() < more.count()
    bits = tables.sign_bits(load(spark, sf, "embeddings"), 8)
    assert bits.columns[:2] == ["b00", "b01"] and len(bits.columns) == 9


def test_plans_push_filters_and_read_few_columns(spark, sf):
    from softdep.operators.joint import joint_table
    from softdep.relation import Relation

    plan = joint_table(Relation.of(load(spark, sf, "lineitem")), ["l_tax", "l_returnflag"])._jdf.queryExecution().executedPlan().toString()
    assert "IsNotNull(l_tax)" in plan and "l_orderkey" not in plan
