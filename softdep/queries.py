"""The driver's queries: name -> (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from softdep import workloads
from softdep.functions import measures, sqlfront
from softdep.operators import audit, blocks, joint, reliable, score, temporal, theory
from softdep.plans import lattice, report
from softdep.plans.search import Options, exact_dependencies, search, threshold_discovery
from softdep.relation import Relation
from softdep.shared import shared_dir
from softdep.sources.tables import load, present_bits, relation, sign_bits
from softdep.streaming import audit as stream_audit

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(name: str) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        return f

    return put


def r6(c: str):
    return F.round(c, 6).alias(c)


def all_stats(rel: Relation, max_lhs: int, complete_rows: int | None = None) -> DataFrame:
    return score.statistics(rel, list(lattice.enumerate_candidates(rel.m, max_lhs)), complete_rows=complete_rows)


def score_table(rel: Relation, max_lhs: int) -> DataFrame:
    return score.named(rel, all_stats(rel, max_lhs)).select("lhs", "rhs", "n", "d_lhs", "d_joint", r6("mu_plus"), "is_exact")


def joined(topk: DataFrame) -> DataFrame:
    return topk.select("rank", F.array_join("lhs", ",").alias("lhs"), "rhs", r6("mu_plus"))


def non_exact(rel: Relation, max_lhs: int) -> DataFrame:
    return all_stats(rel, max_lhs).where("n > 1 and not is_exact").select("lhs", "rhs", "rho", "mu_plus")


def names_of(rel: Relation, c: str):
    names = F.array(*map(F.lit, rel.columns))
    return F.array_join(F.transform(c, lambda i: F.element_at(names, i + 1)), ",").alias(c)


def name_of(rel: Relation, c: str):
    return F.element_at(F.array(*map(F.lit, rel.columns)), F.col(c) + 1).alias(c)


# Measures.
for _name in ("part", "orders", "dirty"):
    QUERIES[f"agreement_{_name}"] = lambda s, d, n=_name: score.named(r := relation(s, d, n), all_stats(r, 1)).select("lhs", "rhs", F.round(1 - F.col("disagree_lhs"), 6).alias("agreement"))
for _name in ("lineitem", "doc"):
    QUERIES[f"marginal_agreement_{_name}"] = lambda s, d, n=_name: score.marginal_agreement(relation(s, d, n)).select("attribute", "n", "d", r6("agreement"))
QUERIES["lift_part"] = lambda s, d: score.named(r := relation(s, d, "part"), all_stats(r, 1)).select("lhs", "rhs", r6("lift"))
QUERIES["rho_raw_events"] = lambda s, d: score.named(r := relation(s, d, "events"), all_stats(r, 1)).select("lhs", "rhs", r6("rho"), F.round(1 - F.col("rho"), 6).alias("mu_raw"))
QUERIES["g3_part"] = lambda s, d: score.named(r := relation(s, d, "part"), all_stats(r, 1)).select("lhs", "rhs", r6("g3_error"))
QUERIES["gain_part"] = lambda s, d: score.named(r := relation(s, d, "part"), all_stats(r, 1)).select("lhs", "rhs", r6("gain"))
for _name in ("lineitem", "orders", "customer", "part", "events", "doc", "dirty", "conv", "page", "wide"):
    QUERIES[f"scores_l1_{_name}"] = lambda s, d, n=_name: score_table(relation(s, d, n), 1)
for _name in ("part", "orders", "events", "doc", "dirty"):
    QUERIES[f"scores_l2_{_name}"] = lambda s, d, n=_name: score_table(relation(s, d, n), 2)

CHAIN = [(("l_quantity",), "l_linenumber"), (("l_quantity", "l_extendedprice"), "l_linenumber"), (("l_quantity", "l_extendedprice", "l_returnflag"), "l_linenumber")]


@query("mu_plus_lineitem_chain")
def mu_plus_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "lineitem")
    cands = [(tuple(rel.position(c) for c in lhs), rel.position(rhs)) for lhs, rhs in CHAIN]
    return score.named(rel, score.statistics(rel, cands)).select("lhs", "rhs", "n", "d_lhs", "d_joint", r6("mu_plus"))


@query("six_row_example")
def six_row_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every quantity that the six-row example explains, on a table of seven attributes with NULLs."""
    rel = relation(spark, sf_dir, "doc")
    return score.named(rel, all_stats(rel, 1)).select("lhs", "rhs", "n", "d_lhs", r6("disagree_lhs"), r6("disagree_rhs"), r6("rho"), r6("mu_plus"), r6("bound"))


QUERIES["bound_table_orders"] = lambda s, d: score.named(r := relation(s, d, "orders"), all_stats(r, 1)).where("not is_exact").select("lhs", "rhs", r6("bound"))


@query("sound_bound_doc")
def sound_bound_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "doc")
    return score.named(rel, all_stats(rel, 1, rel.profile.complete)).where("not is_exact").select("lhs", "rhs", r6("sound_bound"))


@query("rfi_plus_dirty")
def rfi_plus_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "dirty")
    return score.named(rel, reliable.rfi_frame(rel, list(lattice.enumerate_candidates(rel.m, 1)))).select("lhs", "rhs", "n", r6("rfi"))


# Exact dependencies.
for _name in ("customer", "wide"):
    QUERIES[f"exact_fd_{_name}"] = lambda s, d, n=_name: exact_dependencies(relation(s, d, n), 1 if n == "wide" else 2, minimal=False).select(F.array_join("lhs", ",").alias("lhs"), "rhs")
for _name in ("customer", "dirty"):
    QUERIES[f"exact_fd_minimal_{_name}"] = lambda s, d, n=_name: exact_dependencies(relation(s, d, n), 2).select(F.array_join("lhs", ",").alias("lhs"), "rhs")

# Searches.
for _v in ("V0", "V1", "V2", "V3", "V4"):
    QUERIES[f"topk_{_v.lower()}_part"] = lambda s, d, v=_v: joined(search(relation(s, d, "part"), Options(20, 2, v)).frame())
TOPK_DEPTH = {"orders": 3, "events": 2, "doc": 2, "dirty": 3}
for _name, _l in TOPK_DEPTH.items():
    QUERIES[f"topk_v4_{_name}"] = lambda s, d, n=_name, k=_l: joined(search(relation(s, d, n), Options(20, k)).frame())
QUERIES["topk_customer_short"] = lambda s, d: joined(search(relation(s, d, "customer"), Options(20, 4)).frame())
for _mode, _label in (("sound", "sound"), ("heuristic", "heuristic"), ("off", "nobound")):
    QUERIES[f"topk_doc_{_label}"] = lambda s, d, m=_mode: joined(search(relation(s, d, "doc"), Options(20, 2, bound_mode=m)).frame())
QUERIES["topk_dirty_late_all_subsets"] = lambda s, d: joined(search(relation(s, d, "dirty"), Options(20, 3, tau_policy="level_end", propagation="all_subsets", inherit=True)).frame())
QUERIES["nullbreak_exhaustive"] = lambda s, d: joined(search(relation(s, d, "doc"), Options(1, 2, "V0")).frame())
QUERIES["nullbreak_sound"] = lambda s, d: joined(search(relation(s, d, "doc"), Options(1, 2, "V4", bound_mode="sound")).frame())
QUERIES["fixed_rhs_market"] = lambda s, d: joined(search(relation(s, d, "dirty"), Options(10, 2, rhs=("market",))).frame())
for _theta in (50, 80, 90, 95):
    QUERIES[f"threshold_dirty_{_theta}"] = lambda s, d, t=_theta: threshold_discovery(relation(s, d, "dirty"), t / 100, 2).select(F.array_join("lhs", ",").alias("lhs"), "rhs", F.round("score", 6).alias("mu_plus"))


@query("candidate_counts")
def candidate_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the first m of 109 columns: the candidates, and the tuples that they keep when NULLs are ignored, summed. A tuple is
    kept by as many candidates as its present values alone would have."""
    rel = Relation.of(present_bits(load(spark, sf_dir, "embeddings")))
    counts = spark.createDataFrame([(m, k, lattice.candidate_count(m, k)) for m in range(rel.m + 1) for k in range(1, 7)], "m int, max_lhs int, candidates long")
    m, present = F.col("m"), F.col("m")
    for w in range(-(-rel.m // joint.WORD)):
        first = F.least(F.greatest(m - joint.WORD * w, F.lit(0)), F.lit(joint.WORD))
        ahead = F.call_function("shiftleft", F.lit(1).cast("long"), first) - 1  # of the word's bits, those of the first m columns
        present = present - F.bit_count(F.element_at("null_mask", w + 1).bitwiseAND(ahead))
    widths = F.explode(F.sequence(F.lit(2), F.lit(rel.m))).alias("m")
    held = joint.null_patterns(rel).select("null_mask", "n", widths).groupBy("m", present.alias("present")).agg(F.sum("n").alias("n"))
    each = counts.select(F.col("m").alias("present"), "max_lhs", F.col("candidates").alias("each"))
    tuples = held.join(F.broadcast(each), "present").groupBy("m", "max_lhs").agg(F.sum(F.col("n") * F.col("each")).alias("tuples"))
    listed = counts.where("m > 1 and max_lhs < m").join(tuples, ["m", "max_lhs"], "left")
    return listed.select("m", "max_lhs", "candidates", F.coalesce("tuples", F.lit(0)).alias("tuples"))


@query("next_level_demo")
def next_level_demo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Levels 2 and 3 of part's lattice with the right sides they start from: what is exact on the table leaves a level's masks
    before the next one is joined."""
    rel = relation(spark, sf_dir, "part")
    found = all_stats(rel, 2).where("n > 1 and is_exact").groupBy("lhs").agg(F.collect_list("rhs").alias("gone"))
    exact = spark.createDataFrame(found.collect(), "lhs array<int>, gone array<int>")  # a row for each left side of one or two
    rel.release()

    def pruned(level: DataFrame) -> DataFrame:
        left = lattice.unset("s_mask", F.coalesce("gone", F.array().cast("array<int>")))
        return level.join(exact, "lhs", "left").select("lhs", "prefix", "last", left.alias("s_mask")).where(F.exists("s_mask", lambda w: w != 0))

    every = (1 << rel.m) - 1
    one = lattice.level_frame(spark, lattice.full_level(rel.m, 1, every, every), rel.m)
    two = lattice.next_level_df(pruned(one))
    three = lattice.next_level_df(pruned(two))
    return two.union(three).select(F.array_join("lhs", ",").alias("lhs"), F.col("s_mask")[0].alias("mask"))


# Paradigms and theory.
@query("paradigms_dirty")
def paradigms_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = score.named(r := relation(spark, sf_dir, "dirty"), all_stats(r, 2)).where("n > 1 and not is_exact").persist()
    top = lambda df, label: df.agg(F.lit(label).alias("paradigm"), F.count("*").alias("n_results"), F.round(F.max("mu_plus"), 6).alias("best"))
    parts = [top(s.where(F.col("mu_plus") >= t), f"threshold {t}") for t in (0.5, 0.8, 0.9, 0.95)]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3]).union(top(s.where("rhs = 'market'").orderBy(F.desc("mu_plus")).limit(10), "fixed market")).union(top(s.orderBy(F.desc("mu_plus")).limit(20), "global"))


for _mode in ("literal", "scored"):
    QUERIES[f"minimal_{_mode}_dirty"] = lambda s, d, m=_mode: theory.minimal_only(non_exact(r := relation(s, d, "dirty"), 2), m, 0.9).select(names_of(r, "lhs"), name_of(r, "rhs"), r6("mu_plus"))


@query("properties_dirty")
def properties_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "dirty")
    scores = non_exact(rel, 2).persist()
    rows = []
    for keep in ("P2P3", "P1P3", "P1P2"):
        p = theory.check_properties(theory.enforce(scores, 2, keep), scores, 2)
        rows.append((keep, p.minimal, p.top_k, p.exactly_k))
    return spark.createDataFrame(rows, "kept string, minimal boolean, top_k boolean, exactly_k boolean")


@query("incompatibility_dirty")
def incompatibility_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "dirty")
    w = theory.incompatibility_witness(non_exact(rel, 2).persist())
    return w.select(name_of(rel, "rhs"), names_of(rel, "small"), names_of(rel, "large"), r6("low"), r6("high"), names_of(rel, "other_lhs"), name_of(rel, "other_rhs"), r6("other"))


@query("growth_pairs_dirty")
def growth_pairs_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "dirty")
    return theory.growth_chains(non_exact(rel, 2)).select(name_of(rel, "rhs"), names_of(rel, "small"), names_of(rel, "large"), r6("low"), r6("high"))


# Audit.
QUERIES["violations_market"] = lambda s, d: audit.violations(relation(s, d, "dirty"), ["c_nationkey"], "market").select("c_nationkey", "market", "group_size", "rhs_count", "majority", "is_violation", F.round("c_acctbal", 2).alias("c_acctbal"))
QUERIES["repairs_market"] = lambda s, d: audit.suggest_repairs(relation(s, d, "dirty"), ["c_nationkey"], "market").select("c_nationkey", "found", "suggested", "n_rows", r6("support"))


# Depth, cost, scale.
def _lists(spark: SparkSession, sf_dir: str, name: str, depth: int) -> list:
    rel = relation(spark, sf_dir, name)
    return [search(rel, Options(20, k)) for k in range(1, depth + 1)]


@query("depth_overlap_dirty")
def depth_overlap_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = [{(x, a) for _, x, a, _ in f.entries} for f in _lists(spark, sf_dir, "dirty", 3)]
    return spark.createDataFrame([(k + 1, 100.0 * len(a & b) / 20) for k, (a, b) in enumerate(zip(found, found[1:], strict=False))], "max_lhs int, overlap double")


@query("depth_tau_dirty")
def depth_tau_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    taus = [(k + 1, f.report.tau_by_level[-1]) for k, f in enumerate(_lists(spark, sf_dir, "dirty", 3))]
    df = spark.createDataFrame(taus, "max_lhs int, tau double")
    step = F.col("tau") - F.lag("tau").over(Window.orderBy("max_lhs"))  # a row for each depth
    return df.select("max_lhs", r6("tau"), F.round(step, 6).alias("increment"))


@query("ecn_report_orders")
def ecn_report_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    rel = relation(spark, sf_dir, "orders")
    frames = [search(rel, Options(20, 5, v)).report.frame(spark) for v in ("V0", "V3", "V4")]
    w = Window.partitionBy("variant").orderBy("level").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return reduce(DataFrame.union, frames).select("variant", "level", "ecn", F.sum("ecn").over(w).alias("running_ecn"), "exact", "bound_pruned", r6("tau"), r6("pruning_ratio"))


@query("scale_rows_lineitem")
def scale_rows_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All columns of growing parts of lineitem: how many dependencies are exact, the best other score, and their sum."""
    li = load(spark, sf_dir, "lineitem").withColumn("bucket", (F.col("l_orderkey") * 31 + F.col("l_linenumber")) % 10)
    rows = []
    for tenths in (1, 2, 4, 6, 8, 10):
        rel = Relation.of(li.where(F.col("bucket") < tenths).drop("bucket"))
        best = F.round(F.max(F.when(~F.col("is_exact"), F.col("mu_plus"))), 6)
        part = all_stats(rel, 1).agg(F.max("n"), F.sum(F.col("is_exact").cast("long")), best, F.round(F.sum("mu_plus"), 6))
        rows.append((tenths, *part.first()))
        rel.release()  # one part's codes at a time
    return spark.createDataFrame(rows, "tenths int, n long, exact long, best double, total double")


@query("cost_model_table")
def cost_model_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cost model at depth 3 for the first m signs of the embeddings. n is the tuples that a search visits when equal ones
    are kept once."""
    bits = sign_bits(load(spark, sf_dir, "embeddings"), 20)
    rows = []
    for m in (5, 10, 20):
        rel = Relation.of(bits.select(*bits.columns[:m]), collapse=True)
        rows += [(v, m, rel.size, *report.cost_model(m, rel.size, 3, v).values()) for v in ("V0", "V1", "V2")]
        rel.release()
    return spark.createDataFrame(rows, "variant string, m int, n long, row_scans long, lhs_key_evaluations long, heap_operations long, mask_words long")


# Aggregation, joins, windows, streams.
QUERIES["null_patterns_doc"] = lambda s, d: joint.null_patterns(relation(s, d, "doc")).select(F.col("null_mask")[0].alias("null_mask"), "n")


@query("null_patterns_bits")
def null_patterns_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of 65 columns, in which every negative sign is a NULL: how many rows have each number of them."""
    df = sign_bits(load(spark, sf_dir, "embeddings"), 64)
    rel = Relation.of(df.select(*(F.when(F.col(c) == 1, 1).alias(c) for c in df.columns if c != "label"), "label"))
    ones = F.aggregate("null_mask", F.lit(0), lambda a, w: a + F.bit_count(w))
    return joint.null_patterns(rel).groupBy(ones.cast("long").alias("nulls")).agg(F.sum("n").alias("n"))


for _name, _kernel in (("joint", "joint"), ("shared", "lhs_shared"), ("each", "candidate")):
    QUERIES[f"scores_l1_{_name}_kernel"] = lambda s, d, k=_kernel: score.named(r := relation(s, d, "part"), score.statistics(r, list(lattice.enumerate_candidates(r.m, 1)), k)).select("lhs", "rhs", "n", "d_lhs", "d_joint", r6("mu_plus"), "is_exact")
QUERIES["scores_l1_many_blocks"] = lambda s, d: _many_blocks(relation(s, d, "doc"))


def _many_blocks(rel: Relation) -> DataFrame:
    """The score table from counts in blocks of a tenth of the relation."""
    cands = list(enumerate(lattice.enumerate_candidates(rel.m, 1)))
    return score_frame(rel, blocks.block_counts(rel, cands, block_rows=max(2, rel.size // 10)), cands)


def score_frame(rel: Relation, counted: DataFrame, cands: list) -> DataFrame:
    listed = rel.df.sparkSession.createDataFrame([(i, list(x), a) for i, (x, a) in cands], "cid int, lhs array<int>, rhs int")
    n = F.col("n")
    mu = measures.mu_plus(n, F.col("d_lhs"), F.col("disagree_lhs"), F.col("disagree_rhs"))
    return score.named(rel, listed.join(counted, "cid")).where("n > 1").select("lhs", "rhs", "n", "d_lhs", "d_joint", F.round(mu, 6).alias("mu_plus"), (F.col("d_joint") == F.col("d_lhs")).alias("is_exact"))
QUERIES["joint_table_doc"] = lambda s, d: joint.joint_table(relation(s, d, "doc"), ["lang", "quality", "toxic"])
QUERIES["grouping_sets_part"] = lambda s, d: load(s, d, "part").groupingSets([["p_brand"], ["p_type"], ["p_brand", "p_type"]], "p_brand", "p_type").agg(F.count("*").alias("f"), F.grouping_id().cast("long").alias("gid"))
QUERIES["cube_part"] = lambda s, d: load(s, d, "part").cube("p_brand", "p_type").agg(F.count("*").alias("f"), F.max("p_size").alias("max_size"))
QUERIES["rollup_orders"] = lambda s, d: load(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("f"), F.round(F.sum("o_totalprice"), 2).alias("total"))
QUERIES["asof_prev_event"] = lambda s, d: temporal.previous_value(load(s, d, "events"), "user_id", "ts", "event_type", "prev_type").select("event_id", "user_id", "prev_type")


@query("asof_last_purchase")
def asof_last_purchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    kind = e.agg(F.min("event_type")).first()[0]
    right = e.where(F.col("event_type") == kind).select("user_id", F.col("ts").alias("seen_ts"), F.col("event_id").alias("seen_id"))
    return temporal.asof_join(e.select("event_id", "user_id", "ts"), right, "user_id", "ts", "seen_ts", ["seen_id"]).select("event_id", "seen_id")


@query("interval_join_events")
def interval_join_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    earlier = e.select(F.col("event_id").alias("earlier_id"), "user_id", F.col("ts").alias("earlier_ts"))
    return temporal.interval_join(e, earlier, "user_id", "ts", "earlier_ts", 6 * 3600).select("event_id", "earlier_id")


WATCHED = (("event_type",), "k")


def _watched_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select("event_id", "ts", "event_type", F.from_json("props", "k int")["k"].alias("k"))


TIME = "yyyy-MM-dd HH:mm:ss"


def _window_rows(df: DataFrame) -> DataFrame:
    return df.select(F.date_format("start", TIME).alias("start"), F.date_format("end", TIME).alias("end"), "n", "d_lhs", "d_joint", r6("mu_plus"))


QUERIES["windowed_scores_events"] = lambda s, d: _window_rows(stream_audit.windowed_scores(_watched_events(s, d), WATCHED))
QUERIES["sliding_scores_events"] = lambda s, d: _window_rows(stream_audit.windowed_scores(_watched_events(s, d), WATCHED, window="2 days", slide="1 day"))
QUERIES["session_scores_events"] = lambda s, d: _window_rows(stream_audit.windowed_scores(_watched_events(s, d), WATCHED, session_gap="20 minutes"))


@query("stream_counts_events")
def stream_counts_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = load(spark, sf_dir, "events").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    watched = stream.select("ts", "event_type", F.from_json("props", "k int")["k"].alias("k"))
    stream_audit.stream_counts(watched, WATCHED, f"{base}/counts", f"{base}/state").awaitTermination()
    return stream_audit.merged_counts(spark, f"{base}/counts")


@query("rank_by_rhs_dirty")
def rank_by_rhs_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = score_table(relation(spark, sf_dir, "dirty"), 2).where("n > 1 and not is_exact")
    w = Window.partitionBy("rhs").orderBy(F.desc("mu_plus"))
    each = Window.partitionBy("rhs").orderBy(F.desc("mu_plus"), "lhs")
    return s.select("lhs", "rhs", "mu_plus", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 6).alias("percent"), F.ntile(4).over(each).alias("quarter"))


@query("contingency_dirty")
def contingency_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The joint counts of a dependency as a table of left by right values."""
    df = relation(spark, sf_dir, "dirty").df
    markets = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST", "OTHER"]
    return df.groupBy("c_nationkey").pivot("market", markets).agg(F.count("n_name")).select("c_nationkey", *(F.coalesce(F.col(f"`{m}`"), F.lit(0)).alias(m.lower().replace(" ", "_")) for m in markets))


@query("result_identity_dirty")
def result_identity_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether each variant's list is that of the exhaustive search."""
    rel = relation(spark, sf_dir, "dirty")
    lists = {v: search(rel, Options(20, 3, v)).frame() for v in ("V0", "V1", "V2", "V3", "V4")}
    return spark.createDataFrame([(v, report.same_result(lists["V0"], x)) for v, x in lists.items()], "variant string, same boolean")


@query("lattice_tables_dirty")
def lattice_tables_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A search whose levels after the first are tables."""
    return joined(search(relation(spark, sf_dir, "dirty"), Options(20, 3, lattice_rows=0)).frame())


@query("sentence_dirty")
def sentence_dirty(spark: SparkSession, sf_dir: str) -> DataFrame:
    relation(spark, sf_dir, "dirty").df.createOrReplaceTempView("softdep_dirty")
    found = sqlfront.sql(spark, "DISCOVER TOP 10 DEPENDENCIES FROM softdep_dirty MAX LHS 2 FOR market ABOVE 0.5")
    return found.select(F.array_join("lhs", ",").alias("lhs"), "rhs", F.round("score", 6).alias("mu_plus"))


# Workloads: all columns of their results but the seconds.
def _rounded(df: DataFrame) -> DataFrame:
    return df.drop("seconds").withColumns({c: F.round(c, 6) for c in ("pruning_ratio", "tau") if c in df.columns})


for _name in workloads.DEPTH:
    QUERIES[f"overall_{_name}"] = lambda s, d, n=_name: _rounded(workloads.overall(s, d, (n,), shared=True))
for _name in workloads.SWEEP:
    QUERIES[f"workload_depth_{_name}"] = lambda s, d, n=_name: _rounded(workloads.depth(s, d, (n,), shared=True))
for _name in workloads.ABLATION:
    QUERIES[f"workload_ablation_{_name}"] = lambda s, d, n=_name: _rounded(workloads.ablation(s, d, (n,)))
QUERIES["workload_scale_rows"] = lambda s, d: _rounded(workloads.scale_rows(s, d, shared=True))
QUERIES["workload_scale_columns"] = lambda s, d: workloads.scale_columns(s, d).select("name", "variant", "m", "n", "ecn", "exact", "n_results")
QUERIES["workload_scale_columns_wide"] = lambda s, d: _rounded(workloads.scale_columns_wide(s, d, shared=True))
QUERIES["workload_scale_k"] = lambda s, d: _rounded(workloads.scale_k(s, d))
QUERIES["workload_null_bound"] = lambda s, d: _rounded(workloads.null_bound(s, d))
QUERIES["workload_paradigms"] = lambda s, d: workloads.paradigms(s, d).withColumn("best", F.round("best", 6))
QUERIES["workload_case_study"] = lambda s, d: workloads.case_study(s, d).withColumns({"mu_plus": F.round("mu_plus", 6), "rhs_per_rank": F.round("rhs_per_rank", 6)})
