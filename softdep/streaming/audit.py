"""Fixed dependencies watched on a stream: joint counts are additive, scores come from the merged counts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from softdep.functions import measures

Watched = tuple[tuple[str, ...], str]


def timed(events: DataFrame, ts: str) -> DataFrame:
    """Event times without zone become instants, as watermarks need them."""
    return events.withColumn(ts, F.col(ts).cast("timestamp"))


def joint_counts(events: DataFrame, ad: Watched, by: list | None = None) -> DataFrame:
    """(by..., lhs_key, rhs_value, f) of an AD over a batch or a stream; NULLs are left out."""
    lhs, rhs = ad
    whole = events.where(" and ".join(f"`{c}` is not null" for c in (*lhs, rhs)))
    key = F.to_json(F.struct(*lhs))
    return whole.groupBy(*(by or []), key.alias("lhs_key"), F.col(rhs).cast("string").alias("rhs_value")).agg(F.count("*").alias("f"))


def scored(counts: DataFrame, by: list[str]) -> DataFrame:
    """(by..., n, d_lhs, d_joint, mu_plus) from joint counts."""
    left = counts.groupBy(*by, "lhs_key").agg(F.sum("f").alias("s"), F.sum(F.col("f").cast("double") * F.col("f")).alias("q"), F.count("*").alias("k"))
    x = left.groupBy(*by).agg(F.sum("s").alias("n"), F.count("*").alias("d_lhs"), F.sum("k").alias("d_joint"), F.sum(F.when(F.col("k") > 1, F.col("s") - F.col("q") / F.col("s")).otherwise(0.0)).alias("dis"))
    right = counts.groupBy(*by, "rhs_value").agg(F.sum("f").alias("s")).groupBy(*by).agg(F.sum(F.col("s").cast("double") * F.col("s")).alias("sq"), F.count("*").alias("d_rhs"))
    both = x.join(right, by) if by else x.withColumn("one", F.lit(1)).join(right.withColumn("one", F.lit(1)), "one").drop("one")
    n = F.col("n").cast("double")
    dis_a = F.when(F.col("d_rhs") == 1, 0.0).otherwise(1 - F.col("sq") / n / n)
    return both.select(*by, "n", "d_lhs", "d_joint", F.when(F.col("n") > 1, measures.mu_plus(n, F.col("d_lhs"), F.col("dis") / n, dis_a)).alias("mu_plus"))


def sessions(events: DataFrame, ts: str, gap: str) -> DataFrame:
    """(slot, start, end): the session of each time slot as long as the gap that has a row. Rows of a slot are of one session,
    so that sessions follow from the first and last time of each slot: the one ordered pass is over slots, of which there
    are as many as the time span has gaps, whatever the number of rows."""
    micros = F.unix_micros(F.timestamp_micros(F.lit(0)) + F.expr(f"interval {gap}"))
    slots = events.select(F.unix_micros(F.col(ts).cast("timestamp")).alias("t"), micros.alias("gap")).where("t is not null")
    slots = slots.groupBy(F.floor(F.col("t") / F.col("gap")).alias("slot"), "gap").agg(F.min("t").alias("a"), F.max("t").alias("b"))
    in_order = Window.orderBy("slot")
    fresh = slots.withColumn("fresh", F.when(F.col("a") - F.lag("b").over(in_order) <= F.col("gap"), 0).otherwise(1))
    numbered = fresh.withColumn("sid", F.sum("fresh").over(in_order))
    bounds = numbered.groupBy("sid").agg(F.min("a").alias("a"), (F.max("b") + F.max("gap")).alias("b"))
    return numbered.select("sid", "slot").join(bounds, "sid").select("slot", F.timestamp_micros("a").alias("start"), F.timestamp_micros("b").alias("end"))


def windowed_scores(events: DataFrame, ad: Watched, ts: str = "ts", window: str = "1 day", slide: str | None = None, session_gap: str | None = None) -> DataFrame:
    """Scores by tumbling, sliding or session window, of a batch. A stream uses stream_counts with a window, which counts each
    batch's finished windows. Session windows here are those of all rows, not of one key."""
    if session_gap:
        w = sessions(events, ts, session_gap)
        gap = F.unix_micros(F.timestamp_micros(F.lit(0)) + F.expr(f"interval {session_gap}"))
        # Counted by slot first, so that the join is of few rows.
        by_slot = joint_counts(events.withColumn("slot", F.floor(F.unix_micros(F.col(ts).cast("timestamp")) / gap)), ad, ["slot"])
        counts = by_slot.join(w, "slot").groupBy("start", "end", "lhs_key", "rhs_value").agg(F.sum("f").alias("f"))
    else:
        counts = joint_counts(events.withColumn("__w", F.window(ts, window, slide)), ad, [F.col("__w.start").alias("start"), F.col("__w.end").alias("end")])
    return scored(counts, ["start", "end"])


def stream_counts(stream: DataFrame, ad: Watched, table: str, checkpoint: str, watermark: str | None = None, ts: str = "ts", window: str | None = None):
    """A started query that writes joint counts to a folder for each batch: of the batch's rows, which merged_counts adds up
    (counts are additive, so no state is kept), or of the windows that the watermark has closed. A batch that runs again
    replaces its folder. Trigger: what is there now."""

    def put(batch: DataFrame, number: int) -> None:
        if window:
            counts = batch.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "lhs_key", "rhs_value", "f")
        else:
            counts = joint_counts(batch, ad)
        counts.write.mode("overwrite").parquet(f"{table}/batch={number}")

    if window:
        closed = joint_counts(timed(stream, ts).withWatermark(ts, watermark or "0 seconds").withColumn("__w", F.window(ts, window)), ad, [F.col("__w").alias("w")])
        writer = closed.writeStream.outputMode("append")
    else:
        writer = stream.writeStream
    return writer.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(put).start()


def merged_counts(spark: SparkSession, table: str) -> DataFrame:
    """(lhs_key, rhs_value, f) over all batches of stream_counts without a window."""
    return spark.read.parquet(table).groupBy("lhs_key", "rhs_value").agg(F.sum("f").alias("f"))


def deduplicated(stream: DataFrame, key: str = "event_id", ts: str = "ts", watermark: str = "1 day") -> DataFrame:
    return timed(stream, ts).withWatermark(ts, watermark).dropDuplicatesWithinWatermark([key])


def violation_alerts(stream: DataFrame, lhs: str, rhs: str) -> DataFrame:
    """(lhs, found, majority, n): rows whose right value is not the left value's majority so far, by a count of each right
    value kept as state for each left value."""

    def watch(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        values, counts = (list(x) for x in state.get) if state.exists else ([], [])
        held = dict(zip(values, counts, strict=True))
        out = []
        for f in frames:
            for v in f[rhs].dropna().astype(str):
                held[v] = held.get(v, 0) + 1
                top = min(held, key=lambda x: (-held[x], x))
                if v != top:
                    out.append((str(key[0]), v, top, sum(held.values())))
        state.update((list(held), list(held.values())))
        yield pd.DataFrame(out, columns=["lhs", "found", "majority", "n"])

    return stream.groupBy(lhs).applyInPandasWithState(watch, "lhs string, found string, majority string, n long", "values array<string>, counts array<long>", "append", "NoTimeout")


def dropped_by_watermark(query) -> int:
    """Late rows that a started query has dropped so far."""
    return sum(int(o.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for o in p["stateOperators"])
