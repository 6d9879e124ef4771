"""Reply trees to training conversations.

Messages name their parent. Self-joins that double the jump each time find every message's distance from its root and the
score of the branch above it (log2 of the depth joins, not depth joins). Leaves are ranked inside their tree by mean
score; for each chosen leaf the same jump tables list the path from root to leaf, and each path becomes one conversation.

Template: <|im_start|>role\\ntext<|im_end|>\\n for each turn. A control string inside a text starts with <|; escaping puts
one more backslash between < and | of every <\\...\\|, and taking one away again undoes it. In a role, backslashes and line
feeds are escaped too. The loss mask holds the code-point spans of the assistants' (escaped) texts.

Edge cases. Null roles and texts are empty. A message whose parent is null, absent or itself is a root. Messages on a
cycle have no root and belong to no path; rootless() returns them. Repeated ids of one tree make repeated paths of equal
text, so ids should be unique: conversations() numbers rows by turn, role and text. Branches of equal score rank by depth,
then by the smaller leaf. A null tree id is one tree. Very long texts stay whole. Only the columns named below are read, so
others cannot clash. An empty table gives no conversation.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from softdep.llm._store import written

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def escaped(text: Column) -> Column:
    return F.regexp_replace(text, r"<(\\*)\|", r"<$1\\|")


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\(\\*)\|", "<$1|")


def escaped_role(role: Column) -> Column:
    return escaped(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def unescaped_role(role: Column) -> Column:
    plain = F.regexp_replace(unescaped(role), r"(?<!\\)((?:\\\\)*)\\n", "$1\n")
    return F.replace(plain, F.lit("\\\\"), F.lit("\\"))


@dataclass(frozen=True)
class Forest:
    """messages: tree, id, parent, score, role, text. jumps[k]: (tree, id, up), up being 2^k levels above id.
    reach: (tree, id, up, depth, total); up is null where the root was reached. tree is a struct of the messages' tree."""

    messages: DataFrame
    jumps: list[DataFrame]
    reach: DataFrame


def forest(messages: DataFrame) -> Forest:
    """The jump tables of messages(tree, id, parent, score, role, text)."""
    # A struct of a null is no null, so that the null tree joins like any other.
    m = written(messages.select(F.struct(F.col("tree").alias("v")).alias("tree"), "id", F.when(F.col("parent") != F.col("id"), F.col("parent")).alias("parent"), "score", "role", "text"), "messages")
    ids = m.select("tree", F.col("id").alias("parent")).distinct().withColumn("there", F.lit(True))
    size = m.groupBy("tree").count().agg(F.max("count")).first()[0] or 0
    reach = m.select("tree", "id", "parent", "score").join(ids, ["tree", "parent"], "left").select("tree", "id", F.when(F.col("there"), F.col("parent")).alias("up"), F.lit(1).cast("long").alias("depth"), F.coalesce(F.col("score"), F.lit(0.0)).cast("double").alias("total"))
    step = 1
    reach = written(reach, "reach")
    done, jumps = reach.where("up is null"), []
    while step <= size and not reach.where("up is not null").isEmpty():
        # Only messages that have not met their root yet are joined again.
        ahead = reach.where("up is not null")
        jumps.append(ahead.select("tree", "id", "up"))
        above = done.unionByName(ahead).select("tree", F.col("id").alias("up"), F.col("up").alias("__up"), F.col("depth").alias("__depth"), F.col("total").alias("__total"))
        reach = written(ahead.join(above, ["tree", "up"]).select("tree", "id", F.col("__up").alias("up"), (F.col("depth") + F.col("__depth")).alias("depth"), (F.col("total") + F.col("__total")).alias("total")), "reach")
        done = done.unionByName(reach.where("up is null"))
        step *= 2
    return Forest(m, jumps, done.unionByName(reach.where("up is not null")))


def rootless(f: Forest) -> DataFrame:
    """Messages on or below a cycle."""
    return f.reach.where("up is not null").select("tree.v", "id").withColumnRenamed("v", "tree")


def branches(f: Forest, best: int | None = 1) -> DataFrame:
    """(tree, leaf, depth, score, rank) of the best leaves of each tree (None: all), by mean score, depth, then id."""
    parents = f.messages.where("parent is not null").select("tree", F.col("parent").alias("id")).distinct()
    leaves = f.reach.where("up is null").join(parents, ["tree", "id"], "left_anti").select("tree", F.col("id").alias("leaf"), "depth", (F.col("total") / F.col("depth")).alias("score"))
    ranked = leaves.withColumn("rank", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("score"), F.desc("depth"), "leaf")))
    return (ranked if best is None else ranked.where(F.col("rank") <= best)).withColumn("tree", F.col("tree.v"))


def paths(f: Forest, chosen: DataFrame) -> DataFrame:
    """(tree, leaf, rank, pos, role, text) of every message from the root (pos 0) to each chosen leaf."""
    out = chosen.select(F.struct(F.col("tree").alias("v")).alias("tree"), "leaf", "rank", "depth", F.col("leaf").alias("id"), F.lit(0).cast("long").alias("above"))
    for k, jump in enumerate(f.jumps):
        out = out.unionByName(out.join(jump, ["tree", "id"]).select("tree", "leaf", "rank", "depth", F.col("up").alias("id"), (F.col("above") + 2**k).alias("above")))
        out = written(out, "path") if k % 3 == 2 else out
    return out.join(f.messages.select("tree", "id", "role", "text"), ["tree", "id"]).select(F.col("tree.v").alias("tree"), "leaf", "rank", (F.col("depth") - 1 - F.col("above")).alias("pos"), "role", "text")


def formatted(path_rows: DataFrame, trained: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """(tree, leaf, rank, formatted, loss_spans) of each path; a span is a start and an end in code points."""
    turn = F.struct("pos", escaped_role(F.coalesce("role", F.lit(""))).alias("r"), escaped(F.coalesce("text", F.lit(""))).alias("t"), F.coalesce(F.col("role").isin(*trained), F.lit(False)).alias("m"))
    g = path_rows.groupBy("tree", "leaf", "rank").agg(F.array_sort(F.collect_list(turn)).alias("turns"))
    head = lambda x: F.concat(F.lit(OPEN), x["r"], F.lit("\n"))
    text = F.array_join(F.transform("turns", lambda x: F.concat(head(x), x["t"], F.lit(CLOSE + "\n"))), "")
    spans = F.aggregate(
        "turns",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("s")),
        lambda a, x: F.struct(
            (a["at"] + F.length(head(x)) + F.length(x["t"]) + len(CLOSE) + 1).alias("at"),
            F.when(x["m"], F.concat(a["s"], F.array(F.struct((a["at"] + F.length(head(x))).alias("start"), (a["at"] + F.length(head(x)) + F.length(x["t"])).alias("end"))))).otherwise(a["s"]).alias("s"),
        ),
        lambda a: a["s"],
    )
    return g.select("tree", "leaf", "rank", text.alias("formatted"), spans.alias("loss_spans"))


def read_turns(text: Column) -> Column:
    """array<struct<role, text>> read back from a formatted conversation."""
    pieces = F.filter(F.split(text, r"<\|im_end\|>\n"), lambda p: p != "")
    body = lambda p: F.substring(p, len(OPEN) + 1, F.length(p))
    return F.transform(pieces, lambda p: F.struct(unescaped_role(F.substring_index(body(p), "\n", 1)).alias("role"), unescaped(F.substring(body(p), F.instr(body(p), "\n") + 1, F.length(p))).alias("text")))


def read_loss(text: Column, spans: Column) -> Column:
    """The unescaped text under the loss mask, span after span."""
    return F.array_join(F.transform(spans, lambda s: unescaped(F.substring(text, s["start"] + 1, s["end"] - s["start"]))), "")


def conversations(rows: DataFrame) -> DataFrame:
    """Messages of the forest from rows(conv_id, turn, role, text): each row replies to the one before it."""
    pos = F.row_number().over(Window.partitionBy("conv_id").orderBy("turn", "role", "text")).cast("long")
    m = rows.select(F.col("conv_id").alias("tree"), pos.alias("id"), "role", "text")
    return m.select("tree", "id", F.when(F.col("id") > 1, F.col("id") - 1).alias("parent"), F.length("text").cast("double").alias("score"), "role", "text")
