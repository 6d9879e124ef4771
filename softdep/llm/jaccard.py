"""Exact self-join of documents on the Jaccard similarity of their word shingles, by a token-group matrix.

1. Sets. Texts are dealt into chunks by a hash; a chunk makes the sets of distinct shingle hashes. Documents of equal sets
   form a class, and one of them stands for it.
2. Frequencies. A chunk lists its distinct tokens once, as differences of truncated hashes; shards sum the lists and answer
   with a byte for each token. A common token is one entry for each chunk, whatever the number of documents that hold it.
3. Prefixes. If |A n B| >= t |A u B|, then A and B share one of the first |A| - ceil(t |A|) + 1 tokens of either, in any
   fixed order. The order is by frequency, then hash, so a document with that many tokens of its own has no partner, and
   passages that many documents share stay out of the prefixes. Only prefix tokens held by two or more sets go on.
4. Stars. Each token's holders are compared with one of them, those left alone with a few more; what is alike falls
   together. Large families of near copies mostly become one component here, with few comparisons for each member.
5. Matrix. Documents that share prefix tokens with other components are put in groups of similar ones (equal most
   frequent prefix token, some tens each); a group stores the union of its members' tokens, and the matrix says which tokens it has.
   Where two groups share a token, one's members query the other: t / (1 + t) * (|Q| + least size in the group) tokens of Q
   must be in the union for any partner there. Only then the group is opened, to those of its members that may in turn have
   a partner in Q's group, and they are compared exactly.
No link is lost: two similar sets share a prefix token, so they are in one component already or meet in step 5.

Edge cases. Null, empty and blank texts have an empty set and link with nothing. A text of fewer words than a shingle is
one token. Repeated rows are counted before they are dealt, and are one class. A document is a row: rows of one id but unlike
texts are of different components, unless the texts link. A class without an id, or whose smallest id is also that of
another class, goes by a number of its own above all ids; a component is named by the smallest id in it, or null. Of equally
frequent tokens the smaller hash comes first. A chunk holds whole texts, so a very long one makes a long chunk. Columns other
than id and text are not read. An empty table gives no rows. Tokens are 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.llm._store import collapsed, written
from softdep.llm._text import lowered, mixed, pieces, shingles, spans, word_hashes
from softdep.llm.graph import components
from softdep.llm.lm import _planes, _unplaned

U64 = np.uint64


def sets_of(texts: pa.Array, size: int = 5) -> list[np.ndarray]:
    """Each text's distinct shingle hashes, in order."""
    out: list[np.ndarray] = []
    for _, data, offs in pieces(texts):
        data = lowered(data)
        row, start, end = spans(data, offs)
        r, h = shingles(row, word_hashes(data, start, end), len(offs) - 1, size)
        cuts = np.searchsorted(r, np.arange(1, len(offs) - 1))
        out += [np.unique(x) for x in np.split(h, cuts)]
    return out


def signature(tokens: np.ndarray) -> tuple[int, int]:
    """128 bits of a set."""
    return tuple(int(np.add.reduce(mixed(tokens + U64(k))).astype(np.int64)) if len(tokens) else 0 for k in (0x1234567, 0x7654321))


def prefix_length(n: np.ndarray, percent: int) -> np.ndarray:
    return n - -(-percent * n // 100) + 1


def _described(size: int) -> Callable[[pa.Table], pa.Table]:
    def describe(t: pa.Table) -> pa.Table:
        found = sets_of(t["text"].combine_chunks(), size)
        sigs = [signature(x) for x in found]
        return pa.table({"chunk": t["chunk"], "key": t["key"], "n": pa.array([len(x) for x in found], pa.int64()), "s1": pa.array([s[0] for s in sigs], pa.int64()), "s2": pa.array([s[1] for s in sigs], pa.int64())})

    return describe


def _standing(docs: pa.Table, side: pa.Table, size: int) -> tuple[list[np.ndarray], list[bool]]:
    """The chunk's sets, and which document stands for its class: side holds (key, s1, s2) of those."""
    found = sets_of(docs["text"].combine_chunks(), size)
    left = {(r["key"], r["s1"], r["s2"]) for r in side.select(["key", "s1", "s2"]).to_pylist() if r["s1"] is not None}
    stands = []
    for key, tokens in zip(docs["key"].to_pylist(), found, strict=True):
        me = (key, *signature(tokens))
        stands.append(bool(len(tokens)) and me in left)
        left.discard(me)
    return found, stands


def _listed(found: list[np.ndarray], stands: list[bool], bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct truncated tokens of the standing documents, and by how many they are held."""
    mine = [x >> U64(64 - bits) for x, s in zip(found, stands, strict=True) if s]
    return np.unique(np.concatenate(mine), return_counts=True) if mine else (np.zeros(0, np.uint64), np.zeros(0, np.int64))


def _cuts(tokens: np.ndarray, shards: int, bits: int) -> np.ndarray:
    """Where the ranges of the shards begin and end in sorted tokens."""
    return np.searchsorted(tokens, np.array([(i << bits) // shards for i in range(shards + 1)], np.uint64))


def _told(size: int, shards: int, bits: int) -> Callable[[pa.Table, pa.Table], pa.Table]:
    def tell(docs: pa.Table, side: pa.Table) -> pa.Table:
        rows = []
        if docs.num_rows:
            tokens, held = _listed(*_standing(docs, side, size), bits)
            cut = _cuts(tokens, shards, bits)
            for s in range(shards):
                own = tokens[cut[s] : cut[s + 1]]
                rows.append({"shard": s, "chunk": docs["chunk"][0].as_py(), "gaps": _planes(np.diff(own, prepend=U64(0)), 7), "held": _planes(held[cut[s] : cut[s + 1]], 4)})
        return pa.Table.from_pylist(rows, pa.schema([("shard", pa.int32()), ("chunk", pa.int32()), ("gaps", pa.binary()), ("held", pa.binary())]))

    return tell


def _counted(t: pa.Table) -> pa.Table:
    lists = [(np.cumsum(_unplaned(r["gaps"], 7)), _unplaned(r["held"], 4)) for r in t.to_pylist()]
    tokens, at = np.unique(np.concatenate([x for x, _ in lists]), return_inverse=True)
    total = np.minimum(np.bincount(at, np.concatenate([x for _, x in lists]), len(tokens)), 255).astype(np.uint8)
    codes = np.split(total[at], np.cumsum([len(x) for x, _ in lists])[:-1])
    return pa.table({"chunk": t["chunk"], "shard": t["shard"], "codes": pa.array([c.tobytes() for c in codes], pa.binary())})


def _probes(size: int, percent: int, shards: int, bits: int, kind: pa.DataType) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """Of each document its class; of standing documents that may have partners also the shared prefix tokens and the set."""
    schema = pa.schema([("key", kind), ("mark", pa.int64()), ("times", pa.int64()), ("n", pa.int64()), ("s1", pa.int64()), ("s2", pa.int64()), ("prefix", pa.list_(pa.int64())), ("tokens", pa.list_(pa.int64()))])

    def probe(docs: pa.Table, side: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return schema.empty_table()
        found, stands = _standing(docs, side, size)
        listed, _ = _listed(found, stands, bits)
        cut = _cuts(listed, shards, bits)
        often = np.zeros(len(listed), np.uint8)
        for r in side.select(["shard", "codes"]).to_pylist():
            if r["codes"] is not None:
                often[cut[r["shard"]] : cut[r["shard"] + 1]] = np.frombuffer(r["codes"], np.uint8)
        sigs, prefixes, sets = [], [], []
        for tokens, stand in zip(found, stands, strict=True):
            sigs.append(signature(tokens))
            shared = np.zeros(0, np.uint64)
            if stand:
                f = often[np.searchsorted(listed, tokens >> U64(64 - bits))]
                p = int(prefix_length(np.array(len(tokens)), percent))
                if (f == 1).sum() < p:
                    first = np.lexsort((tokens, f))[:p]
                    shared = tokens[first][f[first] > 1]
            prefixes.append(shared.astype(np.int64) if len(shared) else None)
            sets.append(tokens.astype(np.int64) if len(shared) else None)
        return pa.table([docs["key"], docs["mark"], docs["times"], pa.array([len(x) for x in found], pa.int64()), pa.array([s[0] for s in sigs], pa.int64()), pa.array([s[1] for s in sigs], pa.int64()), pa.array(prefixes, pa.list_(pa.int64())), pa.array(sets, pa.list_(pa.int64()))], schema=schema)

    return probe


def probes(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 5, percent: int = 80, chunk_chars: int = 8_000_000) -> DataFrame:
    """(key, mark, times, n, s1, s2, prefix, tokens) of the documents, as a written table (steps 1 to 3). Rows of equal key
    and text are one, times says how many; mark is xxhash64 of the text."""
    rows = collapsed(docs, key, text)
    chars = rows.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    chunks = int(chars // chunk_chars) + 1
    shards, bits = chunks // 2 + 1, min(54, max(20, int(chars).bit_length() + 12))
    kind = dict(rows.dtypes)["key"]
    number = F.pmod(F.xxhash64("key", "text"), F.lit(chunks)).cast("int")
    dealt = rows.select("key", "text", F.xxhash64("text").alias("mark"), "times", number.alias("chunk")).repartition(chunks, "chunk")
    info = dealt.groupBy("chunk").applyInArrow(_described(size), f"chunk int, key {kind}, n long, s1 long, s2 long")
    standing = info.where("n > 0").groupBy("n", "s1", "s2").agg(F.min(F.struct(F.col("key").isNull(), "key", "chunk")).alias("r")).select("r.chunk", "r.key", "s1", "s2")
    told = dealt.groupBy("chunk").cogroup(standing.groupBy("chunk")).applyInArrow(_told(size, shards, bits), "shard int, chunk int, gaps binary, held binary")
    codes = told.groupBy("shard").applyInArrow(_counted, "chunk int, shard int, codes binary")
    side = standing.unionByName(codes, allowMissingColumns=True)
    arrow_kind = pa.int64() if kind == "bigint" else pa.int32() if kind == "int" else pa.string()
    out = dealt.groupBy("chunk").cogroup(side.groupBy("chunk")).applyInArrow(_probes(size, percent, shards, bits, arrow_kind), f"key {kind}, mark long, times long, n long, s1 long, s2 long, prefix array<long>, tokens array<long>")
    return written(out, "probes")


def _alike(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets are similar, by exact comparison."""
    x = sets.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("tokens").alias("ta"))
    y = sets.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("tokens").alias("tb"))
    both = F.size(F.array_intersect("ta", "tb"))
    return pairs.join(x, "a").join(y, "b").where(100 * both >= percent * (F.col("na") + F.col("nb") - both)).select("a", "b")


def _sizes_fit(na: str, nb: str, percent: int) -> F.Column:
    return (100 * F.col(na) >= percent * F.col(nb)) & (100 * F.col(nb) >= percent * F.col(na))


def named(probed: DataFrame) -> DataFrame:
    """(n, s1, s2, key, members, id) of each class, as a written table: its smallest key, its number of rows, and an id that
    no other class has: the key, or where another class has that too, or there is none, one above all keys made from the
    signature."""
    kind = dict(probed.dtypes)["key"]
    each = probed.where("n > 0").groupBy("n", "s1", "s2").agg(F.min("key").alias("key"), F.sum("times").alias("members"))
    twice = each.where("key is not null").groupBy("key").agg(F.count("*").alias("c")).where("c > 1").select(F.col("key").alias("again"))
    top = probed.agg(F.max("key")).first()[0]
    if kind == "string":
        own = F.concat(F.lit(top or ""), F.lit("\x00"), F.sha2(F.concat_ws(" ", "n", "s1", "s2"), 256))
    else:
        top = max(top or 0, 0)
        own = F.lit(top) + 1 + F.pmod(F.xxhash64("n", "s1", "s2"), F.lit(max((1 << 63) - 2 - top, 1)))
    mine = F.col("key").cast("string" if kind == "string" else "long")
    joined = each.join(twice, F.col("key") == F.col("again"), "left")
    return written(joined.select("n", "s1", "s2", "key", "members", F.when(F.col("key").isNotNull() & F.col("again").isNull(), mine).otherwise(own).alias("id")), "named")


def linked(probed: DataFrame, classes_: DataFrame, percent: int = 80, stars: tuple[int, ...] = (1, 3, 8, 16), group_size: int = 16) -> DataFrame:
    """(id, component) of the standing documents that link with others (steps 4 and 5)."""
    asking = probed.where("prefix is not null")
    if classes_.where("key is null or key != id").isEmpty():
        asking = asking.withColumn("id", F.col("key").cast(dict(classes_.dtypes)["id"]))
    else:
        asking = asking.join(classes_.select("n", "s1", "s2", "id"), ["n", "s1", "s2"])
    sets = written(asking.select("id", "n", "prefix", "tokens"), "sets")
    holds = written(sets.select("id", "n", F.explode("prefix").alias("token")), "holds")
    edges, seed = None, 0
    for many in stars:
        # After the first round only documents without a link ask, more centres at a time.
        asks = holds if edges is None else holds.join(edges.select(F.col("a").alias("id")).union(edges.select("b")).distinct(), "id", "left_anti")
        lead = lambda k: F.min(F.struct(F.xxhash64("id", F.lit(k)).alias("h"), F.col("id").alias("a"), F.col("n").alias("na")))
        centres = holds.groupBy("token").agg(F.array(*(lead(seed + k) for k in range(many))).alias("c"), F.count("*").alias("held")).where("held > 1").select("token", F.explode(F.array_distinct(F.transform("c", lambda x: F.struct(x["a"].alias("a"), x["na"].alias("na"))))).alias("c"))
        star = asks.join(centres, "token").where((F.col("id") != F.col("c.a")) & _sizes_fit("c.na", "n", percent)).select("c.a", F.col("id").alias("b")).distinct()
        found = _alike(star if edges is None else star.join(edges, ["a", "b"], "left_anti"), sets, percent)
        edges = written(found if edges is None else edges.union(found), "stars")
        seed += many
    comp = written(components(edges), "components")
    of = holds.join(comp, "id", "left").select("token", "id", "n", F.coalesce("component", "id").alias("component"))
    mixed_tokens = of.groupBy("token").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("held")).where("lo != hi").select("token", "held")
    open_ = written(of.join(mixed_tokens, "token"), "open")
    # Groups: documents of the same most frequent prefix token, split into parts of about group_size; a component of that size
    # or more has groups of its own, smaller ones share them.
    least = open_.groupBy("id", "component", "n").agg(F.max(F.struct("held", "token"))["token"].alias("root"))
    sizes = least.groupBy("component").agg(F.count("*").alias("comp_size"))
    rooted = least.join(sizes, "component").withColumn("gc", F.when(F.col("comp_size") >= group_size, F.col("component"))).withColumn("pool", F.struct("gc", "root"))
    # A pool may be large: its number of members goes to sixteen places, its documents to one of these each.
    parts = rooted.groupBy("pool").agg(F.count("*").alias("members")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(15))))
    salted = rooted.withColumn("salt", F.pmod(F.xxhash64("id", F.lit(5)), F.lit(16)).cast("int"))
    member = written(salted.join(parts, ["pool", "salt"]).select("id", "n", "component", "gc", F.xxhash64("pool", F.pmod(F.xxhash64("id"), F.ceil(F.col("members") / group_size))).alias("grp")), "members")
    matrix = written(open_.select("token", "id", "n").join(member.select("id", "grp", "gc"), "id").groupBy("token", "grp").agg(F.first("gc").alias("gc"), F.min("n").alias("lo"), F.max("n").alias("hi")), "matrix")
    # The groups of a token's largest component do not query each other: all other groups query those and one another.
    main = matrix.groupBy("token", "gc").agg(F.count("*").alias("k")).where("gc is not null").groupBy("token").agg(F.max(F.struct("k", "gc")).alias("m")).select("token", F.col("m.gc").alias("main"))
    side = matrix.join(main, "token", "left").withColumn("asks", ~F.coalesce(F.col("gc") == F.col("main"), F.lit(False)))
    asking = side.where("asks").select("token", F.col("grp").alias("qgrp"), F.col("lo").alias("qlo"), F.col("hi").alias("qhi"))
    fits = (100 * F.col("qhi") >= percent * F.col("lo")) & (100 * F.col("hi") >= percent * F.col("qlo")) & (~F.col("asks") | (F.col("qgrp") <= F.col("grp")))
    meet = asking.join(side, "token").where(fits).select("qgrp", "grp").distinct()
    needed = written(member.join(sets.select("id", "tokens"), "id"), "needed")
    union = written(needed.groupBy("grp").agg(F.min("n").alias("lo"), F.array_distinct(F.flatten(F.collect_list("tokens"))).alias("all")), "unions")

    def opened(own: str, other: str) -> DataFrame:
        """(own, other, id, n, component) of own's members that may have a partner in other: |A n B| / |A u B| >= t needs
        |A n B| >= t (|A| + |B|) / (1 + t), and A's overlap with the union is no less than |A n B|."""
        members = needed.withColumnRenamed("grp", own)
        overlap = F.size(F.array_intersect("tokens", "all"))
        met = meet.join(union.withColumnRenamed("grp", other), other).join(members, own)
        return met.where((100 + percent) * overlap >= percent * (F.col("n") + F.col("lo"))).select(own, other, "id", "n", "component")

    a = opened("qgrp", "grp").select("qgrp", "grp", F.col("id").alias("a"), F.col("n").alias("na"), F.col("component").alias("ca"))
    b = opened("grp", "qgrp").select("qgrp", "grp", F.col("id").alias("b"), "n", "component")
    once = (F.col("qgrp") != F.col("grp")) | (F.col("a") < F.col("b"))
    pairs = a.join(b, ["qgrp", "grp"]).where((F.col("ca") != F.col("component")) & once & _sizes_fit("na", "n", percent)).select("a", "b").distinct()
    more = written(_alike(pairs, sets, percent), "opened")
    if more.isEmpty():
        return comp
    links = more.join(comp.select(F.col("id").alias("a"), F.col("component").alias("ca")), "a", "left").join(comp.select(F.col("id").alias("b"), F.col("component").alias("cb")), "b", "left").select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b"))
    return components(comp.select(F.col("id").alias("a"), F.col("component").alias("b")).union(links))


def members(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 5, percent: int = 80, **options: int) -> DataFrame:
    """(key, mark, times, n_shingles, component, component_id) of the distinct rows: component tells the groups of linked
    documents apart (null without words), component_id is the smallest key in it."""
    probed = probes(docs, key, text, size, percent, **options)
    each = named(probed)
    comp = linked(probed, each, percent)
    stands = written(each.join(comp, "id", "left").select("n", "s1", "s2", "key", "members", "id", F.coalesce("component", "id").alias("component")), "stands")
    rows, odd = stands.agg(F.coalesce(F.sum("members"), F.lit(0)), F.coalesce(F.sum((F.col("key").isNull() | (F.col("key") != F.col("id"))).cast("long")), F.lit(0))).first()
    if odd:  # else ids are keys, and a component's id is its smallest key
        least = stands.groupBy("component").agg(F.min("key").alias("component_id"))
        stands = stands.join(least, "component")
    else:
        stands = stands.withColumn("component_id", F.col("component").cast(dict(probed.dtypes)["key"]))
    slim = probed.select("key", "mark", "times", F.col("n").alias("n_shingles"), "n", "s1", "s2")
    told = stands.select("n", "s1", "s2", "members", "component", "component_id")
    # Classes of a five-thousandth of all rows or more are five thousand at most: they are broadcast, and meet in no task.
    large = F.col("members") >= max(100, rows // 5000)
    hot = F.broadcast(told.where(large).drop("members"))
    rest = slim.join(hot.select("n", "s1", "s2"), ["n", "s1", "s2"], "left_anti").join(told.where(~large).drop("members"), ["n", "s1", "s2"], "left")
    both = slim.join(hot, ["n", "s1", "s2"]).unionByName(rest)
    return both.select("key", "mark", "times", "n_shingles", "component", F.when(F.col("component").isNull(), F.col("key")).otherwise(F.col("component_id")).alias("component_id"))


def classes(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 5, percent: int = 80, **options: int) -> DataFrame:
    """(key, n_shingles, component_id) of every document; component_id is the smallest id reachable by links."""
    out = members(docs, key, text, size, percent, **options)
    return out.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "times"))).select("key", "n_shingles", "component_id")
