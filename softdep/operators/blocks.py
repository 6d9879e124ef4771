"""Counts of many candidates by refinement of stripped partitions, on blocks of rows that fit a task.

A block holds all rows that agree on a pivot attribute, so that the groups of every left side with the pivot are whole in
it. Inside, a left side's groups are refined from those of its prefix, which neighbouring left sides share, and a group of
one row is dropped on the spot: it adds no disagreement under any right side, and stays alone under any refinement. What
was dropped is only counted. Of near-key columns little is left after one or two attributes.

- One block: a relation of up to BLOCK_ROWS rows goes whole to each task, and the candidates are dealt to the tasks.
- Many blocks: a pivot is an attribute of which no value is in more than half a block. Left sides with one use the finest:
  one exchange of the relation for each pivot, in a job of its own, serves all of them. Left sides without one, with a right side that is one, are
  counted in blocks of the right side, and their groups added up. What has no pivot at all (few values, or some in very many
  rows) is left to the joint tables, whose counts combine before they are exchanged.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.relation import Relation

Z = tuple[int, ...]
Candidate = tuple[Z, int]
Numbered = tuple[int, Candidate]

#: Rows and cells of a block at most, on average; row visits that are worth a task of their own, and what a candidate costs
#: besides its rows, in visits.
BLOCK_ROWS, BLOCK_CELLS, TASK_VISITS, CANDIDATE_VISITS = 1_000_000, 32_000_000, 40_000_000, 20_000

TOTALS = ("cid", "n", "d_lhs", "d_joint", "max_sum", "dis", "d_rhs", "sq")
TOTALS_DDL = "cid int, n long, d_lhs long, d_joint long, max_sum long, dis double, d_rhs long, sq double"
GROUPS_DDL = "cid int, k1 long, k2 long, s long, q double, k long, top long"


def _dense(column: pa.ChunkedArray) -> tuple[np.ndarray, int]:
    """Values as numbers from 0, -1 for null, and how many there are."""
    column = column.combine_chunks()
    valid = None
    if column.null_count:
        valid = column.is_valid().to_numpy(zero_copy_only=False)
        column = column.fill_null(0)
    codes, values = pd.factorize(column.to_numpy(zero_copy_only=False))
    codes = codes.astype(np.int64)
    if valid is not None:
        codes[~valid] = -1
    return codes, max(1, len(values))


class Groups:
    """The rows (of a block, by number) in groups of two or more under a left side, and their groups' numbers."""

    __slots__ = ("rows", "gid", "d")

    def __init__(self, rows: np.ndarray | None, gid: np.ndarray, d: int):
        self.rows, self.gid, self.d = rows, gid, d


class Block:
    """Coded columns of some rows, with their weights."""

    def __init__(self, table: pa.Table, columns: dict[int, list[str]], strip: bool = True):
        self.size, self.strip = table.num_rows, strip
        self.codes: dict[int, np.ndarray] = {}
        self.values: dict[int, int] = {}
        self.raw: dict[int, list[np.ndarray]] = {}
        for i, names in columns.items():
            codes, d = _dense(table[names[0]])
            if len(names) > 1:  # two hashes
                second, d2 = _dense(table[names[1]])
                both, values = pd.factorize(np.where(codes >= 0, codes * d2 + second, 0))
                codes, d = np.where(codes >= 0, both.astype(np.int64), -1), max(1, len(values))
            self.codes[i], self.values[i] = codes, d
        self.table = table
        w = np.asarray(table["w"].combine_chunks()) if "w" in table.column_names else None
        self.w = None if w is None or not len(w) or (w == 1).all() else w.astype(np.float64)
        self.nullable = {i for i, c in self.codes.items() if len(c) and c.min() < 0}
        self._totals: dict[Z, tuple[int, int]] = {}
        self._rights: dict[tuple[Z, int], tuple[int, float]] = {}

    def complete(self, attributes: Z) -> np.ndarray | None:
        """Which rows have no null among attributes; None for all."""
        some = [self.codes[i] >= 0 for i in attributes if i in self.nullable]
        return reduce(np.logical_and, some) if some else None

    def total(self, attributes: Z) -> tuple[int, int]:
        """Rows without null among attributes, and their weight."""
        key = tuple(i for i in attributes if i in self.nullable)
        if key not in self._totals:
            mask = self.complete(key)
            rows = self.size if mask is None else int(mask.sum())
            self._totals[key] = rows, rows if self.w is None else int((self.w if mask is None else self.w[mask]).sum())
        return self._totals[key]

    def right(self, lhs: Z, rhs: int) -> tuple[int, float]:
        """Number of right values among the rows without null in the candidate, and the sum of their squared counts."""
        key = tuple(sorted(i for i in lhs if i in self.nullable)), rhs
        if key not in self._rights:
            mask = self.complete((*lhs, rhs))
            codes, w = self.codes[rhs], self.w
            if mask is not None:
                codes, w = codes[mask], None if w is None else w[mask]
            counts = np.bincount(codes, w, self.values[rhs]).astype(np.float64)
            self._rights[key] = int((counts > 0).sum()), float((counts * counts).sum())
        return self._rights[key]

    def start(self) -> Groups:
        return Groups(None, np.zeros(self.size, np.int64), 1)

    def refined(self, g: Groups, attribute: int) -> Groups:
        """The groups split by one more attribute; rows with a null there and rows left alone go."""
        codes = self.codes[attribute]
        codes = codes if g.rows is None else codes[g.rows]
        rows, gid = g.rows, g.gid
        if attribute in self.nullable:
            keep = np.flatnonzero(codes >= 0)
            codes, gid = codes[keep], gid[keep]
            rows = keep if rows is None else rows[keep]
        key = gid * self.values[attribute] + codes
        span = g.d * self.values[attribute]
        if span <= 4 * len(key) + 1024:
            counts = np.bincount(key, minlength=span)
        else:
            key, _ = pd.factorize(key)
            counts = np.bincount(key)
        live = counts > (1 if self.strip else 0)
        number = np.cumsum(live) - 1
        if self.strip:
            keep = live[key]
            if not keep.all():
                keep = np.flatnonzero(keep)
                key = key[keep]
                rows = keep if rows is None else rows[keep]
        return Groups(rows, number[key], int(live.sum()))

    def counted(self, g: Groups, rhs: int) -> tuple[np.ndarray, np.ndarray, int]:
        """Counts of the joint groups, their left groups in order, and the number of rows in them."""
        codes = self.codes[rhs]
        codes = codes if g.rows is None else codes[g.rows]
        gid, w = g.gid, None if self.w is None else self.w if g.rows is None else self.w[g.rows]
        if rhs in self.nullable:
            keep = codes >= 0
            codes, gid, w = codes[keep], gid[keep], None if w is None else w[keep]
        d = self.values[rhs]
        key = gid * d + codes
        span = g.d * d
        if span <= 4 * len(key) + 1024:
            f = np.bincount(key, w, span)
            some = np.flatnonzero(f)
            return f[some].astype(np.int64), some // d, len(key)
        if w is None:
            key = np.sort(key)
        else:
            order = np.argsort(key, kind="stable")
            key, w = key[order], w[order]
        begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        f = np.diff(np.append(begin, len(key))) if w is None else np.add.reduceat(w, begin).astype(np.int64) if len(begin) else np.zeros(0, np.int64)
        return f, key[begin] // d, len(key)

    def scored(self, lhs: Z, rhs: int, g: Groups, with_right: bool) -> tuple:
        """TOTALS without cid: of the whole candidate if the left groups are whole in the block. d_rhs and sq are those of
        the block, or 0."""
        rows, n = self.total((*lhs, rhs))
        f, of, held = self.counted(g, rhs)
        alone = rows - held  # dropped rows: a group and a joint group each
        k = np.bincount(of, minlength=1)
        s = np.bincount(of, f, len(k))
        mixed = np.flatnonzero(k > 1)
        q = np.bincount(of, f.astype(np.float64) * f, len(k))[mixed]
        dis = float((s[mixed] - q / s[mixed]).sum())
        begin = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])) if len(of) else np.zeros(0, np.int64)
        top = int(np.maximum.reduceat(f, begin).sum()) if len(begin) else 0
        d_rhs, sq = self.right(lhs, rhs) if with_right else (0, 0.0)
        return n, len(begin) + alone, len(f) + alone, top + n - int(f.sum()), dis, d_rhs, sq

    def walked(self, jobs: list[Numbered], reuse: bool) -> Iterator[tuple[int, Z, int, Groups]]:
        """(cid, lhs, rhs, groups) of jobs in the order of their left sides, which share the groups of their prefixes; without
        reuse each candidate starts anew."""
        stack: list[tuple[int, Groups]] = []
        for cid, (lhs, rhs) in jobs:
            same = 0
            while reuse and same < min(len(stack), len(lhs)) and stack[same][0] == lhs[same]:
                same += 1
            del stack[same:]
            for i in lhs[same:]:
                stack.append((i, self.refined(stack[-1][1] if stack else self.start(), i)))
            yield cid, lhs, rhs, stack[-1][1]

    def identities(self, lhs: Z, columns: dict[int, list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """Two hashes of each row's values of lhs, the same in every block."""
        out = []
        for salt in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
            h = np.full(self.size, salt, np.uint64)
            for i in lhs:
                for name in columns[i]:
                    h = (h ^ self.table[name].combine_chunks().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)) * np.uint64(0xBF58476D1CE4E5B9)
                    h ^= h >> np.uint64(29)
            out.append(h.view(np.int64))
        return out[0], out[1]


def _tables(batches: Iterator[pa.RecordBatch]) -> pa.Table | None:
    held = list(batches)
    return pa.Table.from_batches(held) if held else None


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[]] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


_TOTALS_SCHEMA = pa.schema([("cid", pa.int32()), *((c, pa.float64() if c in ("dis", "sq") else pa.int64()) for c in TOTALS[1:])])
_GROUPS_SCHEMA = pa.schema([("cid", pa.int32()), ("k1", pa.int64()), ("k2", pa.int64()), ("s", pa.int64()), ("q", pa.float64()), ("k", pa.int64()), ("top", pa.int64())])


def _closed(jobs: dict[int, list[Numbered]], columns: dict[int, list[str]], reuse: bool, with_right: bool) -> Callable:
    """TOTALS of candidates whose left groups are whole in the block; jobs by slice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _tables(batches)
        if table is None or not table.num_rows:
            return
        numbers = np.asarray(table["slice"].combine_chunks()) if "slice" in table.column_names else np.zeros(table.num_rows, np.int64)
        for s in np.unique(numbers).tolist():
            own = jobs[s]
            used = {i for _, (x, a) in own for i in (*x, a)}
            block = Block(table if (numbers == s).all() else table.filter(pa.array(numbers == s)), {i: columns[i] for i in sorted(used)}, strip=reuse)
            yield _batch([(cid, *block.scored(x, a, g, with_right)) for cid, x, a, g in block.walked(own, reuse)], _TOTALS_SCHEMA)

    return run


def _open(jobs: list[Numbered], columns: dict[int, list[str]]) -> Callable:
    """Of candidates whose right values are whole in the block: each left group's part in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _tables(batches)
        if table is None or not table.num_rows:
            return
        block = Block(table, columns, strip=False)
        for cid, lhs, rhs, g in block.walked(jobs, True):
            f, of, _ = block.counted(g, rhs)
            if not len(f):
                continue
            begin = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]]))
            some = of[begin]
            first = np.full(g.d, -1, np.int64)
            first[g.gid[::-1]] = (np.arange(block.size) if g.rows is None else g.rows)[::-1]
            k1, k2 = (h[first[some]] for h in block.identities(lhs, columns))
            s, q, k = np.add.reduceat(f, begin), np.add.reduceat(f.astype(np.float64) * f, begin), np.diff(np.append(begin, len(f)))
            arrays = (np.full(len(some), cid, np.int32), k1, k2, s, q, k, np.maximum.reduceat(f, begin))
            yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(arrays, _GROUPS_SCHEMA, strict=True)], schema=_GROUPS_SCHEMA)

    return run


def _dealt(cands: list[Numbered], slices: int) -> dict[int, list[Numbered]]:
    """The candidates in the order of their left sides, runs of which go to the slices in turn."""
    ordered = sorted(cands, key=lambda c: c[1])
    run = max(1, -(-len(ordered) // (4 * slices)))
    out: dict[int, list[Numbered]] = {s: [] for s in range(slices)}
    for k in range(0, len(ordered), run):
        out[k // run % slices] += ordered[k : k + run]
    return out


def _finished(rel: Relation, totals: DataFrame) -> DataFrame:
    n = F.col("n").cast("double")
    return totals.where("n > 0").select("cid", "n", "d_lhs", "d_joint", "max_sum", "d_rhs", (F.col("dis") / n).alias("disagree_lhs"), F.when(F.col("d_rhs") == 1, 0.0).otherwise(1 - F.col("sq") / (n * n)).alias("disagree_rhs"))


def whole(rel: Relation, used: int, block_rows: int = BLOCK_ROWS) -> bool:
    """Whether a relation of so many used columns is one block."""
    return rel.size <= block_rows and rel.size * (used + 1) <= BLOCK_CELLS


def block_counts(rel: Relation, cands: list[Numbered], reuse: bool = True, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Counts of each candidate; a candidate without a tuple has no row."""
    used = sorted({i for _, (x, a) in cands for i in (*x, a)})
    if not whole(rel, len(used), block_rows):
        return _many_blocks(rel, cands, reuse, block_rows)
    # One hash of 64 bits tells a block's values apart.
    columns = {i: rel.physical(i)[:1] for i in used}
    base = rel.codes.select(*(c for i in used for c in columns[i]), *(["w"] if rel.weighted else []))
    work = (rel.size + CANDIDATE_VISITS) * len(cands)
    slices = max(1, min(rel.df.sparkSession.sparkContext.defaultParallelism, len(cands), work // TASK_VISITS))
    jobs = _dealt(cands, slices)
    if slices == 1:
        dealt = base.repartition(1)
    else:
        dealt = base.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1)))).repartition(slices, "slice")
    return _finished(rel, dealt.mapInArrow(_closed(jobs, columns, reuse, True), TOTALS_DDL))


def _many_blocks(rel: Relation, cands: list[Numbered], reuse: bool, block_rows: int) -> DataFrame:
    from softdep.operators.score import joint_counts

    marginals = rel.marginals
    fine = sorted((i for i in range(rel.m) if i in marginals and 2 * marginals[i].largest <= block_rows), key=lambda i: -marginals[i].values)
    place = {i: k for k, i in enumerate(fine)}
    closed: dict[int, list[Numbered]] = {}
    opened: dict[int, list[Numbered]] = {}
    rest: list[Numbered] = []
    for c in cands:
        x, a = c[1]
        inside = [i for i in x if i in place]
        if inside:
            closed.setdefault(min(inside, key=place.get), []).append(c)
        elif a in place:
            opened.setdefault(a, []).append(c)
        else:
            rest.append(c)
    # A job for each pivot, whose rows of counts reach the driver, so that no more than one copy of the relation is exchanged
    # at a time: the exchange's files go with its job.
    spark = rel.df.sparkSession
    names = ", ".join(f"{c} {'double' if c == 'dis' else 'int' if c == 'cid' else 'long'}" for c in TOTALS[:6])
    parts: list[pa.Table] = []
    for pivots, whole_left in ((closed, True), (opened, False)):
        for p, own in sorted(pivots.items()):
            used = sorted({i for _, (x, a) in own for i in (*x, a)})
            columns = {i: rel.physical(i) for i in used}
            blocks = max(1, -(-rel.size // block_rows), -(-rel.size * len(used) // BLOCK_CELLS))
            base = rel.codes.select(*(c for i in used for c in columns[i]), *(["w"] if rel.weighted else [])).where(F.col(columns[p][0]).isNotNull())
            dealt = base.repartition(2 * blocks, *columns[p])
            if whole_left:
                counted = dealt.mapInArrow(_closed({0: sorted(own, key=lambda c: c[1])}, columns, reuse, False), TOTALS_DDL)
                counted = counted.groupBy("cid").agg(*(F.sum(c).alias(c) for c in TOTALS[1:6]))
            else:
                groups = dealt.mapInArrow(_open(sorted(own, key=lambda c: c[1]), columns), GROUPS_DDL)
                each = groups.groupBy("cid", "k1", "k2").agg(F.sum("s").alias("s"), F.sum("q").alias("q"), F.sum("k").alias("k"), F.max("top").alias("top"))
                dis = F.when(F.col("k") > 1, F.col("s") - F.col("q") / F.col("s")).otherwise(0.0)
                counted = each.groupBy("cid").agg(F.sum("s").alias("n"), F.count("*").alias("d_lhs"), F.sum("k").alias("d_joint"), F.sum("top").alias("max_sum"), F.sum(dis).alias("dis"))
            parts.append(_collected(counted))
    out = []
    if parts:
        left = {c[0] for c in rest}
        known = rights(rel, [c for c in cands if c[0] not in left])
        n = F.col("n").cast("double")
        counts = spark.createDataFrame([r for t in parts for r in zip(*(t[c].to_pylist() for c in TOTALS[:6]), strict=True)], names)
        out.append(counts.where("n > 0").join(known, "cid").select("cid", "n", "d_lhs", "d_joint", "max_sum", "d_rhs", (F.col("dis") / n).alias("disagree_lhs"), "disagree_rhs"))
    if rest:
        out.append(joint_counts(rel, rest))
    return reduce(DataFrame.union, out)


#: Session setting under which the files of a query's exchanges are removed as soon as it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def _collected(counted: DataFrame) -> pa.Table:
    """The rows, without leaving files of exchanges behind."""
    spark = counted.sparkSession
    held = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        return counted.select("*").toArrow()  # a frame of its own, which is planned under the setting
    finally:
        if held is None:
            spark.conf.unset(CLEANUP)
        else:
            spark.conf.set(CLEANUP, held)


def rights(rel: Relation, cands: list[Numbered]) -> DataFrame:
    """(cid, d_rhs, disagree_rhs): each right side's values among the rows without null in the candidate. They depend on the
    left side's nullable attributes only, so that few sets of rows are counted."""
    spark = rel.df.sparkSession
    nullable = {i for i in range(rel.m) if rel.profile.nulls[i]}
    if not nullable:
        m = rel.marginals
        return spark.createDataFrame([(cid, m[a].values, m[a].disagreement) for cid, (_, a) in cands if a in m], "cid int, d_rhs long, disagree_rhs double")
    by: dict[Z, dict[int, list[int]]] = {}
    for cid, (x, a) in cands:
        by.setdefault(tuple(i for i in x if i in nullable), {}).setdefault(a, []).append(cid)
    parts = []
    for given, rights_ in by.items():
        rows = rel.codes
        for i in given:
            rows = rows.where(F.col(rel.physical(i)[0]).isNotNull())
        attributes = sorted(rights_)
        names = [p for a in attributes for p in rel.physical(a)]
        grouped = rows.select(*names, "w").groupingSets([[F.col(p) for p in rel.physical(a)] for a in attributes], *names).agg(F.sum("w").alias("f"), F.grouping_id().alias("gid"))
        width = len(names)
        gid = {a: sum(1 << (width - 1 - k) for k, p in enumerate(names) if p not in rel.physical(a)) for a in attributes}
        own = reduce(lambda x, y: x | y, [(F.col("gid") == g) & F.col(rel.physical(a)[0]).isNotNull() for a, g in gid.items()])
        sums = grouped.where(own).groupBy("gid").agg(F.count("*").alias("d_rhs"), F.sum("f").alias("s"), F.sum(F.col("f").cast("double") * F.col("f")).alias("q"))
        listed = spark.createDataFrame([(gid[a], cid) for a in attributes for cid in rights_[a]], "gid long, cid int")
        s = F.col("s").cast("double")
        parts.append(sums.join(F.broadcast(listed), "gid").select("cid", "d_rhs", F.when(F.col("d_rhs") == 1, 0.0).otherwise(1 - F.col("q") / (s * s)).alias("disagree_rhs")))
    return reduce(DataFrame.union, parts)
