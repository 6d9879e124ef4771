"""Counts of many candidates on growing parts of a relation, each of which holds the parts before it.

A row's layer is the first part that holds it. The relation has it as one more attribute, its last. In a block whose rows are in
the order of their layers each part is a run from the start, so that one exchange for each pivot, and one refinement for each
left side, serve all parts; only the joint groups are counted for each. A row that is alone in its left group is alone in every
part. Right sides with a pivot are counted from the same exchange as left sides with it. What has no pivot is first added up to
one row for each combination of its attributes and layer, where these are few enough for a block.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.operators.blocks import BLOCK_CELLS, BLOCK_ROWS, CANDIDATE_VISITS, TASK_VISITS, Block, Groups, Numbered, Z, _collected, _dealt, _tables, whole
from softdep.relation import Marginal, Profile, Relation

#: Counts of a candidate in a part: n, d_lhs, d_joint, max_sum, d_rhs, disagree_lhs, disagree_rhs.
Counts = tuple[int, int, int, int, int, float, float]

#: A row is a left group's share in a block, or, with k1 and k2 of 0, what all left groups of a block add up to: then dis is
#: their disagreement and d their number.
ROWS = pa.schema([("cid", pa.int32()), ("part", pa.int32()), ("k1", pa.int64()), ("k2", pa.int64()), ("s", pa.int64()), ("q", pa.float64()), ("k", pa.int64()), ("top", pa.int64()), ("d", pa.int64()), ("dis", pa.float64())])
ROWS_DDL = "cid int, part int, k1 long, k2 long, s long, q double, k long, top long, d long, dis double"


class Layers(Block):
    """A block with its rows in the order of their layers; part t ends before row ends[t]."""

    def __init__(self, table: pa.Table, columns: dict[int, list[str]], layer: str, parts: int):
        at = table[layer].combine_chunks().to_numpy(zero_copy_only=False).astype(np.int16)
        order = np.argsort(at, kind="stable")
        super().__init__(table.take(pa.array(order)), columns)
        self.ends = np.searchsorted(at[order], np.arange(parts), "right")
        self._last: tuple[Groups, np.ndarray, tuple] | None = None  # a left side's groups, which neighbours share, and their weights

    def refined(self, g: Groups, attribute: int) -> Groups:
        """As a block's, by a sort of keys with their rows beside them where the keys are many and both fit a word."""
        n = self.size if g.rows is None else len(g.rows)
        span = g.d * self.values[attribute]
        width = max(1, n - 1).bit_length()
        if span <= 4 * n + 1024 or not self.strip or attribute in self.nullable or span.bit_length() + width > 62:
            return super().refined(g, attribute)
        codes = self.codes[attribute]
        key = g.gid * self.values[attribute] + (codes if g.rows is None else codes[g.rows])
        key <<= width
        key |= np.arange(n)
        key.sort()
        rank = key & ((1 << width) - 1)
        key >>= width
        same = key[1:] == key[:-1]
        live = np.zeros(n, bool)
        live[1:] = same
        live[:-1] |= same
        first = live.copy()
        first[1:] &= ~same
        number = np.full(n, -1, np.int64)
        kept = np.flatnonzero(live)
        groups = np.cumsum(first[kept]) - 1
        number[rank[kept]] = groups
        keep = np.flatnonzero(number >= 0)
        return Groups(keep if g.rows is None else g.rows[keep], number[keep], int(groups[-1]) + 1 if len(groups) else 0)

    def totals(self, attributes: Z) -> list[tuple[int, int]]:
        """Of each part: rows without null among attributes, and their weight."""
        key = tuple(i for i in attributes if i in self.nullable)
        if key not in self._totals:
            mask = self.complete(key)
            rows = [int(e if mask is None else mask[:e].sum()) for e in self.ends]
            if self.w is None:
                self._totals[key] = [(r, r) for r in rows]
            else:
                w = self.w if mask is None else np.where(mask, self.w, 0.0)
                self._totals[key] = [(r, int(w[:e].sum())) for r, e in zip(rows, self.ends, strict=True)]
        return self._totals[key]

    def shares(self, g: Groups, rhs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """By part and left group: s, the weight without null on the right, and of the group's joint groups the sum of squared
        weights less s, s less their number, and the largest less 1; and by part the rows of them all."""
        codes = self.codes[rhs]
        codes = codes if g.rows is None else codes[g.rows]
        gid, w = g.gid, None if self.w is None else self.w if g.rows is None else self.w[g.rows]
        ends = self.ends if g.rows is None else np.searchsorted(g.rows, self.ends)
        if rhs in self.nullable:
            keep = np.flatnonzero(codes >= 0)
            codes, gid, w, ends = codes[keep], gid[keep], None if w is None else w[keep], np.searchsorted(keep, ends)
            s = self._sizes(gid, w, ends, g.d)
        else:
            if self._last is None or self._last[0] is not g:
                s = self._sizes(gid, w, ends, g.d)
                self._last = g, s, self._sums(s)
            s = self._last[1]
        d = self.values[rhs]
        span, parts = g.d * d, len(ends)
        width = max(1, parts - 1).bit_length()
        if span <= len(codes) + 1024:
            squares, fewer, top = np.empty_like(s), np.empty_like(s), np.empty_like(s)
            shape, axis = ((d, g.d), 0) if d <= g.d else ((g.d, d), 1)
            key = codes * g.d + gid if axis == 0 else gid * d + codes
            f = np.zeros(shape, np.int64)
            for t, (at, end) in enumerate(zip([0, *ends[:-1]], ends, strict=True)):
                f += np.bincount(key[at:end], None if w is None else w[at:end], span).astype(np.int64, copy=False).reshape(shape)
                np.sum(f * f, axis, out=squares[t])
                np.sum(f != 0, axis, out=fewer[t])
                np.max(f, axis, out=top[t])
            return s, squares - s, s - fewer, np.maximum(top - 1, 0), ends
        if w is None and span.bit_length() + width <= 62:
            key = gid * d + codes
            key <<= width
            for t in range(1, parts):
                key[ends[t - 1] : ends[t]] |= t
            key.sort()
            joint = key >> width
            again = np.empty(len(key), bool)
            again[:1] = False
            np.equal(joint[1:], joint[:-1], out=again[1:])
            rest = np.flatnonzero(again)  # rows that find their joint group begun: the r-th adds 2 r to the squares
            r = rest - np.flatnonzero(~again)[rest - np.arange(1, len(rest) + 1)]
            cell = (key[rest] & ((1 << width) - 1)) * g.d + joint[rest] // d
            fewer, squares, top = np.bincount(cell, None, parts * g.d), np.bincount(cell, 2.0 * r, parts * g.d), np.zeros(parts * g.d, np.int64)
            np.maximum.at(top, cell, r)
            squares, fewer, top = (x.reshape(parts, g.d) for x in (squares, fewer, top))
            for t in range(1, parts):
                squares[t] += squares[t - 1]
                fewer[t] += fewer[t - 1]
                np.maximum(top[t], top[t - 1], out=top[t])
            return s, squares, fewer, top, ends
        squares, fewer, top = np.zeros_like(s), np.zeros_like(s), np.zeros_like(s)
        order = np.lexsort((codes, gid))
        first = np.ones(len(order), bool)
        first[1:] = (gid[order][1:] != gid[order][:-1]) | (codes[order][1:] != codes[order][:-1])
        number = np.empty(len(order), np.int64)
        number[order] = np.cumsum(first) - 1
        of = gid[order][first]
        begin = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])) if len(of) else of
        for t, end in enumerate(ends):
            f = np.bincount(number[:end], None if w is None else w[:end], len(of)).astype(np.int64)
            if len(of):
                squares[t, of[begin]], fewer[t, of[begin]], top[t, of[begin]] = np.add.reduceat(f * f, begin), np.add.reduceat((f > 0).astype(np.int64), begin), np.maximum.reduceat(f, begin)
        return s, squares - s, s - fewer, np.maximum(top - 1, 0), ends

    def _sizes(self, gid: np.ndarray, w: np.ndarray | None, ends: np.ndarray, d: int) -> np.ndarray:
        """The weight of each group in each part."""
        out = np.zeros((len(ends), d), np.int64)
        for t, (at, end) in enumerate(zip([0, *ends[:-1]], ends, strict=True)):
            out[t] = np.bincount(gid[at:end], None if w is None else w[at:end], d)
            if t:
                out[t] += out[t - 1]
        return out

    @staticmethod
    def _sums(s: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of the weights of groups by part: their sums, how many groups have any, and the weights as divisors."""
        return s.sum(1), np.count_nonzero(s, 1), np.maximum(s, 1).astype(np.float64)

    def closed(self, cid: int, lhs: Z, rhs: int, g: Groups) -> Iterator[tuple]:
        """A row of each part for a candidate whose left groups are whole in the block."""
        s, squares, fewer, top, ends = self.shares(g, rhs)
        inside, groups, some = self._last[2] if self._last is not None and s is self._last[1] else self._sums(s)
        joints, tops = inside - fewer.sum(1), groups + top.sum(1)
        agree = (squares / some).sum(1)
        for t, (rows, n) in enumerate(self.totals((*lhs, rhs))):
            if rows:
                alone = rows - int(ends[t])  # dropped rows: a group and a joint group each
                yield cid, t, 0, 0, n, 0.0, joints[t] + alone, tops[t] + n - inside[t], groups[t] + alone, inside[t] - groups[t] - agree[t]

    def opened(self, cid: int, lhs: Z, rhs: int, g: Groups, columns: dict[int, list[str]]) -> Iterator[pa.RecordBatch]:
        """Each left group's row in each part, for a candidate whose right values are whole in the block."""
        first = np.full(g.d, -1, np.int64)
        first[g.gid[::-1]] = (np.arange(self.size) if g.rows is None else g.rows)[::-1]
        k1, k2 = (h[first] for h in self.identities(lhs, columns))
        s, squares, fewer, top, _ = self.shares(g, rhs)
        for t in range(len(s)):
            some = np.flatnonzero(s[t])
            if len(some):
                zero, of = np.zeros(len(some), np.int64), s[t, some]
                yield _rows([np.full(len(some), cid), np.full(len(some), t), k1[some], k2[some], of, (squares[t, some] + of).astype(np.float64), of - fewer[t, some], top[t, some] + 1, zero, zero])


def _rows(columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.asarray(c)).cast(f.type) for c, f in zip(columns, ROWS, strict=True)], schema=ROWS)


def _kernel(closed: dict[int, list[Numbered]], opened: list[Numbered], columns: dict[int, list[str]], layer: str, parts: int) -> Callable:
    """ROWS of a block; closed by slice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _tables(batches)
        if table is None or not table.num_rows:
            return
        numbers = np.asarray(table["slice"].combine_chunks()) if "slice" in table.column_names else np.zeros(table.num_rows, np.int64)
        for s in np.unique(numbers).tolist():
            used = {i for _, (x, a) in (*closed[s], *opened) for i in (*x, a)}
            block = Layers(table if (numbers == s).all() else table.filter(pa.array(numbers == s)), {i: columns[i] for i in sorted(used)}, layer, parts)
            out = [r for cid, x, a, g in block.walked(closed[s], True) for r in block.closed(cid, x, a, g)]
            if out:
                yield _rows(list(zip(*out, strict=True)))
            block.strip = False
            for cid, x, a, g in block.walked(opened, True):
                yield from block.opened(cid, x, a, g, columns)

    return run


def _folded(rows: DataFrame) -> pa.Table:
    """(cid, part, n, d_lhs, d_joint, max_sum, dis)."""
    each = rows.groupBy("cid", "part", "k1", "k2").agg(*(F.sum(c).alias(c) for c in ("s", "q", "k", "d", "dis")), F.sum("top").alias("tops"), F.max("top").alias("top"))
    own = F.col("d") == 0  # a left group's; that of a block has groups
    return _collected(
        each.groupBy("cid", "part").agg(
            F.sum("s").alias("n"),
            F.sum(F.when(own, 1).otherwise(F.col("d"))).alias("d_lhs"),
            F.sum("k").alias("d_joint"),
            F.sum(F.when(own, F.col("top")).otherwise(F.col("tops"))).alias("max_sum"),
            F.sum(F.when(own, F.when(F.col("k") > 1, F.col("s") - F.col("q") / F.col("s")).otherwise(0.0)).otherwise(F.col("dis"))).alias("dis"),
        )
    )


class Nested:
    """A relation whose last attribute is each row's layer, from 0 to parts - 1 and never null."""

    def __init__(self, rel: Relation, parts: int, block_rows: int = BLOCK_ROWS):
        self.rel, self.parts, self.block_rows = rel, parts, block_rows
        self.m = rel.m - 1
        self.layer = rel.physical(self.m)[0]
        by = rel.profiles(self.m)
        none = Profile(0, 0, (0,) * rel.m, 0)
        self.profiles: list[Profile] = []  # of the parts, without the layer; at most distinct tuples differ
        for t in range(parts):
            some = [by.get(u, none) for u in range(t + 1)]
            nulls = tuple(sum(p.nulls[i] for p in some) for i in range(self.m))
            self.profiles.append(Profile(sum(p.rows for p in some), sum(p.complete for p in some), nulls, sum(p.distinct for p in some)))
        last = self.profiles[-1]
        rel._profile = Profile(last.rows, last.complete, (*last.nulls, 0), last.distinct)
        self._rights: dict[tuple[Z, int], list[Marginal | None]] = {}

    def rows(self) -> DataFrame:
        """Codes with w: kept where equal tuples were added up, else read again by each job, each what it needs."""
        return self.rel.codes if self.rel.weighted else self.rel.coded.withColumn("w", F.lit(1).cast("long"))

    def rights(self, wanted: set[tuple[Z, int]]) -> dict[tuple[Z, int], list[Marginal | None]]:
        """The marginals in each part of an attribute, among the rows without null in the others given with it."""
        todo = sorted(k for k in wanted if k not in self._rights)
        for at in range(0, len(todo), 24):
            jobs = None
            for number, (given, a) in enumerate(todo[at : at + 24]):
                rows, names = self.rows(), self.rel.physical(a)
                for i in (*given, a):
                    rows = rows.where(F.col(self.rel.physical(i)[0]).isNotNull())
                f = [F.sum(F.when(F.col(self.layer) <= t, F.col("w"))).alias(f"f{t}") for t in range(self.parts)]
                sums = [e for t in range(self.parts) for c in [F.col(f"f{t}")] for e in (F.count(c), F.sum(c.cast("double")), F.sum(c.cast("double") * c), F.max(c))]
                one = rows.groupBy(*names).agg(*f).agg(F.lit(number), *sums)
                jobs = one if jobs is None else jobs.union(one)
            for number, *r in zip(*(c.to_pylist() for c in _collected(jobs.toDF(*(f"x{i}" for i in range(4 * self.parts + 1)))).columns), strict=True):
                four = [r[4 * t : 4 * t + 4] for t in range(self.parts)]
                self._rights[todo[at + number]] = [Marginal(d, 0.0 if d == 1 else 1 - q / (n * n), top) if d else None for d, n, q, top in four]
        return self._rights

    def counts(self, cands: list[Numbered]) -> list[dict[int, Counts]]:
        """Of each part, the counts by cid of the candidates with a tuple."""
        nullable = {i for i in range(self.m) if self.profiles[-1].nulls[i]}
        right = {cid: (tuple(sorted(i for i in x if i in nullable)), a) for cid, (x, a) in cands}
        rights = self.rights(set(right.values()))
        out: list[dict[int, Counts]] = [{} for _ in range(self.parts)]
        for table in self._tables(cands):
            for cid, t, n, d_lhs, d_joint, max_sum, dis in zip(*(c.to_pylist() for c in table.columns), strict=True):
                if n:
                    r = rights[right[cid]][t]
                    out[t][cid] = (n, d_lhs, d_joint, max_sum, r.values, dis / n, r.disagreement)
        return out

    def _tables(self, cands: list[Numbered]) -> Iterator[pa.Table]:
        if whole(self.rel, self.rel.m, self.block_rows):
            yield _folded(self._one(self.rows(), cands, self.rel.size))
            return
        own = self.rights({((), i) for i in range(self.m)})
        marginals = {i: own[(), i][-1] for i in range(self.m) if own[(), i][-1]}
        fine = sorted((i for i in marginals if 2 * marginals[i].largest <= self.block_rows), key=lambda i: -marginals[i].values)
        closed: dict[int, list[Numbered]] = {i: [] for i in fine}
        opened: dict[int, list[Numbered]] = {i: [] for i in fine}
        rest: list[Numbered] = []
        for c in cands:
            x, a = c[1]
            inside = [i for i in fine if i in x]
            (closed[inside[0]] if inside else opened[a] if a in opened else rest).append(c)
        for p in fine:
            if closed[p] or opened[p]:
                yield _folded(self._dealt(p, closed[p], opened[p]))
        alone: list[Numbered] = []
        for some, most in self._few(rest, {i: v.values + 1 for i, v in marginals.items()}):
            if most is None:
                alone += some
            else:
                names = [c for i in self._used(some) for c in self.rel.physical(i)]
                yield _folded(self._one(self.rows().groupBy(*names, self.layer).agg(F.sum("w").alias("w")), some, most, True))
        if alone:
            yield from self._joints(alone, own)

    def _used(self, cands: list[Numbered]) -> list[int]:
        return sorted({i for _, (x, a) in cands for i in (*x, a)})

    def _few(self, cands: list[Numbered], values: dict[int, int]) -> Iterator[tuple[list[Numbered], int | None]]:
        """Runs of candidates whose attributes and layer have few combinations, and how many at most; None for those that have
        many alone."""
        most = lambda used: self.parts * prod(values.get(i, 1) for i in used)
        fits = lambda used: most(used) * (len(used) + 2) <= BLOCK_CELLS and 4 * most(used) <= max(self.rel.size, 4 * self.block_rows)
        held: list[Numbered] = []
        for c in sorted(cands, key=lambda c: (tuple(sorted((*c[1][0], c[1][1]))), c[1])):
            if held and not fits(self._used([*held, c])):
                yield held, most(self._used(held)) if fits(self._used(held)) else None
                held = []
            held.append(c)
        if held:
            yield held, most(self._used(held)) if fits(self._used(held)) else None

    def _one(self, rows: DataFrame, cands: list[Numbered], size: int, weighted: bool = False) -> DataFrame:
        """The candidates dealt to tasks, each of which gets all rows."""
        columns = {i: self.rel.physical(i)[:1] for i in self._used(cands)}  # one hash of 64 bits tells a block's values apart
        base = rows.select(*(c for n in columns.values() for c in n), self.layer, *(["w"] if weighted or self.rel.weighted else []))
        work = (self.parts * size // 2 + CANDIDATE_VISITS) * len(cands)
        slices = max(1, min(self.rel.df.sparkSession.sparkContext.defaultParallelism, len(cands), work // TASK_VISITS))
        dealt = base.repartition(1) if slices == 1 else base.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1)))).repartition(slices, "slice")
        return dealt.mapInArrow(_kernel(_dealt(cands, slices), [], columns, self.layer, self.parts), ROWS_DDL)

    def _dealt(self, p: int, closed: list[Numbered], opened: list[Numbered]) -> DataFrame:
        """Blocks of rows by the values of p, which closed have on the left and opened on the right."""
        size, columns = self.rel.size, {i: self.rel.physical(i) for i in self._used([*closed, *opened])}
        blocks = max(1, -(-size // self.block_rows), -(-size * (len(columns) + 1) // BLOCK_CELLS))
        base = self.rows().select(*(c for n in columns.values() for c in n), self.layer, *(["w"] if self.rel.weighted else [])).where(F.col(columns[p][0]).isNotNull())
        order = lambda some: sorted(some, key=lambda c: c[1])
        return base.repartition(2 * blocks, *columns[p]).mapInArrow(_kernel({0: order(closed)}, order(opened), columns, self.layer, self.parts), ROWS_DDL)

    def _joints(self, cands: list[Numbered], own: dict) -> Iterator[pa.Table]:
        """By joint tables of each part: many combinations of values that are each in very many rows."""
        from softdep.operators.score import joint_counts

        for t in range(self.parts):
            if not self.profiles[t].rows:
                continue
            rel = Relation(self.rel.df, self.rel.columns[: self.m], wide=self.rel.wide, null_policy=self.rel.null_policy)
            rel._codes, rel._profile, rel._size = self.rows().where(F.col(self.layer) <= t), self.profiles[t], self.profiles[t].rows
            rel._marginals = {i: own[(), i][t] for i in range(self.m) if own[(), i][t]}
            yield _collected(joint_counts(rel, cands).select("cid", F.lit(t).alias("part"), "n", "d_lhs", "d_joint", "max_sum", (F.col("disagree_lhs") * F.col("n")).alias("dis")))
