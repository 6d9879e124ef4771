"""Reliable fraction of information: information gain less its mean under permutations of the right side.

The mean over all permutations is known in closed form: the overlap of a left group of s tuples with a right value of t
tuples is hypergeometric, so that only the numbers of groups by size count. No permutation is made, and nothing is sampled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softdep.operators.blocks import Block, _dealt, whole
from softdep.operators.joint import joint_table
from softdep.operators.score import Candidate
from softdep.relation import Relation


def log_factorial(x: np.ndarray) -> np.ndarray:
    """ln x!, by Stirling's series from 16 on."""
    x = np.asarray(x, np.float64)
    small = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1.0, 17.0)))])
    y = np.maximum(x, 16.0)
    series = y * np.log(y) - y + 0.5 * np.log(2 * np.pi * y) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5)
    return np.where(x < 16, small[np.minimum(x, 16).astype(np.int64)], series)


def expected_information(left: np.ndarray, right: np.ndarray) -> float:
    """Mean mutual information, in bits, of left groups and right values of the given sizes over all permutations."""
    n = int(left.sum())
    total = 0.0
    (ls, lc), (rs, rc) = np.unique(left, return_counts=True), np.unique(right, return_counts=True)
    for s, many in zip(ls.tolist(), lc.tolist(), strict=True):
        # All overlaps of a group of s with each right size, one run of them after the other.
        lo, hi = np.maximum(1, s + rs - n), np.minimum(s, rs)
        length = hi - lo + 1
        t = np.repeat(rs, length)
        c = np.repeat(rc, length)
        k = np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length) + np.repeat(lo, length)
        log_p = log_factorial(s) + log_factorial(n - s) + log_factorial(t) + log_factorial(n - t) - log_factorial(n)
        log_p = log_p - log_factorial(k) - log_factorial(s - k) - log_factorial(t - k) - log_factorial(n - s - t + k)
        total += many * float((c * np.exp(log_p) * k / n * np.log2(n * k / (s * t))).sum())
    return total


def _entropy(counts: np.ndarray) -> float:
    p = counts / counts.sum()
    return float(-(p * np.log2(p)).sum())


def reliable(joint: np.ndarray, left: np.ndarray, right: np.ndarray) -> float:
    """Of the sizes of joint groups, left groups and right values."""
    top = _entropy(right)
    if top <= 1e-15:
        return 0.0  # a constant right side holds no information that could be gained
    gain = (_entropy(left) + top - _entropy(joint)) / top
    mean = expected_information(left, right) / top
    return max(0.0, (gain - mean) / (1 - mean)) if mean < 1 - 1e-12 else 0.0


def fraction_of_information(rel: Relation, lhs: list[str], rhs: str) -> float:
    """1 - H(A | X) / H(A), from joint counts, by built-in aggregates; 1 where A is constant."""
    joint = joint_table(rel, [*lhs, rhs])
    groups = joint.groupBy(*lhs).agg(F.sum("f").alias("s"), F.sum(F.col("f") * F.log2("f")).alias("l"))
    n, h = groups.agg(F.sum("s"), F.sum(F.col("s") * F.log2("s") - F.col("l"))).first()
    q = joint.groupBy(rhs).agg(F.sum("f").alias("s")).agg(F.sum(F.col("s") * F.log2("s"))).first()[0]
    top = np.log2(n) - q / n
    return 1.0 if top <= 1e-15 else float(1 - h / n / top)


def rfi_prime_plus(rel: Relation, lhs: list[str], rhs: str, max_sizes: int = 100_000) -> float:
    """The fraction of information less its permutation mean, over 1 less that mean, at least 0. Of any relation: only how
    many groups have each size reaches the driver, at most the square root of twice the tuples for each side (and at most
    max_sizes, else an error)."""
    joint = joint_table(rel, [*lhs, rhs])

    def sizes(by: list[str]) -> np.ndarray:
        rows = joint.groupBy(*by).agg(F.sum("f").alias("s")).groupBy("s").agg(F.count("*").alias("c")).limit(max_sizes + 1).collect()
        if len(rows) > max_sizes:
            raise ValueError("groups of too many sizes")
        return np.repeat([r["s"] for r in rows], [r["c"] for r in rows])

    return reliable(sizes([*lhs, rhs]), sizes(lhs), sizes([rhs])) if not joint.isEmpty() else 0.0


def rfi_frame(rel: Relation, cands: list[Candidate]) -> DataFrame:
    """(lhs, rhs, n, rfi) of many candidates on a relation that is one block (see blocks.whole; rfi_prime_plus has no such
    limit); rfi is null for candidates of one tuple or none."""
    used = sorted({i for x, a in cands for i in (*x, a)})
    if not whole(rel, len(used)):
        raise ValueError("the relation is larger than a block: use rfi_prime_plus for each candidate")
    columns = {i: rel.physical(i)[:1] for i in used}
    slices = max(1, min(rel.df.sparkSession.sparkContext.defaultParallelism, len(cands)))
    jobs = _dealt(list(enumerate(cands)), slices)
    schema = pa.schema([("lhs", pa.list_(pa.int32())), ("rhs", pa.int32()), ("n", pa.int64()), ("rfi", pa.float64())])

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        table = pa.Table.from_batches(held) if held else None
        if table is None or not table.num_rows:
            return
        numbers = np.asarray(table["slice"].combine_chunks())
        for s in np.unique(numbers).tolist():
            block = Block(table.filter(pa.array(numbers == s)), columns, strip=False)
            out = []
            for _, x, a, g in block.walked(jobs[s], True):
                f, of, _ = block.counted(g, a)
                codes = block.codes[a] if g.rows is None else block.codes[a][g.rows]
                w = None if block.w is None else block.w if g.rows is None else block.w[g.rows]
                right = np.bincount(codes[codes >= 0], None if w is None else w[codes >= 0])
                left = np.bincount(of, f) if len(f) else np.zeros(0)
                n = int(f.sum())
                out.append((list(x), a, n, reliable(f, left[left > 0].astype(np.int64), right[right > 0].astype(np.int64)) if n > 1 else None))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t.type) for k, t in enumerate(schema)], schema=schema)

    base = rel.codes.select(*(c for i in used for c in columns[i]), "w", F.explode(F.sequence(F.lit(0), F.lit(slices - 1))).alias("slice"))
    return base.repartition(slices, "slice").mapInArrow(score, "lhs array<int>, rhs int, n long, rfi double")
