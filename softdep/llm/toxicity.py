"""Toxicity scores from positive and unlabelled texts, with a non-negative risk estimator.

Confirmed toxic texts (P) and all texts of the training folds without regard to labels (U) train a linear model in NumPy on
the presence of words and word beginnings. With class prior c and logistic loss l, the risk is

    c * mean_P l(g) + max(0, mean_U l(-g) - c * mean_P l(-g)),

the second term being the negatives' risk with the positives' share taken out of U. Where a step makes that term
negative, the step goes against it instead, so that the model cannot fit by driving it below zero.

Features are hashes of words. Candidates are those of three positives or more, and those in a hundredth or more of all
training rows; how many rows of U hold each is counted over every training row. Features are those whose frequencies in P and U differ by a G2
of min_g2, if c * P(word | P) / P(word | U), the share of toxic texts among those with the word, is min_share or more (they
tell toxic texts) or under c (they tell others). Their number has no cap, their weights either sign. U's part of risk and
gradient is summed over every training row, a pass over the rows' feature numbers for each step. Only P is bounded, at
max_positive rows, the first in the order of a hash of their ids. The class prior is the share of toxic rows among all
labelled training rows. Every text is scored, whole.

Edge cases. A null or empty text has no words and gets the bias's score. Without labels, or with no telling word, every
text gets the prior (0 without labels). Null labels are ignored; conflicting ones of one id count as toxic. Repeated rows
each count and are scored alike; texts of equal words tie. A null id belongs to no fold: it is held out. Very long texts are
read in pieces of whole rows. Other columns, whatever their names, are neither read nor changed.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softdep.llm._store import bounded_batches, written
from softdep.llm._text import Hashes, lowered_latin, pieces, spans

#: Beginnings of words, in bytes, stand beside whole words, so that inflected forms share what is learnt.
STEMS = (4, 5, 6, 7, 8, 9)
#: All ASCII but letters and digits separates words.
APART = tuple(b for b in range(128) if not chr(b).isalnum())


def features(texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, rows, row, hash) of runs of texts: a hash for each word and each of its beginnings."""
    for first, data, offs in pieces(texts):
        data = lowered_latin(data)
        row, start, end = spans(data, offs, APART)
        h = Hashes(data)
        parts = [(row, h.of(start, end))]
        for k in STEMS:
            long = end - start > k
            parts.append((row[long], h.of(start[long], start[long] + k) ^ np.uint64(0x5851F42D4C957F2D)))
        yield first, len(offs) - 1, *map(np.concatenate, zip(*parts, strict=True))


def in_training(key: Column) -> Column:
    """The rows whose labels may be learnt from."""
    return F.coalesce(F.crc32(key.cast("string")) % 5 != 0, F.lit(False))


def present(words: np.ndarray, texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, rows, row, place in words) of runs of texts: each of the sorted words that occurs in a row once."""
    for first, n, row, h in features(texts):
        at = np.minimum(np.searchsorted(words, h), len(words) - 1)
        hit = words[at] == h
        pairs = np.unique(row[hit] * len(words) + at[hit])
        yield first, n, *np.divmod(pairs, len(words))


class Sparse:
    """Rows of zeros and ones by the columns of the ones."""

    def __init__(self, row: np.ndarray, column: np.ndarray, shape: tuple[int, int]):
        self.row, self.column, self.shape = row, column, shape

    def times(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, w[self.column], self.shape[0])

    def back(self, v: np.ndarray) -> np.ndarray:
        return np.bincount(self.column, v[self.row], self.shape[1])


@dataclass(frozen=True)
class Model:
    """Feature hashes in order, their weights, the bias and the class prior."""

    words: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float

    def score(self, texts: pa.Array) -> np.ndarray:
        if not len(self.words):
            return np.full(len(texts), self.prior)
        sums = np.zeros(len(texts))
        for first, n, row, at in present(self.words, texts):
            sums[first : first + n] = np.bincount(row, self.weights[at], n)
        return 1 / (1 + np.exp(-np.clip(self.bias + sums, -700, 700)))


_NONE = (np.zeros(0, np.uint64), np.zeros(0))


def softplus(x: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, x)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -500, 500)))


@dataclass(frozen=True)
class Side:
    """Sums over rows at some weights: their number, of softplus(g), of sigmoid(g), and of sigmoid(g) by feature."""

    n: float
    loss: float
    bias: float
    weights: np.ndarray

    @staticmethod
    def of(x: Sparse, w: np.ndarray) -> Side:
        g = x.times(w[:-1]) + w[-1]
        s = sigmoid(g)
        return Side(x.shape[0], float(softplus(g).sum()), float(s.sum()), x.back(s))

    @property
    def gradient(self) -> np.ndarray:
        """Of the mean of softplus(g)."""
        return np.append(self.weights, self.bias) / self.n


def risk(pos: Side, unl: Side, share: np.ndarray, g_mean: float, prior: float) -> tuple[float, float, np.ndarray, np.ndarray]:
    """(risk without the correction, the negatives' part, gradient of the risk, gradient of the negatives' part). share: of
    the positives with each feature, and 1; g_mean: the positives' mean of g."""
    away = unl.loss / unl.n - prior * pos.loss / pos.n
    down = unl.gradient - prior * pos.gradient
    # l(g) = softplus(-g) = softplus(g) - g.
    return prior * (pos.loss / pos.n - g_mean) + away, away, prior * (pos.gradient - share) + down, down


def fit_weights(pos: Sparse, unlabelled: Callable[[np.ndarray], Side], prior: float, steps: int = 40, rate: float = 0.3, decay: float = 1e-4) -> np.ndarray:
    """Weights, then the bias, by Adam with a falling rate on gradients of the non-negative risk over all rows. unlabelled
    gives U's sums at some weights."""
    d = pos.shape[1]
    w, m, v = np.zeros(d + 1), np.zeros(d + 1), np.zeros(d + 1)
    share = np.append(pos.back(np.ones(pos.shape[0])) / pos.shape[0], 1.0)
    for t in range(1, steps + 1):
        _, away, g, down = risk(Side.of(pos, w), unlabelled(w), share, float(share @ w), prior)
        g = (-down if away < 0 else g) + decay * np.append(w[:-1], 0)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w = w - rate * (1.03 - t / steps) * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return w


def row_frequency(texts: DataFrame, words: np.ndarray) -> tuple[int, np.ndarray]:
    """Number of rows of texts, and of those with each of the sorted words."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, seen = np.zeros(len(words), np.int64), 0
        for batch in batches:
            seen += batch.num_rows
            for _, _, _, at in present(words, batch.column(0)):
                total += np.bincount(at, minlength=len(words))
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(total[some], seen))], ["word", "n"])

    got = texts.mapInArrow(count, "word long, n long").groupBy("word").agg(F.sum("n").alias("n")).toArrow()
    n = np.zeros(len(words) + 1, np.int64)
    n[got["word"].to_numpy()] = got["n"].to_numpy()  # -1, the total, is the last place
    return int(n[-1]), n[:-1]


def frequent(texts: DataFrame, share: float) -> np.ndarray:
    """Hashes that may be in at least that share of all rows: each is so in some partition, which names it."""

    def name(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, counts, since = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        fresh: list[np.ndarray] = []
        rows = before = 0

        def merged() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            """A word that falls short of the share since it came is forgotten: if it reaches the share of all rows, it does
            so in those to come alone."""
            w, n = np.unique(np.concatenate(fresh), return_counts=True)
            both, at = np.unique(np.concatenate([words, w]), return_inverse=True)
            total = np.bincount(at, np.concatenate([counts, n]), len(both)).astype(np.int64)
            came = np.full(len(both), before, np.int64)
            came[at[: len(words)]] = since
            keep = total >= share * (rows - came)
            return both[keep], total[keep], came[keep]

        for batch in batches:
            for _, n, row, h in features(batch.column(0)):
                order = np.lexsort((h, row))
                row, h = row[order], h[order]
                new = np.ones(len(h), bool)
                new[1:] = (row[1:] != row[:-1]) | (h[1:] != h[:-1])
                fresh.append(h[new])
                rows += n
                if sum(map(len, fresh)) > 1 << 20:
                    words, counts, since = merged()
                    fresh, before = [], rows
        if fresh:
            words, counts, since = merged()
        yield pa.RecordBatch.from_arrays([pa.array(words.astype(np.int64))], ["word"])

    got = texts.mapInArrow(name, "word long").distinct().toArrow()
    return np.sort(got["word"].to_numpy().astype(np.uint64))


def numbered(texts: DataFrame, words: np.ndarray) -> DataFrame:
    """(w array<int>): for each row the places of the sorted words that it holds, as a written table."""

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, n, row, at in present(words, batch.column(0)):
                cuts = np.searchsorted(row, np.arange(n + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(cuts), pa.array(at.astype(np.int32)))], ["w"])

    return written(texts.mapInArrow(number, "w array<int>"), "numbered")


def _sparse(lists: pa.Array, d: int) -> Sparse:
    sizes = np.diff(lists.offsets.to_numpy())
    return Sparse(np.repeat(np.arange(len(lists)), sizes), lists.flatten().to_numpy(), (len(lists), d))


def summed(rows: DataFrame, d: int) -> Callable[[np.ndarray], Side]:
    """U's sums at given weights, by a pass over rows(w array<int>); a value for each feature reaches the driver."""

    def at(w: np.ndarray) -> Side:
        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            n, loss, bias, weights = 0.0, 0.0, 0.0, np.zeros(d)
            for batch in batches:
                if batch.num_rows:
                    own = Side.of(_sparse(batch.column(0), d), w)
                    n, loss, bias, weights = n + own.n, loss + own.loss, bias + own.bias, weights + own.weights
            some = np.flatnonzero(weights)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([some, [d, d + 1, d + 2]])), pa.array(np.concatenate([weights[some], [n, loss, bias]]))], ["k", "x"])

        got = rows.mapInArrow(add, "k long, x double").groupBy("k").agg(F.sum("x").alias("x")).toArrow()
        x = np.zeros(d + 3)
        x[got["k"].to_numpy()] = got["x"].to_numpy()
        return Side(max(x[d], 1.0), x[d + 1], x[d + 2], x[:d])

    return at


def fit(
    docs: DataFrame,
    labels: DataFrame,
    key: str = "doc_id",
    text: str = "text",
    max_positive: int = 3000,
    min_g2: float = 24.0,
    min_share: float = 0.6,
    frequent_share: float = 0.01,
    **options: float,
) -> Model:
    """A model from the training folds; options are those of fit_weights. Counts by word, sums by feature and the feature
    numbers of the positives reach the driver."""
    bounded_batches(docs.sparkSession)
    known = labels.where(in_training(F.col(key)) & F.col("toxic").isNotNull()).groupBy(F.col(key).alias("k")).agg(F.max("toxic").alias("toxic"))
    n, n_pos = known.agg(F.count("*"), F.coalesce(F.sum((F.col("toxic") == 1).cast("long")), F.lit(0))).first()
    if not n_pos:
        return Model(*_NONE, 0.0, 0.0)
    prior = min(max(n_pos / n, 1e-3), 0.999)
    chosen = F.broadcast(known.where("toxic = 1").select("k").orderBy(F.xxhash64("k"), "k").limit(max_positive))  # max_positive ids at most
    everything = docs.where(in_training(F.col(key))).select(F.col(text).cast("string").alias("t"))
    # The positives' texts are read again rather than kept: they are few, but each is whole.
    positives = docs.select(F.col(key).alias("k"), F.col(text).cast("string").alias("t")).join(chosen, "k", "left_semi").select("t")

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, row, h in features(batch.column(0)):
                pairs = np.unique(np.stack([row.astype(np.uint64), h]), axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[1].astype(np.int64))], ["word"])

    told = positives.mapInArrow(words, "word long").groupBy("word").agg(F.count("*").alias("p")).where("p >= 3").select("word").toArrow()
    vocabulary = np.union1d(told["word"].to_numpy().astype(np.uint64), frequent(everything, frequent_share))
    if not len(vocabulary):
        return Model(*_NONE, 0.0, prior)
    (n_p, p), (n_all, u) = row_frequency(positives, vocabulary), row_frequency(everything, vocabulary)
    if not n_p or not n_all:
        return Model(*_NONE, 0.0, prior)
    in_p, in_u, share = p / n_p, u / n_all, (p + u) / (n_p + n_all)
    term = lambda a, b: np.where(a > 0, a * np.log(np.maximum(a, 1e-300) / np.maximum(b, 1e-300)), 0.0)
    g2 = 2 * (n_p * (term(in_p, share) + term(1 - in_p, 1 - share)) + n_all * (term(in_u, share) + term(1 - in_u, 1 - share)))
    toxic = prior * in_p / np.maximum(in_u, 1e-300)
    vocabulary = vocabulary[(share < 1) & (g2 >= min_g2) & ((toxic >= min_share) | (toxic < prior))]
    if not len(vocabulary):
        return Model(*_NONE, 0.0, prior)
    own = numbered(positives, vocabulary).toArrow()["w"].combine_chunks()
    w = fit_weights(_sparse(own, len(vocabulary)), summed(numbered(everything, vocabulary), len(vocabulary)), prior, **options)
    return Model(vocabulary, w[:-1], float(w[-1]), prior)


def scored(model: Model, text: Column) -> Column:
    """The score of each whole text, between 0 and 1."""

    @F.arrow_udf("double")
    def score(t: pa.Array) -> pa.Array:
        return pa.array(model.score(t))

    return score(text.cast("string"))
