"""Benchmark passages in documents, verbatim or paraphrased, by latent semantic retrieval.

1. Statistics. The words of the benchmark are the terms; their document frequencies are counted over all documents.
2. Space. A randomised SVD of the TF-IDF matrix A of the benchmark's passages: partitions multiply their rows by a random
   matrix and back, sums of the products A'(A M) are added by blocks of terms, and only terms x rank matrices reach the
   driver. The right singular vectors span the latent space.
3. Search. Every document, whole, becomes overlapping windows of words; a window's latent vector is compared with all
   passages of the benchmark block. Candidates have a cosine of at least min_cosine and project on the passage's vector
   at least min_projection of its length (a window that contains the passage among other words projects in full).
4. Counting. What the space holds badly is found without it: a leak keeps T of an item's L words, so of any L - T + r of
   them it keeps r. Each item is watched for by its rarest words, r of them within a stretch of a quarter more than its
   length, with the r of least expected work. No leak within such a stretch is lost, whatever the rank and the cosines.
5. Check. A candidate's item and the words around it are compared word by word: coverage is the length of the
   longest common subsequence over that of the item. It is a leak at coverage >= sure, or at >= likely where the item's
   answer (its last line, or else its last quarter) is covered as well as that.

The benchmark is taken in blocks of at most block_items items, each with a pass over the documents, so that what goes to
the executors is bounded whatever its size. Documents are never shuffled.

Items of fewer than min_words words are too short for a share of them to tell: they match where all their words stand in a
row, items of one or two words only where they are the whole document.

Edge cases. Words are runs of ASCII letters, digits and non-ASCII bytes; Latin-1 capitals count as small letters. Null and
empty texts, and items without words, hold nothing. Very long texts are searched whole. Items of equal text are each
reported, and of equally good stretches the first; repeated document rows give repeated hits. An empty table on either side
gives no hit. A null item id is reported as null. clean keeps all columns, whatever their names; leaks reads only id and text.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass
from itertools import chain, islice

import numpy as np
import pyarrow as pa
from pyspark import Broadcast, cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from softdep.llm._store import bounded_batches
from softdep.llm._text import Hashes, lowered_latin, mixed, pieces, spans

APART = tuple(b for b in range(128) if not chr(b).isalnum())
#: Windows are made of blocks of so many words.
BLOCK = 12


def common_words(a: np.ndarray, b: np.ndarray) -> int:
    """Length of the longest common subsequence, bit-parallel over a."""
    places: dict[int, int] = {}
    for i, w in enumerate(a.tolist()):
        places[w] = places.get(w, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for w in b.tolist():
        m = places.get(w)
        if m:
            u = row & m
            row = ((row + u) | (row - u)) & full
    return len(a) - row.bit_count()


def word_rows(texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, rows, row, word hash) of runs of texts."""
    for first, data, offs in pieces(texts):
        data = lowered_latin(data)
        row, start, end = spans(data, offs, APART)
        yield first, len(offs) - 1, row, Hashes(data).of(start, end)


def words_of(text: str | None) -> np.ndarray:
    return np.concatenate([np.zeros(0, np.uint64), *(h for *_, h in word_rows(pa.array([text or ""])))])


@dataclass(frozen=True)
class Items:
    """A block of the benchmark: ids, words and answers; passages are (item, first word, end) of the long items, and short
    holds the places of the others."""

    ids: list
    words: list[np.ndarray]
    answers: list[np.ndarray]
    passages: list[tuple[int, int, int]]
    short: list[int]

    @staticmethod
    def of(rows: Iterable[tuple], min_words: int, passage_words: int) -> Items:
        out = Items([], [], [], [], [])
        for key, text, answer in rows:
            w = words_of(text)
            if not len(w):
                continue
            if len(w) < min_words:
                out.short.append(len(out.ids))
                out.ids.append(key)
                out.words.append(w)
                out.answers.append(w)
                continue
            last = words_of(answer) if answer is not None else words_of((text or "").strip().rpartition("\n")[2]) if "\n" in (text or "").strip() else w[-max(3, len(w) // 4) :]
            n = -(-len(w) // passage_words)
            cuts = [round(i * len(w) / n) for i in range(n + 1)]
            out.passages.extend((len(out.ids), a, b) for a, b in zip(cuts, cuts[1:], strict=False))
            out.ids.append(key)
            out.words.append(w)
            out.answers.append(last)
        return out


def _runs(h: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of size words."""
    n = max(0, len(h) - size + 1)
    out = np.zeros(n, np.uint64)
    for k in range(size):
        out = mixed(out * np.uint64(0x9E3779B97F4A7C15) + h[k : k + n])
    return out


@dataclass(frozen=True)
class Short:
    """Items matched by all their words in a row: of each length the hashes in order and their items."""

    by_length: dict[int, tuple[np.ndarray, np.ndarray]]

    @staticmethod
    def of(items: Items) -> Short:
        lengths: dict[int, list[tuple[int, int]]] = {}
        for i in items.short:
            w = items.words[i]
            lengths.setdefault(len(w), []).append((int(_runs(w, len(w))[0]), i))
        return Short({n: (np.array([h for h, _ in sorted(x)], np.uint64), np.array([i for _, i in sorted(x)])) for n, x in lengths.items()})

    def found(self, n: int, row: np.ndarray, h: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """(row, item, first word, end)."""
        first = np.searchsorted(row, np.arange(n + 1))
        for size, (hashes, of) in self.by_length.items():
            runs = _runs(h, size)
            lo, hi = np.searchsorted(hashes, runs, "left"), np.searchsorted(hashes, runs, "right")
            for x in np.flatnonzero(hi > lo):
                r = row[x]
                if row[x + size - 1] == r and (size > 2 or first[r + 1] - first[r] == size):
                    for k in range(lo[x], hi[x]):
                        yield int(r), int(of[k]), int(x - first[r]), int(x - first[r] + size)


def _place(terms: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Index of each word in the sorted terms, -1 for others."""
    at = np.minimum(np.searchsorted(terms, words), len(terms) - 1)
    return np.where(terms[at] == words, at, -1)


def document_frequency(docs: DataFrame, terms: np.ndarray, text: str = "text") -> tuple[int, np.ndarray, int, np.ndarray]:
    """Number of documents, of those with each term, of words, and of occurrences of each term; all documents count."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, times = np.zeros(len(terms), np.int64), np.zeros(len(terms), np.int64)
        docs_seen = words_seen = 0
        for batch in batches:
            docs_seen += batch.num_rows
            for _, _, row, h in word_rows(batch.column(0)):
                at = _place(terms, h)
                words_seen += len(at)
                times += np.bincount(at[at >= 0], minlength=len(terms))
                pairs = np.unique(row[at >= 0] * len(terms) + at[at >= 0])
                total += np.bincount(pairs % len(terms), minlength=len(terms))
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(total[some], docs_seen)), pa.array(np.append(times[some], words_seen))], ["term", "n", "times"])

    got = docs.select(F.col(text).cast("string")).mapInArrow(count, "term long, n long, times long").groupBy("term").agg(F.sum("n").alias("n"), F.sum("times").alias("times")).toArrow()
    df, times = np.zeros(len(terms) + 1, np.int64), np.zeros(len(terms) + 1, np.int64)
    at = got["term"].to_numpy()  # -1, the totals, is the last place
    df[at], times[at] = got["n"].to_numpy(), got["times"].to_numpy()
    return int(df[-1]), df[:-1], int(times[-1]), times[:-1]


def gram_times(passages: DataFrame, terms: np.ndarray, idf: np.ndarray, m: np.ndarray, block: int = 2048) -> np.ndarray:
    """A'(A m) for the TF-IDF matrix A of passages(words array<long>), added up by blocks of terms."""
    n = m.shape[1]

    def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(terms), n), np.float64)
        for batch in batches:
            for ws in batch.column(0):
                at = _place(terms, np.array(ws.as_py(), np.int64).astype(np.uint64))
                t, tf = np.unique(at[at >= 0], return_counts=True)
                a = tf * idf[t]
                total[t] += np.outer(a, a @ m[t])
        starts = range(0, len(terms), block)
        yield pa.RecordBatch.from_arrays([pa.array([s // block for s in starts], pa.int32()), pa.array([total[s : s + block].astype(np.float32).tobytes() for s in starts], pa.binary())], ["block", "part"])

    def add(t: pa.Table) -> pa.Table:
        return pa.table({"block": t["block"][:1], "part": pa.array([sum(np.frombuffer(x, np.float32) for x in t["part"].to_pylist()).astype(np.float32).tobytes()], pa.binary())})

    parts = passages.mapInArrow(multiply, "block int, part binary").groupBy("block").applyInArrow(add, "block int, part binary").collect()
    return np.concatenate([np.frombuffer(r["part"], np.float32).reshape(-1, n) for r in sorted(parts, key=lambda r: r["block"])]) if parts else np.zeros((len(terms), n), np.float32)


def latent_space(spark: SparkSession, items: Items, terms: np.ndarray, idf: np.ndarray, rank: int, seed: int = 7, spare: int = 16) -> np.ndarray:
    """terms x rank: right singular vectors of the passages' TF-IDF matrix, by a randomised range finder on its Gram matrix."""
    rows = [([int(x) for x in items.words[i][a:b].astype(np.int64)],) for i, a, b in items.passages]
    passages = spark.createDataFrame(rows, "words array<long>").repartition(max(1, min(8, len(rows) // 64)))
    width = min(rank + spare, len(rows), len(terms))
    random = np.random.default_rng(seed).standard_normal((len(terms), width)).astype(np.float32)
    q, _ = np.linalg.qr(gram_times(passages, terms, idf, random).astype(np.float64))
    core = q.T @ gram_times(passages, terms, idf, q.astype(np.float32)).astype(np.float64)
    value, vector = np.linalg.eigh((core + core.T) / 2)
    keep = [k for k in np.argsort(-value)[:rank] if value[k] > 1e-6 * max(value.max(), 1e-30)]
    return (q @ vector[:, keep]).astype(np.float32)


def _stretch(words: int) -> tuple[int, int]:
    """Length of the parts compared with an item, and the step from one to the next."""
    return words + words // 2, max(1, words // 4)


@dataclass(frozen=True)
class Watch:
    """Word hashes in order, the items each is watched for (from start on), and how many of an item's make a candidate."""

    words: np.ndarray
    start: np.ndarray
    items: np.ndarray
    need: np.ndarray
    span: np.ndarray

    @staticmethod
    def of(items: Items, terms: np.ndarray, share: np.ndarray, least: float, check_cost: float = 2000.0) -> Watch:
        """share: of all words of the documents, by term; least: the coverage below which nothing is a leak; check_cost: a
        candidate's work over that of an occurrence of a watched word."""
        pairs, needs, spans_ = [np.zeros((2, 0), np.int64)], [], []
        short = set(items.short)
        for i, words in enumerate(items.words):
            if i in short:  # watched for by none of its words
                needs.append(1)
                spans_.append(1)
                continue
            n = len(words)
            kept = max(1, int(np.ceil(least * n - 1e-9)))
            at = _place(terms, words)
            at = at[np.lexsort((at, share[at]))]
            new = np.concatenate([[True], at[1:] != at[:-1]])
            part, step = _stretch(n)
            need = np.arange(1, kept + 1)
            rate = np.maximum(np.cumsum(np.where(new, share[at], 0.0)), 1e-15)[n - kept + need - 1]
            # Poisson tail of need - 1 more within the span, by its exponential bound.
            mean, more = rate * (part - step), need - 1
            tail = np.exp(np.where(more > mean, more - mean - more * np.log(np.maximum(more, 1) / mean), 0.0))
            r = int(np.argmin(rate * (1 + check_cost * tail))) + 1
            own = np.unique(at[: n - kept + r])
            pairs.append(np.stack([own, np.full(len(own), i)]))
            needs.append(r)
            spans_.append(part - step)
        at, of = np.concatenate(pairs, axis=1)
        order = np.argsort(at, kind="stable")
        seen, start = np.unique(at[order], return_index=True)
        return Watch(terms[seen], np.append(start, len(at)), of[order], np.array(needs), np.array(spans_))

    def candidates(self, n: int, row: np.ndarray, h: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """(row, item, first word, end) of stretches that hold enough of an item's watched words, each with all the words
        that a leak there can reach."""
        if not len(self.words):
            return
        at = _place(self.words, h)
        some = np.flatnonzero(at >= 0)
        if not len(some):
            return
        at = at[some]
        many = self.start[at + 1] - self.start[at]
        within = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        item, place = np.divmod(np.sort(self.items[np.repeat(self.start[at], many) + within] * len(h) + np.repeat(some, many)), len(h))
        last = np.arange(len(item)) + self.need[item] - 1
        a = np.flatnonzero(last < len(item))
        b = last[a]
        near = (item[a] == item[b]) & (place[b] - place[a] < self.span[item[a]])
        a, b = a[near], b[near]
        a, b = (x[row[place[a]] == row[place[b]]] for x in (a, b))
        if not len(a):
            return
        first = np.searchsorted(row, np.arange(n + 1))
        i, r = item[a], row[place[a]]
        lo = np.maximum(place[b] + 1 - self.span[i], first[r]) - first[r]
        hi = np.minimum(place[a] + self.span[i], first[r + 1]) - first[r]
        new = np.concatenate([[True], (i[1:] != i[:-1]) | (r[1:] != r[:-1]) | (lo[1:] > hi[:-1])])
        begin = np.flatnonzero(new)
        end = np.append(begin[1:], len(a)) - 1
        yield from zip(r[begin].tolist(), i[begin].tolist(), lo[begin].tolist(), hi[end].tolist(), strict=True)


@dataclass(frozen=True)
class Search:
    items: Items
    watch: Watch
    short: Short
    terms: np.ndarray
    weights: np.ndarray  # terms x rank: idf times latent vector
    window: int
    min_cosine: float
    min_projection: float
    sure: float
    likely: float

    def passages(self) -> np.ndarray:
        out = np.zeros((len(self.items.passages), self.weights.shape[1]), np.float32)
        for k, (i, a, b) in enumerate(self.items.passages):
            at = _place(self.terms, self.items.words[i][a:b])
            out[k] = self.weights[at[at >= 0]].sum(axis=0)
        return out

    def candidates(self, n: int, row: np.ndarray, h: np.ndarray, targets: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """(row, item, first word, end) of windows near a passage in the space; words count from the row's first."""
        if not len(targets):
            return
        first = np.searchsorted(row, np.arange(n + 1))
        blocks = -(-np.diff(first) // BLOCK)
        base = np.concatenate([[0], np.cumsum(blocks)])
        if not base[-1]:
            return
        at = _place(self.terms, h)
        some = np.flatnonzero(at >= 0)
        if not len(some):
            return
        of = base[row[some]] + (some - first[row[some]]) // BLOCK
        new = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]]))
        sums = np.zeros((base[-1] + 1, self.weights.shape[1]), np.float32)
        sums[of[new] + 1] = np.add.reduceat(self.weights[at[some]], new, axis=0)
        np.cumsum(sums, axis=0, out=sums)
        start = np.arange(base[-1])
        owner = np.repeat(np.arange(n), blocks)
        end = np.minimum(start + self.window // BLOCK, base[owner + 1])
        size = np.linalg.norm(targets, axis=1)
        unit = targets / np.maximum(size, 1e-12)[:, None]
        need = np.where(size > 0, self.min_projection * size, np.inf).astype(np.float32)
        least = need.min(initial=np.inf)
        for s in range(0, len(start), 8192):
            v = sums[end[s : s + 8192]] - sums[start[s : s + 8192]]
            norm = np.sqrt(np.einsum("ij,ij->i", v, v))
            far = np.flatnonzero(norm >= least)  # a shorter vector projects too little on any passage
            dot = v[far] @ unit.T
            hit = (dot >= need) & (dot >= self.min_cosine * norm[far, None])
            for w, p in zip(*np.nonzero(hit), strict=True):
                w = far[w]
                b = start[s + w]
                r = owner[s + w]
                yield int(r), self.items.passages[p][0], int((b - base[r]) * BLOCK), int(min((end[s + w] - base[r]) * BLOCK, first[r + 1] - first[r]))

    def stretches(self, n: int, row: np.ndarray, h: np.ndarray, targets: np.ndarray, first: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """The candidates with the words around them."""
        for r, i, a, b in self.candidates(n, row, h, targets):
            size = len(self.items.words[i])
            slack = max(self.window // 2, size + size // 4 - (b - a) // 2)
            yield r, i, max(0, a - slack), int(min(first[r + 1] - first[r], b + slack))

    def found(self, texts: pa.Array) -> dict[tuple[int, int], tuple[float, float, int, int]]:
        """(row, item): (coverage, answer's coverage, first word, end) of each leak."""
        targets = self.passages()
        found: dict[tuple[int, int], tuple[float, float, int, int]] = {}
        for origin, n, row, h in word_rows(texts):
            first = np.searchsorted(row, np.arange(n + 1))
            for r, i, lo, hi in self.short.found(n, row, h):
                found.setdefault((origin + r, i), (1.0, 1.0, lo, hi))
            seen: set[tuple[int, int, int, int]] = set()
            for r, i, lo, hi in chain(self.stretches(n, row, h, targets, first), self.watch.candidates(n, row, h)):
                if (r, i, lo, hi) in seen or found.get((origin + r, i), (0.0,))[0] == 1.0:
                    continue
                seen.add((r, i, lo, hi))
                item, answer, text = self.items.words[i], self.items.answers[i], h[first[r] : first[r + 1]]
                # The item may begin anywhere in the stretch: the best of parts of one and a half times its length.
                part, step = _stretch(len(item))
                for x in range(lo, max(lo + 1, hi - part + step), step):
                    words = text[x : min(x + part, hi)]
                    best = common_words(item, words) / len(item)
                    if best < min(self.sure, self.likely) or best <= found.get((origin + r, i), (0.0,))[0]:
                        continue
                    told = common_words(answer, words) / len(answer) if len(answer) else 1.0
                    if best >= self.sure or told >= self.likely:
                        found[(origin + r, i)] = (best, told, x, min(x + part, hi))
        return found

    def hits(self, batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = sorted(self.found(batch.column(1)).items())
            keys = batch.column(0).take(pa.array([r for (r, _), _ in rows], pa.int64()))
            ids = pa.array([self.items.ids[i] for (_, i), _ in rows], schema.field(1).type)
            yield pa.RecordBatch.from_arrays([keys, ids, *(pa.array([x[k] for _, x in rows], schema.field(2 + k).type) for k in range(4))], schema=schema)


def _telling(items: Items, terms: np.ndarray, df: np.ndarray, most: float, least: int = 8) -> np.ndarray:
    """The terms in at most that many documents, and of every passage at least its few rarest."""
    keep = df <= most
    for i, a, b in items.passages:
        own = np.unique(_place(terms, items.words[i][a:b]))
        if keep[own].sum() < least:
            keep[own[np.lexsort((own, df[own]))[:least]]] = True
    return keep


def searches(
    docs: DataFrame,
    benchmark: DataFrame,
    text: str = "text",
    item_key: str = "item_id",
    rank: int = 128,
    window: int = 48,
    passage_words: int = 36,
    min_words: int = 8,
    max_share: float = 0.1,
    min_cosine: float = 0.3,
    min_projection: float = 0.55,
    sure: float = 0.8,
    likely: float = 0.65,
    block_items: int = 20_000,
) -> Iterator[Search]:
    """A search for each block of the benchmark. Terms in more than max_share of all documents do not count in the vectors,
    unless a passage has few others; all words count in the check."""
    spark = docs.sparkSession
    bounded_batches(spark)
    answer = F.col("answer").cast("string") if "answer" in benchmark.columns else F.lit(None).cast("string")
    rows = benchmark.select(F.col(item_key), F.col("text").cast("string"), answer).toLocalIterator()
    slim = docs.select(F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    while block := list(islice(rows, block_items)):
        items = Items.of((tuple(r) for r in block), min_words, passage_words)
        if not items.ids:
            continue
        terms = np.unique(np.concatenate(items.words))
        n, df, n_words, times = document_frequency(slim, terms)
        watch = Watch.of(items, terms, times / max(n_words, 1), min(sure, likely))
        rare = _telling(items, terms, df, max_share * n)
        terms, idf = terms[rare], np.log((n + 1) / (df[rare] + 1)) + 1e-3
        space = latent_space(spark, items, terms, idf, rank) if items.passages and len(terms) else np.zeros((len(terms), 0))
        yield Search(items, watch, Short.of(items), terms, (space * idf[:, None]).astype(np.float32), window, min_cosine, min_projection, sure, likely)


def leaks(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", **options: float) -> DataFrame:
    """(key, item_id, coverage, answer_coverage, first_word, end_word) of each document and item it leaks."""
    spark = docs.sparkSession
    arrow = {"bigint": pa.int64(), "int": pa.int32()}
    kinds = [dict(docs.select(F.col(key).alias("k")).dtypes)["k"], dict(benchmark.select(F.col(item_key).alias("k")).dtypes)["k"]]
    ddl = f"key {kinds[0]}, item_id {kinds[1]}, coverage double, answer_coverage double, first_word long, end_word long"
    schema = pa.schema([("key", arrow.get(kinds[0], pa.string())), ("item_id", arrow.get(kinds[1], pa.string())), ("coverage", pa.float64()), ("answer_coverage", pa.float64()), ("first_word", pa.int64()), ("end_word", pa.int64())])
    slim = docs.select(F.col(key).alias("key"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    out = spark.createDataFrame([], ddl)
    for search in searches(docs, benchmark, text, item_key, **options):
        held = _sent(spark, search)
        out = out.unionByName(slim.mapInArrow(lambda batches, held=held: pickle.loads(held.value).hits(batches, schema), ddl))
    return out


def _sent(spark: SparkSession, search: Search) -> Broadcast:
    """A search for the executors, its class along with it."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(search))


def _flag(held: Broadcast) -> Callable[[Column], Column]:
    kept: list[Search] = []  # filled once in each task

    @F.arrow_udf("boolean")
    def leaking(t: pa.Array) -> pa.Array:
        if not kept:
            kept.append(pickle.loads(held.value))
        hit = np.zeros(len(t), bool)
        hit[[r for r, _ in kept[0].found(t)]] = True
        return pa.array(hit)

    return leaking


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_key: str = "item_id", **options: float) -> DataFrame:
    """The documents that leak no item, with all their columns; no exchange."""
    out = docs
    for search in searches(docs, benchmark, text, item_key, **options):
        out = out.where(~_flag(_sent(docs.sparkSession, search))(F.coalesce(F.col(text).cast("string"), F.lit(""))))
    return out
