"""N-gram language-model scores from a sharded Elias-Fano trie.

The documents are dealt into chunks of a few MB by a hash. Two rounds of messages between chunks and shards make the model
and use it:

1. Words. A chunk sends its distinct words with their training counts to the shards that their hashes name. A shard sums
   them and answers with each word's count and its rank by frequency among the shard's words; ranks and shards make word
   numbers of 1 to 4 bytes, exact, and small for frequent words, so that lists of them compress.
2. N-grams. A chunk sends its distinct pairs and triples of numbered words, with their training counts, to the shard that
   the pair's (for a triple, its first two words') hash names. A shard merges what all chunks sent into one trie: level by
   level the words below their parents, as Elias-Fano sequences made monotone by the parent's rank, with monotone
   Elias-Fano pointers from each parent to its children. A pair's entry holds a byte for its quantised smoothed probability
   and one for the quantised weight that it leaves to shorter contexts, a triple's a byte for its probability. The levels
   are mapped into memory. Every chunk's list is answered by context-relative successor search: from the parent's place
   its two pointers, and between them the successor of the word. A chunk scores its documents from the answers.

An n-gram moves once for each chunk that has it, so frequent ones are no burden; shards and chunks are as many as the
input's size asks for; no model is broadcast. The mapping lives as long as its task: no other task reads it, and a
shard's trie is made anew from the messages if its executor is lost.

Probabilities, with counts c from the training documents and Dirichlet priors m2, m3:
p1(w) = (c(w) + 0.5) / (N + 0.5 (V + 1)), from exact counts;
p2(w | v) = a2 + m2 / (c(v) + m2) p1(w), a2 = c(vw) / (c(v) + m2);
p3(w | u v) = a3 + b(u v) p2(w | v), a3 = c(uvw) / (c(uv) + m3), b = m3 / (c(uv) + m3).
a2, a3 and b are stored as bytes, steps of a 24th of a decade, so each is exact to 5 %, and a score to 0.042 for a token
(b a2 errs twice); under 10^-10.5 a value counts as that. Words are told apart by 64-bit hashes, n-grams exactly by their
words' numbers; pairs and triples with a word that no training document has are not sent, as they cannot be in the trie.

Edge cases. A null or empty text is one end token. Repeated rows each count; equal rows are counted before they are dealt.
A chunk holds whole texts, so a very long one makes a long chunk. A null id belongs to the training documents. Without
training documents, N = V = 0 and every word's p1 is 1. Columns other than id and text are not read, whatever their names.
An empty table gives no rows.
"""

from __future__ import annotations

import math
import mmap
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softdep.llm._store import collapsed
from softdep.llm._text import lowered, mixed, pieces, spans, word_hashes

END = np.uint64(0xE7037ED1A0B428DB)
U64 = np.uint64
_POPCOUNT = np.array([bin(i).count("1") for i in range(256)], np.uint8)
#: _NTH[b, k]: place of the k-th set bit of byte b.
_NTH = np.array([([i for i in range(8) if b >> i & 1] + [8] * 8)[:8] for b in range(256)], np.uint8)


def _select(byte_words: np.ndarray, totals: np.ndarray, k: np.ndarray, flip: int) -> np.ndarray:
    """Place of the k-th (from 0) set bit, or clear bit with flip 255, of rows of 8 bytes; totals: such bits before each row."""
    row = np.searchsorted(totals, k, "right") - 1
    b = byte_words[row] ^ np.uint8(flip)
    sums = np.cumsum(_POPCOUNT[b], axis=1, dtype=np.int64)
    left = k - totals[row]
    col = (sums <= left[:, None]).sum(axis=1)
    left = left - np.where(col > 0, sums[np.arange(len(k)), np.maximum(col - 1, 0)], 0)
    return row * 64 + col * 8 + _NTH[b[np.arange(len(k)), col], left]


class EliasFano:
    """A non-decreasing sequence of integers: low bytes as they are, the rest as a bit vector of unary gaps."""

    def __init__(self, size: int, low_bytes: int, low: np.ndarray, high: np.ndarray):
        self.size, self.low_bytes, self.low, self.high = size, low_bytes, low, high
        ones = _POPCOUNT[high].sum(axis=1, dtype=np.int64)
        self.ones = np.concatenate([[0], np.cumsum(ones)[:-1]]).astype(np.int64)
        self.zeros = np.concatenate([[0], np.cumsum(64 - ones)[:-1]]).astype(np.int64)

    @staticmethod
    def encoded(values: np.ndarray) -> bytes:
        n = len(values)
        values = values.astype(np.uint64)
        top = int(values[-1]) if n else 0
        low_bytes = min(7, max(0, -(-int(math.log2(max(1, top // max(1, n)))) // 8)))
        upper = (values >> U64(8 * low_bytes)).astype(np.int64)
        bits = np.zeros(-(-(n + (int(upper[-1]) if n else 0) + 2) // 64) * 64, bool)
        bits[upper + np.arange(n)] = True
        low = values.view(np.uint8).reshape(-1, 8)[:, :low_bytes]
        head = np.array([n, low_bytes, len(bits) // 64], np.int64).tobytes()
        return head + np.packbits(bits, bitorder="little").tobytes() + low.tobytes() + b"\0" * (-n * low_bytes % 8)

    @staticmethod
    def at(buffer: memoryview, start: int) -> tuple[EliasFano, int]:
        n, low_bytes, rows = (int(x) for x in np.frombuffer(buffer, np.int64, 3, start))
        start += 24
        high = np.frombuffer(buffer, np.uint8, rows * 8, start).reshape(rows, 8)
        start += rows * 8
        low = np.frombuffer(buffer, np.uint8, n * low_bytes, start).reshape(n, low_bytes)
        return EliasFano(n, low_bytes, low, high), start + n * low_bytes + (-n * low_bytes % 8)

    def _low(self, i: np.ndarray) -> np.ndarray:
        out = np.zeros((len(i), 8), np.uint8)
        out[:, : self.low_bytes] = self.low[i]
        return out.view(np.uint64).ravel()

    def get(self, i: np.ndarray) -> np.ndarray:
        upper = _select(self.high, self.ones, i, 0) - i
        return (upper.astype(np.uint64) << U64(8 * self.low_bytes)) | self._low(i)

    def find(self, x: np.ndarray, begin: np.ndarray | None = None, end_: np.ndarray | None = None) -> np.ndarray:
        """Index of each value, -1 where there is none: the successor among those of the same upper part, from place begin to
        before end_ if given."""
        out = np.full(len(x), -1, np.int64)
        if not self.size or not len(x):
            return out
        upper = (x >> U64(8 * self.low_bytes)).astype(np.int64)
        last = int(_select(self.high, self.ones, np.array([self.size - 1]), 0)[0]) - (self.size - 1)
        live = np.flatnonzero(upper <= last)
        upper = upper[live]
        hi = _select(self.high, self.zeros, upper, 255) - upper
        lo = np.where(upper > 0, _select(self.high, self.zeros, np.maximum(upper - 1, 0), 255) - np.maximum(upper - 1, 0), 0)
        if begin is not None:
            lo, hi = np.maximum(lo, begin[live]), np.minimum(hi, end_[live])
        want = x[live] & U64((1 << (8 * self.low_bytes)) - 1)
        end = hi.copy()
        while len(open_ := np.flatnonzero(lo < hi)):
            mid = (lo[open_] + hi[open_]) // 2
            below = self._low(mid) < want[open_]
            lo[open_[below]] = mid[below] + 1
            hi[open_[~below]] = mid[~below]
        there = np.flatnonzero(lo < end)
        there = there[self._low(lo[there]) == want[there]]
        out[live[there]] = lo[there]
        return out


#: Bytes to a decade of a probability.
STEPS = 24


def code_of(p: np.ndarray) -> np.ndarray:
    """A byte for each probability: 0 for 0, else 1 and more by its logarithm."""
    with np.errstate(divide="ignore"):
        steps = np.rint(-STEPS * np.log10(p))
    return np.where(p > 0, np.clip(steps, 0, 254) + 1, 0).astype(np.uint8)


_DECODED = np.concatenate([[0.0], 10.0 ** (-np.arange(255) / STEPS)])


def probability_of(codes: np.ndarray) -> np.ndarray:
    return _DECODED[codes]


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys of a positive total, in order, and their totals."""
    keys, counts = keys[counts > 0], counts[counts > 0]
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order].astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else np.zeros(0, np.int64)


class Trie:
    """One shard. The first words of its pairs, pairs below their first word and triples below their pair: each level with
    pointers from its parents, keys made monotone by the parent's rank, and bytes. bits: those of a word's number."""

    def __init__(self, buffer: memoryview, bits: int):
        self.bits = U64(bits)
        self.roots, at = EliasFano.at(buffer, 0)
        self.levels = []
        for width in (2, 1):
            pointers, at = EliasFano.at(buffer, at)
            keys, at = EliasFano.at(buffer, at)
            codes = np.frombuffer(buffer, np.uint8, keys.size * width, at).reshape(width, keys.size)
            self.levels.append((pointers, keys, codes))
            at += -(-keys.size * width // 8) * 8

    @staticmethod
    def encoded(bits: int, first: np.ndarray, last: np.ndarray, pair_codes: np.ndarray, parent: np.ndarray, third: np.ndarray, triple_codes: np.ndarray) -> bytes:
        """Pairs in the order of their first and last words; triples in that of their parents' places, then their third."""
        b = U64(bits)
        pad = lambda x: x + b"\0" * (-len(x) % 8)
        pointers = lambda of, n: EliasFano.encoded(np.searchsorted(of, np.arange(n + 1)))
        roots, rank = np.unique(first, return_inverse=True)
        return b"".join((
            EliasFano.encoded(roots),
            pointers(rank, len(roots)), EliasFano.encoded(rank.astype(np.uint64) << b | last), pad(pair_codes.tobytes()),
            pointers(parent, len(first)), EliasFano.encoded(parent.astype(np.uint64) << b | third), pad(triple_codes.tobytes()),
        ))

    def children(self, level: int, parent: int) -> np.ndarray:
        """Words below a parent."""
        pointers, keys, _ = self.levels[level]
        lo, hi = (int(x) for x in pointers.get(np.array([parent, parent + 1])))
        return keys.get(np.arange(lo, hi)) & U64((1 << int(self.bits)) - 1)

    def _below(self, level: int, parent: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Place of word below each parent, -1 without parent or word. Equal parents stand together, and their pointers are
        read once; the successor is searched between these."""
        pointers, keys, _ = self.levels[level]
        out = np.full(len(parent), -1, np.int64)
        known = np.flatnonzero(parent >= 0)
        if not len(known) or not keys.size:
            return out
        own = parent[known]
        new = np.concatenate([[True], own[1:] != own[:-1]])
        of = np.cumsum(new) - 1
        lo, hi = pointers.get(own[new]).astype(np.int64)[of], pointers.get(own[new] + 1).astype(np.int64)[of]
        some = np.flatnonzero(lo < hi)
        out[known[some]] = keys.find(own[some].astype(np.uint64) << self.bits | word[known[some]], lo[some], hi[some])
        return out

    def codes(self, first: np.ndarray, last: np.ndarray, parent: np.ndarray, third: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The two bytes of pairs, in the order of their words, and the byte of triples given by the places of their first two
        words among these pairs."""
        new = np.concatenate([[True], first[1:] != first[:-1]]) if len(first) else np.zeros(0, bool)
        place = self._below(0, self.roots.find(first[new])[np.cumsum(new) - 1], last)
        below = self._below(1, place[parent], third)
        pick = lambda codes, i: np.where(i >= 0, codes[:, np.maximum(i, 0)], 0).astype(np.uint8) if codes.shape[1] else np.zeros((len(codes), len(i)), np.uint8)
        return pick(self.levels[0][2], place), pick(self.levels[1][2], below)[0]


def _planes(a: np.ndarray, keep: int) -> bytes:
    """The lowest keep bytes of each integer, all first bytes first: what differs little compresses well."""
    return np.ascontiguousarray(a.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :keep].T).tobytes()


def _unplaned(b: bytes, keep: int) -> np.ndarray:
    planes = np.frombuffer(b, np.uint8).reshape(keep, -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, :keep] = planes.T
    return out.view("<u8").ravel()


def _packed(a: np.ndarray, keep: int) -> bytes:
    """As _planes, deflated: for counts and codes, mostly 0 and 1."""
    return zlib.compress(_planes(a, keep), 1)


def _unpacked(b: bytes, keep: int) -> np.ndarray:
    return _unplaned(zlib.decompress(b), keep)


def _width(bits: int) -> int:
    return -(-bits // 8)


@dataclass
class Words:
    """Tokens in text order, each text's words and then its end: the row of each, the distinct words, and each token's."""

    row: np.ndarray
    words: np.ndarray
    at: np.ndarray
    shard: np.ndarray


def words_of(texts: pa.Array, shards: int) -> Words:
    rows, hashes, n = [], [], len(texts)
    for first, data, offs in pieces(texts):
        data = lowered(data)
        r, s, e = spans(data, offs)
        rows.append(r + first)
        hashes.append(word_hashes(data, s, e))
    row = np.concatenate(rows) if rows else np.zeros(0, np.int64)
    token = np.full(len(row) + n, END, np.uint64)
    if len(row):
        token[np.arange(len(row)) + row] = np.concatenate(hashes)
    words, at = np.unique(token, return_inverse=True)
    return Words(np.repeat(np.arange(n), np.bincount(row, minlength=n) + 1), words, at, (mixed(words) % U64(shards)).astype(np.int64))


@dataclass
class Grams:
    """Distinct pairs and triples of numbered words. Tokens at pair_of end a pair, those at triple_of a triple."""

    pairs: np.ndarray
    pair_at: np.ndarray
    pair_of: np.ndarray
    parent: np.ndarray
    third: np.ndarray
    triple_at: np.ndarray
    triple_of: np.ndarray
    shard: np.ndarray


def grams_of(row: np.ndarray, number: np.ndarray, bits: int, shards: int) -> Grams:
    """Of tokens' rows and word numbers, -1 for words that no training document has."""
    b = U64(bits)
    ok = np.zeros(len(row), bool)
    ok[1:] = (row[1:] == row[:-1]) & (number[1:] >= 0) & (number[:-1] >= 0)
    i = np.flatnonzero(ok)
    pairs, pair_at = np.unique(number[i - 1].astype(np.uint64) << b | number[i].astype(np.uint64), return_inverse=True)
    place = np.zeros(len(row), np.int64)
    place[i] = pair_at
    j = np.flatnonzero(ok[1:] & ok[:-1]) + 1
    triples, triple_at = np.unique(place[j - 1].astype(np.uint64) << b | number[j].astype(np.uint64), return_inverse=True)
    return Grams(pairs, pair_at, i, (triples >> b).astype(np.int64), triples & U64((1 << bits) - 1), triple_at, j, (mixed(pairs) % U64(shards)).astype(np.int64))


def _by_shard(shard: np.ndarray, shards: int) -> list[np.ndarray]:
    order = np.argsort(shard, kind="stable")
    return np.split(order, np.searchsorted(shard[order], np.arange(1, shards)))


def _slices(g: Grams, shards: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """For each shard the places of its pairs and of its triples, and the triples' parents among these pairs. Both sides of
    the exchange use this order, which is that of the words."""
    rank = np.empty(len(g.pairs), np.int64)
    for s, (p, r) in enumerate(zip(_by_shard(g.shard, shards), _by_shard(g.shard[g.parent], shards), strict=True)):
        rank[p] = np.arange(len(p))
        yield s, p, r, rank[g.parent[r]]


def _table(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    return pa.Table.from_pylist([dict(zip(schema.names, x, strict=True)) for x in rows], schema)


def _schema(*names: str) -> pa.Schema:
    kinds = {"shard": pa.int32(), "chunk": pa.int32(), "n": pa.int64(), "v": pa.int64(), "bits": pa.int32()}
    return pa.schema([(n, kinds.get(n, pa.binary())) for n in names])


def _ddl(schema: pa.Schema) -> str:
    kinds = {pa.int32(): "int", pa.int64(): "long", pa.binary(): "binary"}
    return ", ".join(f"{f.name} {kinds[f.type]}" for f in schema)


_TOLD = _schema("shard", "chunk", "words", "word_counts")
_WORDS = _schema("chunk", "shard", "n", "v", "counts", "ranks")
_SENT = _schema("shard", "chunk", "bits", "first_gaps", "lasts", "pair_counts", "first_counts", "children", "thirds", "triple_counts")
_BACK = _schema("chunk", "shard", "pair_codes", "triple_codes")


def _learnt(t: pa.Table) -> np.ndarray:
    """How often each row counts in training."""
    return np.asarray(t["learn"].combine_chunks()).astype(np.float64) * np.asarray(t["times"].combine_chunks())


def _told(shards: int) -> Callable[[pa.Table], pa.Table]:
    """Round 1: of each chunk its words and their training counts, a row for each shard."""

    def tell(t: pa.Table) -> pa.Table:
        w = words_of(t["text"].combine_chunks(), shards)
        counts = np.bincount(w.at, _learnt(t)[w.row], len(w.words)).astype(np.int64)
        key = t["chunk"][0].as_py()
        return _table([(s, key, _planes(np.diff(w.words[i], prepend=U64(0)), 8), _packed(counts[i], 8)) for s, i in enumerate(_by_shard(w.shard, shards))], _TOLD)

    return tell


def _numbered(t: pa.Table) -> pa.Table:
    """A shard sums its words and tells every chunk their counts and, of those in training documents, ranks."""
    asked = [(np.cumsum(_unplaned(r["words"], 8)), _unpacked(r["word_counts"], 8)) for r in t.to_pylist()]
    words, counts = _summed(np.concatenate([w for w, _ in asked]), np.concatenate([c for _, c in asked]))
    n, v, out = int(counts.sum()), len(words), []
    rank = np.empty(v, np.int64)
    rank[np.lexsort((words, -counts))] = np.arange(v)
    for (own, _), chunk, shard in zip(asked, t["chunk"].to_pylist(), t["shard"].to_pylist(), strict=True):
        at = np.searchsorted(words, own)
        known = np.zeros(len(own), bool)
        known[at < v] = words[at[at < v]] == own[at < v]
        told = np.zeros(len(own), np.int64)
        told[known] = counts[at[known]]
        out.append((chunk, shard, n, v, _packed(told, 8), _planes(rank[at[known]], 4)))
    return _table(out, _WORDS)


def _known(w: Words, answers: dict[int, dict], shards: int) -> tuple[int, int, int, np.ndarray, np.ndarray]:
    """N, V, the bits of a word's number, and of each of the chunk's words its count and number, -1 for unknown ones."""
    count, number = np.zeros(len(w.words), np.int64), np.full(len(w.words), -1, np.int64)
    n = v = most = 0
    for s, i in enumerate(_by_shard(w.shard, shards)):
        a = answers[s]
        count[i] = _unpacked(a["counts"], 8).astype(np.int64)
        number[i[count[i] > 0]] = _unplaned(a["ranks"], 4).astype(np.int64) * shards + s
        n, v, most = n + a["n"], v + a["v"], max(most, a["v"])
    return n, v, max(1, (most * shards).bit_length()), count, number


def _sent(shards: int) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """Round 2: of each chunk its pairs and triples with their training counts, and the counts of the pairs' first words, a
    row for each shard."""

    def send(t: pa.Table, numbers: pa.Table) -> pa.Table:
        if not t.num_rows:
            return _SENT.empty_table()
        w = words_of(t["text"].combine_chunks(), shards)
        _, _, bits, count, number = _known(w, {r["shard"]: r for r in numbers.to_pylist()}, shards)
        g = grams_of(w.row, number[w.at], bits, shards)
        learn = _learnt(t)[w.row]
        pair_counts = np.bincount(g.pair_at, learn[g.pair_of], len(g.pairs)).astype(np.int64)
        triple_counts = np.bincount(g.triple_at, learn[g.triple_of], len(g.third)).astype(np.int64)
        order = np.argsort(number, kind="stable")
        keep, key, out = _width(bits), t["chunk"][0].as_py(), []
        for s, p, r, parent in _slices(g, shards):
            first = g.pairs[p] >> U64(bits)
            new = np.concatenate([[True], first[1:] != first[:-1]]) if len(first) else np.zeros(0, bool)
            own = count[order[np.searchsorted(number, first[new].astype(np.int64), sorter=order)]]
            out.append((s, key, bits, _planes(np.diff(first, prepend=U64(0)), keep), _planes(g.pairs[p] & U64((1 << bits) - 1), keep), _packed(pair_counts[p], 4), _packed(own, 8), _packed(np.bincount(parent, minlength=len(p)), 4), _planes(g.third[r], keep), _packed(triple_counts[r], 4)))
        return _table(out, _SENT)

    return send


def _received(t: pa.Table) -> list[tuple[np.ndarray, ...]]:
    """Of each chunk: first and last words of pairs, counts, counts of the first words, the triples' parents among the pairs,
    third words, counts."""
    out = []
    for r in t.to_pylist():
        keep = _width(r["bits"])
        first = np.cumsum(_unplaned(r["first_gaps"], keep))
        run = np.cumsum(np.concatenate([[True], first[1:] != first[:-1]]) if len(first) else np.zeros(0, bool)) - 1
        parent = np.repeat(np.arange(len(first)), _unpacked(r["children"], 4).astype(np.int64))
        out.append((first, _unplaned(r["lasts"], keep), _unpacked(r["pair_counts"], 4), _unpacked(r["first_counts"], 8)[run], parent, _unplaned(r["thirds"], keep), _unpacked(r["triple_counts"], 4)))
    return out


def trie_of(parts: list[tuple[np.ndarray, ...]], bits: int, m2: float, m3: float) -> bytes:
    """A shard's trie of what all chunks sent."""
    b = U64(bits)
    every = np.concatenate([p[0] << b | p[1] for p in parts])
    pairs, counts = _summed(every, np.concatenate([p[2] for p in parts]))
    at = np.minimum(np.searchsorted(pairs, every), max(len(pairs) - 1, 0))
    first_counts = np.zeros(len(pairs))
    hit = pairs[at] == every if len(pairs) else np.zeros(len(every), bool)
    first_counts[at[hit]] = np.concatenate([p[3] for p in parts])[hit]  # the same from every chunk
    seen = np.concatenate([p[6] for p in parts]) > 0
    above = np.concatenate([(p[0] << b | p[1])[p[4]] for p in parts])[seen]
    parent = np.searchsorted(pairs, above).astype(np.uint64)
    triples, triple_counts = _summed(parent << b | np.concatenate([p[5] for p in parts])[seen], np.concatenate([p[6] for p in parts])[seen])
    parent = (triples >> b).astype(np.int64)
    codes = np.stack([code_of(counts / (first_counts + m2)), code_of(m3 / (counts + m3))])
    return Trie.encoded(bits, pairs >> b, pairs & U64((1 << bits) - 1), codes, parent, triples & U64((1 << bits) - 1), code_of(triple_counts / (counts[parent] + m3)))


def _answered(m2: float, m3: float) -> Callable[[pa.Table], pa.Table]:
    """A shard builds its trie and answers every chunk."""

    def answer(t: pa.Table) -> pa.Table:
        parts = _received(t)
        bits = t["bits"][0].as_py()
        blob = trie_of(parts, bits, m2, m3)
        with mmap.mmap(-1, max(len(blob), 1)) as held:
            held[: len(blob)] = blob
            del blob
            trie = Trie(memoryview(held), bits)
            back = []
            for (first, last, _, _, parent, third, _), chunk, shard in zip(parts, t["chunk"].to_pylist(), t["shard"].to_pylist(), strict=True):
                two, three = trie.codes(first, last, parent, third)
                back.append((chunk, shard, zlib.compress(two.tobytes(), 1), zlib.compress(three.tobytes(), 1)))
            out = _table(back, _BACK)
            del trie
            try:
                held.close()
            except BufferError:  # views on it live on until they are collected
                pass
        return out

    return answer


def _scored(shards: int, m2: float, m3: float) -> Callable[[pa.Table, pa.Table], pa.Table]:
    def score(docs: pa.Table, back: pa.Table) -> pa.Table:
        rows = back.to_pylist()
        w = words_of(docs["text"].combine_chunks(), shards)
        n, v, bits, count, number = _known(w, {r["shard"]: r for r in rows if r["counts"] is not None}, shards)
        g = grams_of(w.row, number[w.at], bits, shards)
        answers = {r["shard"]: r for r in rows if r["pair_codes"] is not None}
        a2, left, a3 = np.zeros(len(g.pairs)), np.ones(len(g.pairs)), np.zeros(len(g.third))
        for s, p, r, _ in _slices(g, shards):
            codes = np.frombuffer(zlib.decompress(answers[s]["pair_codes"]), np.uint8).reshape(2, len(p))
            a2[p] = probability_of(codes[0])
            left[p] = np.where(codes[1] > 0, probability_of(codes[1]), 1.0)
            a3[r] = probability_of(np.frombuffer(zlib.decompress(answers[s]["triple_codes"]), np.uint8))
        own = count[w.at].astype(np.float64)
        p1 = (own + 0.5) / max(n + 0.5 * (v + 1), 0.5)
        p = p1.copy()
        inside = np.flatnonzero(w.row[1:] == w.row[:-1]) + 1
        p[inside] = m2 / (own[inside - 1] + m2) * p1[inside]
        p[g.pair_of] += a2[g.pair_at]
        place = np.full(len(own), -1, np.int64)
        place[g.pair_of] = g.pair_at
        deep = inside[(inside > 1) & (w.row[inside] == w.row[inside - 2]) & (place[inside - 1] >= 0)]  # tokens after a known pair
        p[deep] *= left[place[deep - 1]]
        p[g.triple_of] += a3[g.triple_at]
        total = lambda x: np.bincount(w.row, weights=x, minlength=len(docs))
        return pa.table({
            "key": docs["key"], "times": docs["times"], "learn": docs["learn"], "n_tokens": pa.array(np.bincount(w.row, minlength=len(docs)).astype(np.int64)), "n_known": pa.array(total(own > 0).astype(np.int64)),
            "train_tokens": pa.array(np.full(len(docs), n, np.int64)), "base_score": pa.array(total(np.log10(p1))), "score": pa.array(total(np.log10(np.minimum(p, 1.0)))),
        })

    return score


def scores(docs: DataFrame, learn: Column, key: str = "doc_id", text: str = "text", m2: float = 4000.0, m3: float = 10.0, chunk_chars: int = 8_000_000) -> DataFrame:
    """(key, learn, n_tokens, n_known, train_tokens, base_score, score) of every document; learn, a column of the key called
    key, marks the training documents."""
    rows = collapsed(docs, key, text)
    chars = rows.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    chunks = int(chars // chunk_chars) + 1
    shards = chunks // 2 + 1
    number = F.pmod(F.xxhash64("key", "text"), F.lit(chunks)).cast("int")
    dealt = rows.select("key", F.coalesce(learn, F.lit(True)).alias("learn"), "text", "times", number.alias("chunk")).repartition(chunks, "chunk")
    told = dealt.groupBy("chunk").applyInArrow(_told(shards), _ddl(_TOLD))
    numbers = told.groupBy("shard").applyInArrow(_numbered, _ddl(_WORDS))
    sent = dealt.groupBy("chunk").cogroup(numbers.groupBy("chunk")).applyInArrow(_sent(shards), _ddl(_SENT))
    back = sent.groupBy("shard").applyInArrow(_answered(m2, m3), _ddl(_BACK))
    side = numbers.unionByName(back, allowMissingColumns=True)
    ddl = f"key {dict(rows.dtypes)['key']}, times long, learn boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    out = dealt.groupBy("chunk").cogroup(side.groupBy("chunk")).applyInArrow(_scored(shards, m2, m3), ddl)
    return out.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "times"))).drop("times", "copy")
