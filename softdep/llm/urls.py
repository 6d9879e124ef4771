"""URL rules as one bit-parallel automaton.

Every rule is a glob (* any run, ? any byte) over the canonical form "." host 0xFF path, in bytes; 0xFF never occurs in
UTF-8, so a glob cannot match across the border of host and path. The positions of all globs are packed into 64-bit words.
A step of Shift-And moves all of them at once: states shift by one (carrying between words), are masked with the byte's
word row, and positions before a * keep themselves alive. URLs of a batch advance together, a byte at a time, so the cost
is bytes x words for any number of rules; the masks are as large as the rule list, a parameter.

Edge cases. A null URL, or one without "://", has an empty host and path; very long ones are read whole, and only they are
still alive in later steps. Ties between rules of one length go to the earlier rule. Repeated rows are judged alike; an empty
rule list matches nothing, an empty table gives no rows. judged is a column: it reads the two it is given, whatever the names
of the others.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

BORDER = b"\xff"


@dataclass(frozen=True)
class Rule:
    name: str
    action: str
    glob: bytes
    #: Of the rules that fit, the one of the highest rank, then weight, decides.
    rank: int = 0
    weight: int = 0


def site_rule(action: str, host: str, path: str = "/") -> Rule:
    """Fits host and its subdomains where the path starts with path. The longest one decides."""
    lit = lambda s: b"".join(b"\\" + bytes([c]) if c in b"*?\\" else bytes([c]) for c in s.encode())
    return Rule(host + path, action, b"*." + lit(host.lower()) + BORDER + lit(path) + b"*", 1, len((host + path).encode()))


def glob_rule(action: str, host: str = "*", path: str = "*") -> Rule:
    """Globs for the host, without its leading dot, and the path; they decide where no site rule fits."""
    return Rule(f"{host}|{path}", action, b"." + host.lower().encode() + BORDER + path.encode() + b"")


class Automaton:
    """All globs at once."""

    def __init__(self, globs: list[bytes]):
        bits: list[tuple[set[int] | None, bool, bool, bool]] = []  # bytes or any, first, injected always, looping
        self.final: list[int] = []
        self.always = [i for i, g in enumerate(globs) if g and not g.strip(b"*")]
        self.on_empty = [i for i, g in enumerate(globs) if not g.strip(b"*")]
        for g in globs:
            i, lead, first = 0, False, True
            while i < len(g):
                c = g[i : i + 1]
                if c == b"*":
                    if first:
                        lead = True
                    else:
                        bits[-1] = (*bits[-1][:3], True)
                    i += 1
                    continue
                if c == b"\\" and i + 1 < len(g):
                    i += 1
                    c = b"\\" + g[i : i + 1]
                bits.append((None if c == b"?" else {c[-1]}, first, first and lead, False))
                first = False
                i += 1
            self.final.append(-1 if first else len(bits) - 1)
        self.words = max(1, -(-len(bits) // 64))
        z = lambda: np.zeros(self.words, np.uint64)
        self.first, self.inject, self.loop = z(), z(), z()
        self.table = np.zeros((256, self.words), np.uint64)
        for k, (what, first, inject, loop) in enumerate(bits):
            w, b = k // 64, np.uint64(1 << (k % 64))
            if what is None:
                self.table[:255, w] |= b  # any byte but the border
            else:
                for c in what:
                    self.table[c, w] |= b
            for mask, on in ((self.first, first), (self.inject, inject), (self.loop, loop)):
                if on:
                    mask[w] |= b

    def match(self, texts: list[bytes]) -> np.ndarray:
        """Boolean matrix: text by glob, whether the whole text matches."""
        n = len(texts)
        lens = np.array([len(t) for t in texts], np.int64)
        order = np.argsort(-lens, kind="stable")
        state = np.zeros((n, self.words), np.uint64)
        data = np.frombuffer(b"".join(texts[i] for i in order), np.uint8)
        start = np.concatenate([[0], np.cumsum(lens[order])])[:-1].astype(np.int64)
        one, top = np.uint64(1), np.uint64(63)
        for j in range(int(lens.max(initial=0))):
            live = int(np.searchsorted(-lens[order], -j, "left"))
            d = state[:live]
            moved = d << one
            moved[:, 1:] |= d[:, :-1] >> top
            moved = (moved & ~self.first) | (self.inject if j else self.first)
            state[:live] = (moved & self.table[data[start[:live] + j]]) | (d & self.loop)
        out = np.zeros((n, len(self.final)), bool)
        for g, k in enumerate(self.final):
            if k >= 0:
                out[order, g] = (state[:, k // 64] >> np.uint64(k % 64)) & one == one
        out[:, self.always] = True
        out[np.ix_(np.flatnonzero(lens == 0), self.on_empty)] = True
        return out


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z in lower case; empty without ://."""
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise(F.lit(""))
    return F.coalesce(F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    """After the host up to ? # or the end."""
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise(F.lit(""))
    return F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def judged(rules: list[Rule], host: Column, path: Column, default: str = "allow") -> Column:
    """struct<rule, verdict, glob>: rule is the deciding site rule's name, glob the deciding pattern's where no site rule fits."""
    best = sorted(range(len(rules)), key=lambda i: (-rules[i].rank, -rules[i].weight, i))
    automaton = Automaton([rules[i].glob for i in best])
    ranked = [rules[i] for i in best]

    # What is said of each rule, and last of none.
    said = np.array([(r.name if r.rank else None, r.action, None if r.rank else r.name) for r in ranked] + [(None, default, None)], dtype=object)

    @F.pandas_udf("rule string, verdict string, glob string")
    def judge(h: pd.Series, p: pd.Series) -> pd.DataFrame:
        texts = [b"." + (a or "").encode() + BORDER + (b or "").encode() for a, b in zip(h, p, strict=True)]
        deciding = np.full(len(texts), len(ranked))
        for at in range(0, len(texts), 4096) if ranked else ():
            hit = automaton.match(texts[at : at + 4096])
            deciding[at : at + 4096] = np.where(hit.any(axis=1), hit.argmax(axis=1), len(ranked))
        return pd.DataFrame(said[deciding], columns=["rule", "verdict", "glob"])

    return judge(host, path)
