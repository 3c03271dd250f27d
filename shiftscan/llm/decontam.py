"""Benchmark decontamination by a random-walk embedding and bit-sampling LSH.

Words (punctuation dropped, case lowered) are the symbols. A window's embedding is a
walk: step t writes the word under the cursor and a random bit of (t, word) says
whether the cursor moves on. Windows at small edit distance write mostly the same
sequence, so their Hamming distance is small, and sampled steps agree. A window that
agrees with an item on a key, a few sampled steps of a walk, is a candidate, and the
words around it are verified by exact word edit distance.

Keys are taken from the whole item: an item that may have e edits is cut into e + 1
pieces, of which e edits leave one as it was. A piece's key is from a walk that starts
with it and whose sampled steps do not leave it, so the untouched piece always agrees:
the candidates hold every window within the limit, recall is one by construction. Each
of ``rounds`` random walks takes the pieces that it covers well; the walk that always
moves on takes the rest.

The walks of all windows of a slice of texts advance together as vectors, and a
window leaves the walk at the first sampled step that no piece has so far. A walk does
not depend on where a window ends: one walk per start serves every item size.

Items are a stated query set. They are held in blocks of at most ``block_chars``
characters, each broadcast with its closure; every block reads all texts. Defined
results: null or wordless texts and items match nothing; each row is judged by
itself; a repeated item id is reported once; an empty benchmark leaves all clean.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import tokens
from .common import need, prepare, text_of

PIECE = 8  # words of a piece that its key may be taken from, from the first on
_STEP = np.uint64(0x9E3779B97F4A7C15)
_ALL = np.uint64((1 << 64) - 1)
_NEAR = np.uint64(46)  # shift of a key to its place in a table of 2**18 marks


class Index:
    """The keys of a block of items; ``percent``: largest edit distance in hundredths of an item's words."""

    def __init__(self, items: list[tuple[int, str]], percent: int, rounds: int, seed: int):
        got = list(tokens.words(pa.array([t for _, t in items], pa.string()), spoken=True))
        self.items: list[tuple[int, np.ndarray]] = []
        for w in got:
            for k in range(w.rows):
                h = w.hash[w.first[k] : w.first[k + 1]]
                if len(h):
                    self.items.append((items[w.base + k][0], h))
        self.percent = percent
        self.vocab = np.unique(np.concatenate([h for _, h in self.items])) if self.items else np.zeros(0, np.uint64)
        self.near = np.zeros(1 << 16, bool)
        self.near[(self.vocab >> np.uint64(48)).astype(np.int64)] = True
        if percent >= 100:
            raise ValueError("percent must be below 100")
        pieces: dict[int, list[tuple[int, int]]] = {}  # by length: item, first word
        for i, (_, h) in enumerate(self.items):
            parts = len(h) * percent // 100 + 1
            cuts = [len(h) * k // parts for k in range(parts + 1)]
            for low, high in zip(cuts, cuts[1:]):
                pieces.setdefault(min(high - low, PIECE), []).append((i, low))
        rng = np.random.default_rng(seed)
        self.rounds = []
        with np.errstate(over="ignore"):
            for length, own in sorted(pieces.items()):
                left = np.array(own, np.int64)
                for _ in range(rounds if length > 2 else 0):
                    # Walks move on at half of their steps.
                    last = 2 * length - 2
                    at = np.sort(np.append(rng.choice(np.arange(1, last), length - 1, replace=False), [0, last]))
                    salt = rng.integers(0, 1 << 63, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
                    left = self._round(left, length, at, salt, max(3, length - 1))
                self._round(left, length, np.arange(length), None, length)

    def _round(self, own: np.ndarray, length: int, at: np.ndarray, salt: np.uint64 | None, least: int) -> np.ndarray:
        """Takes those of ``own`` (item, first word) whose walk stays inside and shows ``least`` of their words; the others are returned."""
        if not len(own):
            return own
        h = np.stack([self.items[i][1][k : k + length] for i, k in own])
        bits = self._bits(h, salt)
        code = self.coded(h.ravel()).reshape(h.shape).astype(np.uint64)
        every = np.arange(len(own))
        cursor, shown = np.zeros(len(own), np.int64), np.zeros(h.shape, bool)
        key, levels = None, []
        for t in range(int(at[-1]) + 1):
            inside = np.minimum(cursor, length - 1)
            if t in at:
                shown[every, inside] = True
                key = self._key(key, code[every, inside])
                levels.append(key)
            if t < at[-1]:
                cursor += ((bits[every, inside] >> np.uint64(63 - t)) & np.uint64(1)).astype(np.int64)
        good = (cursor < length) & (shown.sum(1) >= least)
        if not good.any():
            return own
        seen = []
        for k in levels:
            there = np.zeros(1 << 18, bool)
            there[(k[good] >> _NEAR).astype(np.int64)] = True
            seen.append(there)
        order = np.argsort(key[good], kind="stable")
        self.rounds.append((at, salt, seen, key[good][order], own[good][order]))
        return own[~good]

    @staticmethod
    def _bits(h: np.ndarray, salt: np.uint64 | None) -> np.ndarray:
        return np.full(h.shape, _ALL) if salt is None else h * salt

    @staticmethod
    def _key(before: np.ndarray | None, code: np.ndarray) -> np.ndarray:
        return tokens.mix(code + _STEP if before is None else before * _STEP + code)

    def coded(self, h: np.ndarray) -> np.ndarray:
        """A word's place in the items' vocabulary from 1, or 0."""
        out = np.zeros(len(h), np.int32)
        maybe = np.flatnonzero(self.near[(h >> np.uint64(48)).astype(np.int64)])
        if len(maybe):
            place = np.minimum(np.searchsorted(self.vocab, h[maybe]), len(self.vocab) - 1)
            good = self.vocab[place] == h[maybe]
            out[maybe[good]] = place[good] + 1
        return out

    def candidates(self, h: np.ndarray) -> set[tuple[int, int, int]]:
        """(start of the item, item, start of the key) of all windows that share a key with an item."""
        out: set[tuple[int, int, int]] = set()
        if not len(self.vocab) or not len(h):
            return out
        code = self.coded(h)
        code = np.append(code, np.int32(0)).astype(np.uint64)
        last = len(h)
        h = np.append(h, np.uint64(0))
        with np.errstate(over="ignore"):
            known = np.flatnonzero(code).astype(np.int32)
            first = self._key(None, code[known])
            place = (first >> _NEAR).astype(np.int64)
            for at, salt, seen, keys, own in self.rounds:
                stay = np.flatnonzero(seen[0][place])
                start = cursor = known[stay]
                key, t = first[stay], 0
                for level, step in enumerate(at[1:], 1):
                    while t < step:
                        moves = 1 if salt is None else ((h[cursor] * salt) >> np.uint64(63 - t)).astype(np.int32) & 1
                        cursor = np.minimum(cursor + moves, last).astype(np.int32)
                        t += 1
                    word = code[cursor]
                    key = self._key(key, word)
                    stay = np.flatnonzero(seen[level][(key >> _NEAR).astype(np.int64)] & (word > 0))
                    start, cursor, key = start[stay], cursor[stay], key[stay]
                    if not len(start):
                        break
                low, high = np.searchsorted(keys, key, "left"), np.searchsorted(keys, key, "right")
                for k in np.flatnonzero(high > low):
                    s = int(start[k])
                    for i, anchor in own[low[k] : high[k]].tolist():
                        out.add((s - anchor, i, s))
        # A window that is near enough holds most of the item's words, all of which are in the vocabulary.
        known = np.zeros(last + 1, np.int64)
        np.cumsum(code[:last] > 0, out=known[1:])

        def enough(start: int, i: int) -> bool:
            n = len(self.items[i][1])
            slack = n * self.percent // 100
            return known[min(last, start + n + slack)] - known[min(last, max(0, start - slack))] >= n - slack

        return {x for x in out if enough(x[0], x[1])}

    def close(self, item: np.ndarray, text: np.ndarray) -> bool:
        """Whether a run of words of ``text`` is within the item's edit distance."""
        n, most = len(item), len(item) * self.percent // 100
        if len(np.intersect1d(item, text)) < len(np.unique(item)) - most:
            return False
        row = np.zeros(len(text) + 1, np.int64)  # a match may begin anywhere
        place = np.arange(len(text) + 1)
        for i in range(n):
            new = np.empty_like(row)
            new[0] = i + 1
            new[1:] = np.minimum(row[1:] + 1, row[:-1] + (text != item[i]))
            row = np.minimum.accumulate(new - place) + place
            if row.min() > most:
                return False
        return bool(row.min() <= most)

    def matches(self, column) -> list[list[int]]:
        """Ids of the items found in each text."""
        out: list[list[int]] = []
        for w in tokens.words(column, spoken=True):
            found: dict[int, set[int]] = {}
            for start, i, doc in sorted({(start, i, int(w.doc[sign])) for start, i, sign in self.candidates(w.hash)}):
                name, item = self.items[i]
                slack = len(item) * self.percent // 100
                window = w.hash[max(w.first[doc], start - slack) : min(w.first[doc + 1], start + len(item) + slack)]
                if name not in found.get(doc, ()) and self.close(item, window):
                    found.setdefault(doc, set()).add(name)
            out += [sorted(found.get(k, ())) for k in range(w.rows)]
        return out


def _finder(items: list[tuple[int, str]], percent: int, rounds: int, seed: int):
    held: list[Index] = []

    @F.arrow_udf("array<long>")
    def find(column: pa.Array) -> pa.Array:
        if not held:
            held.append(Index(items, percent, rounds, seed))
        return pa.array(held[0].matches(column), pa.list_(pa.int64()))

    return find


def contamination(docs: DataFrame, benchmark: DataFrame, percent: int = 20, rounds: int = 6, seed: int = 11, block_chars: int = 4_000_000, into: str = "items") -> DataFrame:
    """The columns of ``docs`` and array ``into`` of the item ids found in its text."""
    need(docs, "text")
    need(benchmark, "item_id", "text")
    prepare(docs.sparkSession)
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), text_of().alias("text")).where("item_id is not null").distinct()
    chars = items.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = -(-chars // block_chars)
    found: list[Column] = []
    for k in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k)
        block = sorted((r.item_id, r.text) for r in part.collect())
        found.append(_finder(block, percent, rounds, seed)(F.col("text").cast("string")))
    if not found:
        return docs.withColumn(into, F.array().cast("array<long>"))
    return docs.withColumn(into, F.array_sort(F.array_distinct(F.concat(*found))) if blocks > 1 else found[0])
