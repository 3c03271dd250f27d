"""Language identification by cross-parsing.

Labelled text of each language becomes a suffix automaton. A text is parsed against
each language into the fewest phrases, each the longest match in that language's
sample; phrases times the sample's bits per pointer, divided by the text's length,
is the cross-parsing entropy, and the smallest wins. Parsing needs no suffix links:
where a phrase cannot grow, the next one starts at the root. That makes it one table
lookup per symbol, so many texts advance together as numpy vectors. Every letter of a
sample is a symbol: the most frequent have a column in a dense table, and the others'
transitions are held sorted.

Fit bounds (documented parameters): ``docs_per_lang`` labelled rows chosen by a hash
of their text, and ``sample_chars`` symbols per language. Prediction reads every
whole text, in blocks of ``block`` symbols that each start a phrase.

Defined results: a null text, or one without any letter, is ``und`` with score 0, and
so is every text if nothing could be learned. Ties go to the first language by name.
Equal rows give equal results; other columns are ignored.
"""

from __future__ import annotations

import sys
from functools import lru_cache
from math import log2

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import need, prepare, trim

UNKNOWN = "und"


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1)


def automaton(sample: np.ndarray, symbols: int, dense: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(state, symbol) -> twice the next state, plus one where a new phrase begins.

    As a table for the first ``dense`` symbols; the same for a new phrase with each of the
    others; and their transitions (state, symbol, twice the next state).
    """
    step: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in sample.tolist():
        new = len(step)
        step.append({})
        link.append(0)
        length.append(length[last] + 1)
        at = last
        while at >= 0 and c not in step[at]:
            step[at][c] = new
            at = link[at]
        if at >= 0:
            to = step[at][c]
            if length[to] == length[at] + 1:
                link[new] = to
            else:
                copy = len(step)
                step.append(step[to].copy())
                link.append(link[to])
                length.append(length[at] + 1)
                while at >= 0 and step[at].get(c) == to:
                    step[at][c] = copy
                    at = link[at]
                link[to] = link[new] = copy
        last = new
    dead = len(step)  # after a symbol that the sample lacks; every parse begins there
    step.append({})
    root = np.full(symbols, dead, np.int32)
    for c, to in step[0].items():
        root[c] = to
    table = np.tile(2 * root[:dense] + 1, (len(step), 1))
    rare: list[tuple[int, int, int]] = []
    for state, out in enumerate(step):
        for c, to in out.items():
            if c < dense:
                table[state, c] = 2 * to
            else:
                rare.append((state, c, 2 * to))
    return table, 2 * root[dense:] + 1, np.array(rare, np.int64).reshape(-1, 3)


class Parser:
    """Automata of all languages over all their letters. ``samples``: (language, text), sorted; ``alphabet``: columns of the dense table."""

    def __init__(self, samples: tuple[tuple[str, str], ...], alphabet: int, block: int):
        self.langs, self.block = [x for x, _ in samples], block
        count: dict[str, int] = {}
        for _, text in samples:
            for c in text.lower():
                if c.isalpha():
                    count[c] = count.get(c, 0) + 1
        known = sorted(sorted(count), key=count.get, reverse=True)
        # 0: anything but a letter; 1: a letter that the samples do not hold.
        self.code = _letters().astype(np.int32)
        for k, c in enumerate(known):
            for x in {c, c.upper()}:
                if len(x) == 1:
                    self.code[ord(x)] = k + 2
        symbols = len(known) + 2
        self.size, self.symbols = min(symbols, alphabet), symbols
        tables, bits, base, rare, begin, self.letters = [], [], [], [], [], []
        at = 0
        for _, text in samples:
            coded, _ = self.coded([text])
            table, root, more = automaton(coded[coded != 1], symbols, self.size)
            tables.append(table + 2 * at)
            begin.append(root + 2 * at)
            rare.append(more + np.array([at, 0, 2 * at]))
            self.letters.append(len(np.unique(coded[coded > 1])))
            base.append(at + len(table) - 1)
            bits.append(log2(max(2, len(coded))))
            at += len(table)
        self.table = np.concatenate(tables).ravel() if tables else np.zeros(0, np.int32)
        every = np.concatenate(rare) if rare else np.zeros((0, 3), np.int64)
        keys = every[:, 0] * symbols + every[:, 1]
        order = np.argsort(keys)
        self.rare, self.rare_to, self.begin = keys[order], every[order, 2].astype(np.int32), np.array(begin, np.int32)
        self.base, self.bits = np.array(base, np.int32), np.array(bits)

    def coded(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of all texts with runs of non-letters as one, and where each text begins."""
        points = np.frombuffer("".join(texts).encode("utf-32-le", "replace"), np.uint32)
        at = np.zeros(len(texts) + 1, np.int64)
        np.cumsum([len(t) for t in texts], out=at[1:])
        code = self.code[points]
        keep = code != 0
        keep[1:] |= code[:-1] != 0
        inner = at[:-1][at[:-1] < len(code)]
        keep[inner] = True
        kept = np.zeros(len(code) + 1, np.int64)
        np.cumsum(keep, out=kept[1:])
        return code[keep], kept[at]

    def _rare(self, to: np.ndarray, state: np.ndarray, symbol: np.ndarray) -> None:
        """Puts the steps with symbols outside the dense table in place."""
        at = np.flatnonzero(symbol >= self.size)
        if len(at):
            key = state[:, at].astype(np.int64) * self.symbols + symbol[at]
            place = np.minimum(np.searchsorted(self.rare, key), len(self.rare) - 1)
            to[:, at] = np.where(self.rare[place] == key, self.rare_to[place], self.begin[:, symbol[at] - self.size])

    def costs(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Bits per symbol for each text and language, and each text's number of letters."""
        code, at = self.coded(texts)
        length = np.diff(at)
        pieces = -(-length // self.block)
        owner = np.repeat(np.arange(len(texts)), pieces)
        nth = np.arange(len(owner)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        start = at[owner] + nth * self.block
        size = np.minimum(self.block, at[owner + 1] - start)
        order = np.argsort(-size, kind="stable")
        start, size, owner = start[order], size[order], owner[order]
        state = np.repeat(self.base[:, None], len(start), 1)
        phrases = np.zeros((len(self.langs), len(start)), np.int32)
        live = np.searchsorted(-size, -np.arange(int(size[0]) if len(size) else 0), "left")
        wide = bool(len(code)) and len(self.langs) > 0 and int(code.max()) >= self.size
        for t, k in enumerate(live):
            # One step of every language and piece that is that long.
            symbol = code[start[:k] + t]
            if wide:
                to = self.table[state[:, :k] * self.size + np.where(symbol < self.size, symbol, 1)]
                self._rare(to, state, symbol)
            else:
                to = self.table[state[:, :k] * self.size + symbol]
            phrases[:, :k] += to & 1
            state[:, :k] = to >> 1
        total = np.stack([np.bincount(owner, x, len(texts)) for x in phrases], 1) if len(self.langs) else np.zeros((len(texts), 0))
        letters = np.zeros(len(code) + 1, np.int64)
        np.cumsum(code > 0, out=letters[1:])
        return total * self.bits / np.maximum(length, 1)[:, None], letters[at[1:]] - letters[at[:-1]]


@lru_cache(maxsize=2)
def _parser(samples: tuple, alphabet: int, block: int) -> Parser:
    return Parser(samples, alphabet, block)


def samples_of(docs: DataFrame, train: Column, docs_per_lang: int, sample_chars: int) -> tuple[tuple[str, str], ...]:
    """The bounded labelled sample: at most ``sample_chars`` characters per language."""
    rows = docs.where(train & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("lang", F.substring("text", 1, sample_chars).alias("text"))
    ranked = Window.partitionBy("lang").orderBy(F.xxhash64("text"), "text")
    few = rows.select("lang", "text", F.row_number().over(ranked).alias("k")).where(F.col("k") <= docs_per_lang).collect()
    out: dict[str, str] = {}
    for r in sorted(few, key=lambda r: (r.lang, r.k)):
        if len(out.get(r.lang, "")) < sample_chars and r.text not in out.get(r.lang, ""):
            out[r.lang] = (out.get(r.lang, "") + "\n" + r.text)[:sample_chars]
    return tuple(sorted(out.items()))


def identify(docs: DataFrame, train: Column, docs_per_lang: int = 200, sample_chars: int = 30_000, alphabet: int = 96, block: int = 1024, into: str = "language") -> DataFrame:
    """The columns of ``docs`` and struct ``into`` (lang_pred, score, bits, alphabet).

    ``train``: which rows may be learned from. ``score`` is the runner-up's lead over
    the winner, 0 to 1; ``bits`` the winner's entropy per symbol, ``alphabet`` the letters in the winner's sample.
    """
    need(docs, "text", "lang")
    prepare(docs.sparkSession)
    samples = samples_of(docs, train, docs_per_lang, sample_chars)

    result = pa.struct([("lang_pred", pa.string()), ("score", pa.float64()), ("bits", pa.float64()), ("alphabet", pa.int32())])

    @F.arrow_udf("struct<lang_pred: string, score: double, bits: double, alphabet: int>")
    def predict(column: pa.Array) -> pa.Array:
        parser = _parser(samples, alphabet, block)
        ends = np.cumsum(np.fromiter((x.as_py() or 0 for x in pc.utf8_length(column)), np.int64, len(column)))
        pred, sizes, score, bits = [], [], [np.zeros(0)], [np.zeros(0)]
        row = 0
        while row < len(column):
            # Slices of whole texts of about half a million characters.
            to = max(row + 1, int(np.searchsorted(ends, (ends[row - 1] if row else 0) + 500_000, "right")))
            cost, letters = parser.costs([t or "" for t in column.slice(row, to - row).to_pylist()])
            if not parser.langs:
                letters = np.zeros_like(letters)
                cost = np.zeros((to - row, 1))
            best, low = cost.argmin(1), cost.min(1)
            second = np.partition(cost, 1, 1)[:, 1] if cost.shape[1] > 1 else np.maximum(low, 2 * low)
            lead = np.where((letters > 0) & (second > 0), 1 - low / np.where(second > 0, second, 1), 0.0)
            pred += [parser.langs[b] if n else UNKNOWN for b, n in zip(best, letters)]
            sizes += [parser.letters[b] if n else 0 for b, n in zip(best, letters)]
            score.append(np.clip(lead, 0, 1))
            bits.append(np.where(letters > 0, low, 0.0))
            row = to
        trim()
        return pa.StructArray.from_arrays([pa.array(pred, pa.string()), pa.array(np.concatenate(score)), pa.array(np.concatenate(bits)), pa.array(sizes, pa.int32())], fields=list(result))

    return docs.withColumn(into, predict(F.col("text").cast("string")))
