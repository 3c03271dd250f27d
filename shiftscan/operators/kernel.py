"""The chain's arithmetic on all windows of a block at once, doing only the work each window needs.

Values are integers. A centre is an exact pair (sum, count); a value on a border
belongs to the higher centre, so clusters depend on the set of seeds and not on their
order, which is what makes reuse under rotation sound. Labels number the centres from
the smallest. A probability is one integer product over another.

Marks (distinct values, rotations) come from where each value occurred last and occurs
next, at a constant cost per slide. Only windows that open a run of rotations, the
anchors, are clustered and labelled. Those that follow take their counts from the
anchor's ring of transitions, one look-up for each of the last ``n``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from numpy.lib.stride_tricks import sliding_window_view

RULES = ("rotation", "single", "few", "iterate")
CELLS = 4_000_000  # of the largest array that a step may make


@dataclass(frozen=True)
class Options:
    """Every shortcut is a switch of its own; results never depend on them.

    ``kept``: the values of a window stay sorted from slide to slide, as counts and sums
    below each distinct value of the block, where those are few enough.
    """

    w: int = 10
    n: int = 5
    max_iter: int = 50
    rotation: bool = True
    single: bool = True
    few: bool = True
    few_inclusive: bool = False
    lazy: bool = True
    ring: bool = True
    sorted_sweep: bool = True
    kept: bool = True
    memo: bool = False


@dataclass
class Marks:
    """What is known of each window before any clustering; one entry per place in the block."""

    keep: np.ndarray
    distinct: np.ndarray
    rotated: np.ndarray


class Block:
    """Values of series that follow one another, as places among the block's distinct values."""

    def __init__(self, v: np.ndarray, w: int, owner: np.ndarray | None = None):
        self.v, self.w = v, w
        self.values, codes = np.unique(v, return_inverse=True)
        self.codes = codes.astype(np.int32).ravel()
        self.owner = np.zeros(len(v), np.int32) if owner is None else owner
        key = self.owner.astype(np.int64) * len(self.values) + self.codes
        order = np.argsort(key, kind="stable")
        same = key[order[1:]] == key[order[:-1]]
        self.last, self.next = np.full(len(v), -1, np.int32), np.full(len(v), len(v), np.int32)
        self.last[order[1:][same]], self.next[order[:-1][same]] = order[:-1][same], order[1:][same]
        self._below: tuple[np.ndarray, np.ndarray] | None = None

    def marks(self, k: int) -> Marks:
        n, w, at = len(self.v), self.w, np.arange(len(self.v) - self.w)
        keep = self.owner[: n - w + 1] == self.owner[w - 1 :]
        distinct = np.empty(n - w + 1, np.int32)
        distinct[0] = (self.last[:w] < 0).sum()
        # A slide loses a value that does not come again in time, and gains one that is not there yet.
        np.cumsum((self.last[w:] <= at).astype(np.int32) - (self.next[: n - w] >= at + w), out=distinct[1:])
        distinct[1:] += distinct[0]
        rotated = np.zeros(n - w + 1, bool)
        came = np.flatnonzero((self.codes[w:] == self.codes[: n - w]) & keep[1:] & keep[:-1] & (self.owner[1 : n - w + 1] == self.owner[: n - w]))
        # What left is back. The seeds are the same if fewer than k others stand before its next place.
        gap = self.next[came] - came - 1
        good = gap < k
        unsure = np.flatnonzero(~good)
        places = sliding_window_view(self.last, w)
        step = max(1, CELLS // w)
        for low in range(0, len(unsure), step):
            part = came[unsure[low : low + step]]
            fresh = (places[part + 1] <= part[:, None]) & (np.arange(w)[None, :] < (self.next[part] - part - 1)[:, None])
            good[unsure[low : low + step]] = fresh.sum(1) < k
        rotated[came[good] + 1] = True
        return Marks(keep, distinct, rotated)

    def seeds(self, at: np.ndarray, k: int) -> np.ndarray:
        """The first ``k`` distinct values, ascending, of windows that hold as many."""
        out = np.empty((len(at), k), np.int64)
        places, codes = sliding_window_view(self.last, self.w), sliding_window_view(self.codes, self.w)
        step = max(1, CELLS // self.w)
        for low in range(0, len(at), step):
            part = at[low : low + step]
            first = places[part] < part[:, None]
            first &= np.cumsum(first, axis=1) <= k
            out[low : low + step] = self.values[np.sort(codes[part][first].reshape(len(part), k), axis=1)]
        return out

    def windows(self, at: np.ndarray) -> np.ndarray:
        return sliding_window_view(self.codes, self.w)[at]

    @property
    def slim(self) -> bool:
        """Whether counts below each distinct value are worth keeping for the block."""
        return len(self.values) <= max(64, self.w) and len(self.values) * len(self.v) <= 4 * CELLS

    def below(self) -> tuple[np.ndarray, np.ndarray]:
        """(count, sum) of the first i readings that are smaller than the x-th value: rows i, columns x."""
        if self._below is None:
            n, d = len(self.v), len(self.values)
            count = np.zeros((n + 1, d + 1), np.int32)
            count[np.arange(1, n + 1), self.codes + 1] = 1
            np.cumsum(count, axis=0, out=count)
            total = count.astype(np.int64)
            total[:, 1:] *= self.values
            self._below = np.cumsum(count, axis=1, dtype=np.int32), np.cumsum(total, axis=1)
        return self._below


def _borders(s: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The smallest integer that belongs to the higher of neighbouring centres."""
    a, b = n[:, :-1], n[:, 1:]
    return -((-(s[:, :-1] * b + s[:, 1:] * a)) // (2 * a * b))


def _settled(s: np.ndarray, n: np.ndarray, part, max_iter: int) -> tuple[np.ndarray, np.ndarray]:
    """Moves centres until they stay. ``part(rows, borders)``: (sum, count) of each cluster. (last borders, iterations)."""
    cuts = np.zeros((len(s), s.shape[1] - 1), np.int64)
    iterations = np.zeros(len(s), np.int32)
    active = np.arange(len(s))
    for _ in range(max_iter):
        if not len(active):
            break
        cuts[active] = t = _borders(s[active], n[active])
        total, count = part(active, t)
        empty = count == 0
        total, count = np.where(empty, s[active], total), np.where(empty, n[active], count)
        moved = (total * n[active] != s[active] * count).any(1)
        s[active], n[active] = total, count
        iterations[active] += 1
        active = active[moved]
    return cuts, iterations


def _rows_of(marks: np.ndarray, width: int) -> np.ndarray:
    """How often each of ``width`` places is marked, row by row."""
    m = len(marks)
    flat = (np.arange(m)[:, None] * width + marks).ravel()
    return np.bincount(flat, minlength=m * width).reshape(m, width)


def sweep(block: Block, at: np.ndarray, seeds: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """Sorted values against sorted centres: borders cut running sums. (labels, iterations)."""
    w, d = block.w, len(block.values)
    m = len(at)
    s, n = seeds.copy(), np.ones_like(seeds)
    if o.kept and block.slim:
        # The sorted order is there already: a window is the difference of two rows.
        count, total = block.below()

        def part(rows, t):
            x = np.searchsorted(block.values, t)
            low, high = at[rows][:, None], at[rows][:, None] + w
            edge = np.empty((2, len(rows), t.shape[1] + 2), np.int64)
            edge[:, :, 0] = 0
            edge[0, :, 1:-1], edge[1, :, 1:-1] = count[high, x] - count[low, x], total[high, x] - total[low, x]
            edge[0, :, -1], edge[1, :, -1] = w, total[high[:, 0], d] - total[low[:, 0], d]
            size, sums = np.diff(edge, axis=2)
            return sums, size

        cuts, iterations = _settled(s, n, part, o.max_iter)
        label = np.cumsum(_rows_of(np.searchsorted(block.values, cuts), d + 1), axis=1).astype(np.int16)
        return np.take_along_axis(label, block.windows(at), 1), iterations
    win = block.windows(at)
    order = np.argsort(win, axis=1, kind="stable")
    ranked = np.take_along_axis(win, order, 1)
    sums = np.zeros((m, w + 1), np.int64)
    np.cumsum(block.values[ranked], axis=1, out=sums[:, 1:])
    flat = (ranked + np.arange(m)[:, None] * (d + 1)).ravel()

    def places(rows, t):
        return np.searchsorted(flat, np.searchsorted(block.values, t) + rows[:, None] * (d + 1)) - rows[:, None] * w

    def part(rows, t):
        edge = np.zeros((len(rows), t.shape[1] + 2), np.int64)
        edge[:, 1:-1], edge[:, -1] = places(rows, t), w
        return np.diff(np.take_along_axis(sums[rows], edge, 1), axis=1), np.diff(edge, axis=1)

    cuts, iterations = _settled(s, n, part, o.max_iter)
    label = np.cumsum(_rows_of(places(np.arange(m), cuts), w + 1), axis=1)[:, :w].astype(np.int16)
    out = np.empty_like(label)
    np.put_along_axis(out, order, label, 1)
    return out, iterations


def naive(block: Block, at: np.ndarray, seeds: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """Every value against every centre, in exact fractions. (labels, iterations)."""
    win = block.values[block.windows(at)]
    m, k = seeds.shape
    s, n = seeds.copy(), np.ones_like(seeds)
    labels = np.zeros(win.shape, np.int16)
    iterations = np.zeros(m, np.int32)
    active = np.arange(m)
    for _ in range(o.max_iter):
        if not len(active):
            break
        x, sa, na = win[active], s[active], n[active]
        best = np.zeros(x.shape, np.int16)
        gap, over = np.abs(x * na[:, :1] - sa[:, :1]), np.repeat(na[:, :1], x.shape[1], 1)
        for j in range(1, k):
            new = np.abs(x * na[:, j : j + 1] - sa[:, j : j + 1])
            closer = new * over <= gap * na[:, j : j + 1]
            best[closer] = j
            gap, over = np.where(closer, new, gap), np.where(closer, na[:, j : j + 1], over)
        labels[active] = best
        total, count = np.empty_like(sa), np.empty_like(na)
        for j in range(k):
            mine = best == j
            total[:, j], count[:, j] = (x * mine).sum(1), mine.sum(1)
        empty = count == 0
        total, count = np.where(empty, sa, total), np.where(empty, na, count)
        moved = (total * na != sa * count).any(1)
        s[active], n[active] = total, count
        iterations[active] += 1
        active = active[moved]
    return labels, iterations


def clusters(block: Block, at: np.ndarray, how_many: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """Labels and iterations of the windows at ``at``; those with fewer seeds have fewer centres."""
    work = sweep if o.sorted_sweep else naive
    labels, iterations = np.zeros((len(at), block.w), np.int16), np.zeros(len(at), np.int32)
    for k in np.unique(how_many):
        rows = np.flatnonzero(how_many == k)
        step = max(1, CELLS // (block.w + int(k) + (len(block.values) if block.slim else 0)))
        for low in range(0, len(rows), step):
            part = rows[low : low + step]
            seeds = block.seeds(at[part], int(k))
            back: np.ndarray | slice = slice(None)
            if o.memo:
                both = np.concatenate([seeds, block.windows(at[part])], axis=1)
                _, one, back = np.unique(both, axis=0, return_index=True, return_inverse=True)
                seeds, back, one = seeds[one], back.ravel(), at[part][one]
            else:
                one = at[part]
            l, i = work(block, one, np.ascontiguousarray(seeds), o)
            labels[part], iterations[part] = l[back], i[back]
    return labels, iterations


def ranks(block: Block, at: np.ndarray) -> np.ndarray:
    """Of each value, its place among the window's distinct values."""
    win = block.windows(at)
    if block.slim:
        there = _rows_of(win, len(block.values)) > 0
        return np.take_along_axis(np.cumsum(there, axis=1, dtype=np.int16) - 1, win, 1).astype(np.int16)
    order = np.argsort(win, axis=1, kind="stable")
    sorted_ = np.take_along_axis(win, order, 1)
    step = np.zeros(win.shape, np.int16)
    step[:, 1:] = np.cumsum(sorted_[:, 1:] != sorted_[:, :-1], axis=1)
    out = np.empty_like(step)
    np.put_along_axis(out, order, step, 1)
    return out


def _tally(code: np.ndarray, size: int):
    """Counts of equal entries of a row, as a function of (row, entry); ``code`` below ``size``."""
    m, w = code.shape
    if size <= 8 * w + 64:
        table = np.bincount((np.arange(m, dtype=np.int64)[:, None] * size + code).ravel(), minlength=m * size)
        return lambda rows, entry: table[rows * size + entry]
    values, counts = np.unique((np.arange(m, dtype=np.int64)[:, None] * size + code).ravel(), return_counts=True)

    def of(rows, entry):
        place = np.minimum(np.searchsorted(values, rows * size + entry), len(values) - 1)
        return np.where(values[place] == rows * size + entry, counts[place], 0)

    return of


def _kind(n: int, w: int):
    """Products of ``n`` counts up to ``w`` may need integers of any size."""
    return object if n * np.log2(max(w, 2)) > 62 else np.int64


def probabilities(labels: np.ndarray, anchor: np.ndarray, shift: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(numerator, denominator, distinct pairs) of the last ``n`` transitions of each window.

    A window is its ``anchor``'s row of ``labels`` turned left by ``shift``. Turned windows
    have the anchor's cyclic pairs, but for the one at the seam.
    """
    m, w = len(anchor), labels.shape[1]
    n = min(o.n, w - 1)
    kind = _kind(n, w)
    num, den, divisions = np.ones(m, kind), np.ones(m, kind), np.zeros(m, np.int32)
    size = int(labels.max(initial=0)) + 1
    step = max(1, CELLS // (w + min(size * size, 8 * w + 64) + (size * size if not o.lazy else 0)))
    for low in range(0, m, step):
        part = slice(low, min(m, low + step))
        own, first = np.unique(anchor[part], return_inverse=True)
        first = first.ravel()
        turned = shift[part][:, None]
        if not o.ring:
            # Every window counts for itself.
            l = np.take_along_axis(labels[anchor[part]], (np.arange(w)[None, :] + turned) % w, 1).astype(np.int64)
            first, turned = np.arange(len(l)), np.zeros((len(l), 1), np.int64)
        else:
            l = labels[own].astype(np.int64)
        cyclic = l * size + np.roll(l, -1, axis=1)
        rows = first[:, None]
        if o.lazy:
            joint, leave = _tally(cyclic, size * size), _tally(l, size)
        else:
            # The full model: every pair of clusters with its count over its leave count.
            pairs = _rows_of(cyclic, size * size)
            below = np.repeat(_rows_of(l, size), size, axis=1)
            joint, leave = (lambda r, c: pairs[r, c]), (lambda r, c: below[r, c * size])
        at = (np.arange(w - 1 - n, w - 1)[None, :] + turned) % w
        seam = (w - 1 + turned) % w
        code, from_ = cyclic[rows, at], l[rows, at]
        a = joint(rows, code) - (cyclic[rows, seam] == code)
        b = leave(rows, from_) - (l[rows, seam] == from_)
        num[part], den[part] = a.astype(kind).prod(1), b.astype(kind).prod(1)
        if n:
            fresh = np.ones(code.shape, bool)
            for t in range(1, n):
                fresh[:, t] = (code[:, :t] != code[:, t : t + 1]).all(1)
            divisions[part] = fresh.sum(1)
    return num, den, divisions


def turned(labels: np.ndarray, anchor: np.ndarray, shift: np.ndarray) -> np.ndarray:
    """Every window's own labels."""
    w = labels.shape[1]
    return np.take_along_axis(labels[anchor], ((np.arange(w)[None, :] + shift[:, None]) % w), 1).astype(np.int32)


def scan(v: np.ndarray, k: int, skip: int | np.ndarray, o: Options, owner: np.ndarray | None = None) -> dict[str, np.ndarray]:
    """All windows of ``v`` but those there for comparison only: the first ``skip``, or those it marks.

    ``owner`` numbers the series that follow one another in ``v``; no window spans two.
    ``at`` of the result is each window's first place. Labels: ``turned`` of ``labels``,
    ``anchor`` and ``shift``.
    """
    block = Block(v, o.w, owner)
    marks = block.marks(k)
    keep = marks.keep
    if isinstance(skip, np.ndarray):
        keep = keep & ~skip
    else:
        keep[:skip] = False
    at = np.flatnonzero(keep)
    distinct, rotated, m = marks.distinct[at], marks.rotated[at], len(at)
    single, few = (distinct == 1) | (k == 1), (distinct <= k) if o.few_inclusive else (distinct < k)
    rule = np.where(rotated, 0, np.where(single, 1, np.where(few, 2, 3)))
    # Labels are reused from the window before, which must be here too.
    done = single & o.single
    reused = rotated & o.rotation & ~done
    reused[:1] = False
    reused[1:] &= at[1:] == at[:-1] + 1
    opens = np.flatnonzero(~reused & ~done)
    place = np.arange(m)
    # Row 0 of the labels is that of all windows with one cluster.
    of = np.zeros(m, np.int64)
    of[opens] = np.arange(1, len(opens) + 1)
    held = np.maximum.accumulate(np.where(reused, -1, place)) if m else place
    shift = np.where(reused, (place - held) % o.w, 0)
    anchor = np.where(reused, of[held], of) if m else of
    labels, iterations = np.zeros((len(opens) + 1, o.w), np.int16), np.zeros(m, np.int32)
    small = few[opens] & o.few
    labels[1:][small] = ranks(block, at[opens[small]])
    todo = opens[~small]
    if len(todo):
        labels[of[todo]], iterations[todo] = clusters(block, at[todo], np.minimum(distinct[todo], k), o)
    # With one cluster all transitions are the same pair.
    n = min(o.n, o.w - 1)
    num = np.full(m, (o.w - 1) ** n, _kind(n, o.w))
    den, divisions = num.copy(), np.full(m, min(n, 1), np.int32)
    rest = np.flatnonzero(~done)
    if len(rest):
        num[rest], den[rest], divisions[rest] = probabilities(labels, anchor[rest], shift[rest], o)
    return {"at": at, "rule": rule, "rotated": rotated, "single": single, "few": few, "distinct": distinct, "iterations": iterations, "num": num, "den": den, "divisions": divisions, "labels": labels, "anchor": anchor, "shift": shift}
