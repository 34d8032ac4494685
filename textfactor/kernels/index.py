"""Compressed text indexes: LF powers by pull-back, evenly sampled and run-sampled locate, and the level index over run boundaries.

Rows are those of the BWT of text + sentinel, 0-based; row 0 is the sentinel's. Text position n is the sentinel.
"""

from __future__ import annotations

import functools
import math
from bisect import bisect_left, bisect_right

import numpy as np

from textfactor.kernels.grammar import PhraseLce
from textfactor.kernels.lz import Phrase, decode, lz77
from textfactor.kernels.suffix import SuffixOrder, bwt, codes_of, lf_mapping, runs_of, with_sentinel


class BwtRuns:
    """Run-length BWT with rank, LF and backward search; O(runs) words."""

    def __init__(self, last: np.ndarray):
        self.n = len(last)
        self.runs = runs_of(last)
        self.first = np.array([a for _, a, _ in self.runs], np.int64)
        self.sym = np.array([c for c, _, _ in self.runs], np.int64)
        size = np.diff(np.r_[self.first, self.n])
        self.start: dict[int, int] = {}
        self.by_sym: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        at = 0
        for c in np.unique(self.sym).tolist():
            mine = np.flatnonzero(self.sym == c)
            self.by_sym[c] = (mine, np.r_[0, np.cumsum(size[mine])])
            self.start[c] = at
            at += int(size[mine].sum())
        self.lf_first = np.empty(len(self.runs), np.int64)
        for c, (mine, before) in self.by_sym.items():
            self.lf_first[mine] = self.start[c] + before[:-1]
        # the same as lists: single rows are looked up much faster in them
        self._first, self._lf = self.first.tolist(), self.lf_first.tolist()
        self._ranks = {c: (self.first[mine].tolist(), before.tolist()) for c, (mine, before) in self.by_sym.items()}

    def run_of(self, row: int) -> int:
        return bisect_right(self._first, row) - 1

    def symbol(self, row: int) -> int:
        return int(self.sym[self.run_of(row)])

    def lf(self, row: int) -> int:
        k = bisect_right(self._first, row) - 1
        return self._lf[k] + row - self._first[k]

    def lf_pow_naive(self, row: int, k: int) -> int:
        for _ in range(k):
            row = self.lf(row)
        return row

    def rank(self, c: int, row: int) -> int:
        """Occurrences of c in rows before row."""
        if c not in self._ranks:
            return 0
        firsts, before = self._ranks[c]
        k = bisect_left(firsts, row) - 1
        if k < 0:
            return 0
        return before[k] + min(row - firsts[k], before[k + 1] - before[k])

    def backward(self, pattern: np.ndarray) -> tuple[int, int]:
        """Half-open row range of the suffixes that start with pattern (codes + 2)."""
        lo, hi = 0, self.n
        for c in pattern[::-1].tolist():
            if c not in self.start:
                return 0, 0
            lo, hi = self.start[c] + self.rank(c, lo), self.start[c] + self.rank(c, hi)
            if lo >= hi:
                return 0, 0
        return lo, hi

    def words(self) -> int:
        return 3 * len(self.runs)


class LfPower:
    """LF^(2^level) as intervals (start, image, symbol id); rows inside an interval keep their offset."""

    def __init__(self, start: np.ndarray, image: np.ndarray, sym: np.ndarray, n: int, power: int = 1):
        self.start, self.image, self.sym, self.n, self.power = start, image, sym, n, power

    @classmethod
    def level0(cls, runs: BwtRuns) -> LfPower:
        return cls(runs.first, runs.lf_first, runs.sym, runs.n)

    def apply(self, row):
        k = np.searchsorted(self.start, row, "right") - 1
        return self.image[k] + row - self.start[k]

    def doubled(self) -> LfPower:
        """Pull back every interval start that lies strictly inside an image; then relabel pairs of symbols."""
        end = np.r_[self.start[1:], self.n]
        size = end - self.start
        low = np.searchsorted(self.start, self.image, "right")
        high = np.searchsorted(self.start, self.image + size, "left")
        n_cuts = np.maximum(high - low, 0)
        owner = np.repeat(np.arange(len(size)), n_cuts)
        inside = np.arange(n_cuts.sum()) - np.repeat(np.cumsum(n_cuts) - n_cuts, n_cuts) + low[owner]
        cuts = self.start[owner] + self.start[inside] - self.image[owner]
        start = np.sort(np.r_[self.start, cuts])
        once = self.apply(start)
        k, own = np.searchsorted(self.start, once, "right") - 1, np.searchsorted(self.start, start, "right") - 1
        pair = self.sym[k] * (self.sym.max(initial=0) + 1) + self.sym[own]
        return LfPower(start, self.apply(once), np.unique(pair, return_inverse=True)[1], self.n, 2 * self.power)

    def __len__(self) -> int:
        return len(self.start)


def lf_power(runs: BwtRuns, tau: int) -> LfPower:
    """Table for tau, a power of two; at most tau * runs intervals."""
    table = LfPower.level0(runs)
    while table.power < tau:
        table = table.doubled()
    return table


class _Built:
    def __init__(self, text):
        self.text = text
        codes = with_sentinel(codes_of(text))
        self.order = SuffixOrder(codes)
        self.n = len(codes)
        self.last = codes[self.order.sa - 1]

    @functools.cached_property
    def runs(self) -> BwtRuns:
        return BwtRuns(self.last)

    @staticmethod
    def pattern(p) -> np.ndarray:
        return codes_of(p) + 2


class Patterns:
    """Many patterns for FmIndex.locate_all: their codes backwards, one row a pattern, ready for any number of texts."""

    def __init__(self, patterns):
        self.size = np.fromiter(map(len, patterns), np.int64, len(patterns))
        self.back = np.full((int(self.size.max(initial=0)), len(patterns)), -1, np.int64)
        for k, p in enumerate(patterns):
            self.back[: len(p), k] = codes_of(p)[::-1] + 2


class FmIndex(_Built):
    """Backward search with suffix-array samples at every step-th text position."""

    def __init__(self, text, step: int = 16):
        super().__init__(text)
        self.step = step
        sa = self.order.sa
        self.sampled = (sa % step == 0) | (sa == self.n - 1)
        rows = np.flatnonzero(self.sampled)
        self.sample_of = np.cumsum(self.sampled) - 1
        self.sample = sa[rows]
        self.samples = dict(zip(rows.tolist(), self.sample.tolist(), strict=True))

    def locate_all(self, patterns: Patterns) -> tuple[np.ndarray, np.ndarray]:
        """(how often each pattern is there, all places, ordered by pattern and place): locate of all patterns, one step of all searches at a time."""
        n = self.n
        order = np.argsort(self.last, kind="stable")
        keys = self.last[order] * (n + 1) + order  # where (symbol, row) stands among these is LF of the row
        lo, hi, left = np.zeros(len(patterns.size), np.int64), np.full(len(patterns.size), n, np.int64), np.arange(len(patterns.size))
        for j, symbols in enumerate(patterns.back):
            left = left[patterns.size[left] > j]
            c = symbols[left] * (n + 1)
            lo[left], hi[left] = np.searchsorted(keys, c + lo[left]), np.searchsorted(keys, c + hi[left])
            left = left[lo[left] < hi[left]]
        count = np.maximum(hi - lo, 0)
        owner = np.repeat(np.arange(len(count)), count)
        row = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count) + lo[owner]
        lf, steps = np.empty(n, np.int64), np.zeros(len(row), np.int64)
        lf[order] = np.arange(n)
        walking = np.flatnonzero(~self.sampled[row])
        while len(walking):
            row[walking] = lf[row[walking]]
            steps[walking] += 1
            walking = walking[~self.sampled[row[walking]]]
        at = self.sample[self.sample_of[row]] + steps
        return count, at[np.argsort(owner * (n + 1) + at, kind="stable")]

    def count(self, p) -> int:
        lo, hi = self.runs.backward(self.pattern(p))
        return hi - lo

    def sa(self, row: int) -> int:
        steps = 0
        while row not in self.samples:
            row, steps = self.runs.lf(row), steps + 1
        return self.samples[row] + steps

    def locate(self, p) -> list[int]:
        lo, hi = self.runs.backward(self.pattern(p))
        return sorted(self.sa(r) for r in range(lo, hi))

    def words(self) -> int:
        return self.runs.words() + 2 * len(self.samples)


class SlowIndex(_Built):
    """Samples tau apart in the text, found by walking LF^tau from the sentinel row; queries take at most tau steps."""

    def __init__(self, text, tau: int | None = None):
        super().__init__(text)
        r = len(self.runs.runs)
        self.tau = tau or 1 << max(0, round(math.log2(max(1.0, math.sqrt(self.n / r)))))
        self.power = lf_power(self.runs, self.tau)
        self.by_row, self.by_pos, row = {}, {}, 0
        for position in range(self.n - 1, -1, -self.tau):
            self.by_row[row], self.by_pos[position] = position, row
            row = int(self.power.apply(row))

    def sa(self, row: int) -> int:
        steps = 0
        while row not in self.by_row:
            row, steps = self.runs.lf(row), steps + 1
            if steps > self.tau:  # rows before the first sample of the text wrap past its start
                break
        if row in self.by_row:
            return (self.by_row[row] + steps) % self.n
        while row not in self.by_row:
            row, steps = self.runs.lf(row), steps + 1
        return (self.by_row[row] + steps) % self.n

    def isa(self, position: int) -> int:
        steps = (self.n - 1 - position) % self.tau
        return self.runs.lf_pow_naive(self.by_pos[position + steps], steps)


class RIndex(_Built):
    """Run-sampled index: a toehold from run ends, neighbours by the phi map over run starts."""

    def __init__(self, text):
        super().__init__(text)
        sa, first = self.order.sa, self.runs.first
        ends = np.r_[first[1:], self.n] - 1
        self.end_sa = sa[ends]
        heads = first[1:]
        order = np.argsort(sa[heads])
        self.phi_at, self.phi_to = sa[heads][order], sa[heads - 1][order]

    def phi(self, value: int) -> int:
        """Suffix array value of the row before the one that holds value."""
        k = int(np.searchsorted(self.phi_at, value, "right")) - 1
        return int(self.phi_to[k] + value - self.phi_at[k])

    def count(self, p) -> int:
        lo, hi = self.runs.backward(self.pattern(p))
        return hi - lo

    def locate(self, p) -> list[int]:
        runs, pattern = self.runs, self.pattern(p)
        lo, hi, held = 0, runs.n, int(self.end_sa[-1])
        for c in pattern[::-1].tolist():
            if c not in runs.start:
                return []
            if runs.symbol(hi - 1) == c:
                held -= 1
            else:
                mine, _ = runs.by_sym[c]
                k = int(np.searchsorted(runs.first[mine], hi - 1, "right")) - 1
                if k < 0:
                    return []
                held = int(self.end_sa[mine[k]]) - 1
            lo, hi = runs.start[c] + runs.rank(c, lo), runs.start[c] + runs.rank(c, hi)
            if lo >= hi:
                return []
        out = [held]
        for _ in range(hi - lo - 1):
            out.append(self.phi(out[-1]))
        return sorted(v for v in out if v < self.n - 1) if len(pattern) else sorted(out)

    def words(self) -> int:
        return self.runs.words() + 3 * len(self.end_sa)


def first_boundary(same: np.ndarray, lf_to, lo: int, hi: int) -> tuple[int, int]:
    """For rows lo..hi-1 (two or more): the least k for which their LF^k image has a run start strictly inside, and the image's first row.

    same[r]: common suffix length of what precedes the suffixes of rows r-1 and r; the image breaks where it is least."""
    k = int(same[lo + 1 : hi].min())
    return k, lf_to(lo, k)


class SaIndex(_Built):
    """Suffix-array values by O(log(n/r)) jumps: every block of rows knows how many LF steps bring it around a run boundary, where blocks
    half as long cover it again; single rows at boundaries hold their value."""

    def __init__(self, text):
        super().__init__(text)
        sa, isa, n = self.order.sa, self.order.isa, self.n
        self.r = len(self.runs.runs)
        back = SuffixOrder(codes_of(with_sentinel(codes_of(text)))[::-1])
        self.same = np.zeros(n, np.int64)
        if n > 1:  # common suffixes of the prefixes before two suffixes: extensions of the reversed text
            self.same[1:] = back.lce(n - sa[:-1], n - sa[1:])
        to = lambda row, k: int(isa[sa[row] - k])
        self.size0 = max(1, math.ceil(n / self.r))
        self.levels: list[dict[tuple[int, int], tuple[int, int, int]]] = []
        self.top = {b: self._node(b * self.size0, min(n, (b + 1) * self.size0), to) for b in range(math.ceil(n / self.size0))}
        self.half = [self.size0]
        while self.half[-1] > 1:
            s, step = self.half[-1], (self.half[-1] + 1) // 2
            level = {}
            for q, p in enumerate(self.runs.first.tolist()):
                for b, lo in enumerate(range(p - s, p + s, step)):
                    a, z = max(0, lo), min(n, lo + step, p + s)
                    if a < z:
                        level[q, b] = self._node(a, z, to)
            self.levels.append(level)
            self.half.append(step)
        self.exact = {row: int(sa[row]) for p in self.runs.first.tolist() for row in (p - 1, p) if row >= 0}

    def _node(self, lo: int, hi: int, to) -> tuple[int, int, int]:
        """(first row, image's first row, steps); a single row has itself with its value as steps = -1 - value."""
        if hi - lo == 1:
            return lo, lo, -1 - int(self.order.sa[lo])
        k, image = first_boundary(self.same, to, lo, hi)
        return lo, image, k

    def sa(self, row: int) -> int:
        lo, image, k = self.top[row // self.size0]
        add = 0
        for t in range(len(self.half)):
            if k < 0:
                return add - 1 - k
            row, add = image + row - lo, add + k
            if t == len(self.half) - 1:
                break
            size = self.half[t]
            q = self._boundary(row, size)
            lo, image, k = self.levels[t][q, (row - (int(self.runs.first[q]) - size)) // self.half[t + 1]]
        return add + self.exact[row]

    def _boundary(self, row: int, size: int) -> int:
        """A run start within size of row."""
        k = self.runs.run_of(row)
        if row - self.runs.first[k] < size:
            return k
        return k + 1

    def isa(self, position: int) -> int:
        """Binary search over rows; suffixes are compared by extension."""
        lo, hi = 0, self.n - 1
        codes = self.order.codes
        while lo < hi:
            mid = (lo + hi) // 2
            v = self.sa(mid)
            if v == position:
                return mid
            m = self.lce(v, position)
            if codes[v + m] < codes[position + m]:
                lo = mid + 1
            else:
                hi = mid
        return lo

    def lce(self, i: int, j: int) -> int:
        """Common extension of two text positions, from fingerprints on the text's phrases."""
        if not hasattr(self, "_phrases"):
            phrases = lz77(self.text)
            self._phrases = PhraseLce(phrases, phrases)
        return self._phrases.lce(i, j)

    def subtree(self, p) -> int:
        """Leaves below the place of pattern p in the suffix tree."""
        lo, hi = self.runs.backward(self.pattern(p))
        return hi - lo

    def dsa(self) -> np.ndarray:
        return np.diff(self.order.sa, prepend=0)

    def words(self) -> int:
        return self.runs.words() + 3 * len(self.top) + 3 * sum(map(len, self.levels)) + 2 * len(self.exact)


def find_q(index: SaIndex, row: int, size: int) -> int:
    """Another row whose differential values over `size` rows equal those after `row`: the image at the first boundary."""
    k = int(index.same[row : row + size].min()) if size else 0
    return int(index.order.isa[index.order.sa[row] - k])


def build_indexes_metered(text) -> dict:
    """Sizes and modelled construction cost of every index of one text."""
    r_index, levels, slow = RIndex(text), SaIndex(text), SlowIndex(text)
    n, r = r_index.n, len(r_index.runs.runs)
    return {"n": n - 1, "r": r, "tau": slow.tau, "lf_intervals": len(slow.power), "r_words": r_index.words(), "sa_words": levels.words(), "fm_words": FmIndex(text, max(1, slow.tau)).words(), "modelled_queries": math.sqrt(r * n), "levels": len(levels.half)}


def rlbwt_from_lz(phrases: list[Phrase]) -> BwtRuns:
    """Run-length BWT of a factorized text."""
    return BwtRuns(bwt(decode(phrases)))


def naive_lf(last: np.ndarray) -> np.ndarray:
    return lf_mapping(last)
