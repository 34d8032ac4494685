"""Suffix order of one text: ranks by doubling, longest common extensions, BWT and its runs, LF."""

from __future__ import annotations

import numpy as np


def codes_of(text) -> np.ndarray:
    """Order-preserving integers: code points of a string, or the given integers."""
    if isinstance(text, str):
        return np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.int64) if text else np.empty(0, np.int64)
    return np.asarray(text, np.int64)


def dense(values: np.ndarray) -> np.ndarray:
    return np.unique(values, return_inverse=True)[1].astype(np.int64)


def symbols_of(text) -> str:
    """Any sequence as a string over dense symbols in the same order, for the C-speed string searches."""
    if isinstance(text, str):
        return text
    codes = dense(codes_of(text))
    return "".join(chr(c if c < 0xD800 else c + 0x800) for c in codes)


class SuffixOrder:
    """levels[t][i]: dense rank of the window of length 2^t at i; the last level is the suffix rank (0-based)."""

    def __init__(self, text):
        self.codes = codes_of(text)
        n = self.n = len(self.codes)
        rank = dense(self.codes) if n else np.empty(0, np.int64)
        self.levels, width = [rank], 1
        while n and rank.max() < n - 1:
            after = np.full(n, -1, np.int64)
            after[: n - width] = rank[width:] if width < n else after[:0]
            rank = dense(rank * (n + 1) + after + 1)
            self.levels.append(rank)
            width *= 2
        self.isa = rank
        self.sa = np.empty(n, np.int64)
        self.sa[rank] = np.arange(n)

    def _lce_one(self, i: int, j: int) -> int:
        if i == j:
            return self.n - i
        if not hasattr(self, "_lists"):
            self._lists = [level.tolist() for level in self.levels]
        n, start = self.n, i
        for t in range(len(self._lists) - 1, -1, -1):
            level, width = self._lists[t], 1 << t
            while i < n and j < n and level[i] == level[j]:
                i, j = i + width, j + width
        return i - start

    def lce(self, i, j):
        """Longest common extension of suffixes i and j (arrays or ints); position n stands for the empty suffix."""
        if isinstance(i, int) and isinstance(j, int):
            return self._lce_one(i, j)
        a, b = np.atleast_1d(np.asarray(i, np.int64)).copy(), np.atleast_1d(np.asarray(j, np.int64)).copy()
        a, b = np.broadcast_arrays(a, b)
        a, b = a.copy(), b.copy()
        start = a.copy()
        same = a == b
        for t in range(len(self.levels) - 1, -1, -1):
            level = self.levels[t]
            for _ in range(2 if t == len(self.levels) - 1 else 1):
                ok = (a < self.n) & (b < self.n)
                hit = np.zeros(len(a), bool)
                hit[ok] = level[a[ok]] == level[b[ok]]
                step = np.where(hit & ~same, 1 << t, 0)
                a, b = a + step, b + step
        out = np.where(same, self.n - start, a - start)
        return out if np.ndim(i) or np.ndim(j) else int(out[0])

    def lcp(self) -> np.ndarray:
        """lcp[r]: common prefix of the suffixes of ranks r-1 and r; 0 first."""
        out = np.zeros(self.n, np.int64)
        if self.n > 1:
            out[1:] = self.lce(self.sa[:-1], self.sa[1:])
        return out


def range_lcp(order: SuffixOrder, lo: int, hi: int) -> int:
    """Common prefix of all suffixes with ranks lo..hi: that of the two outer ones."""
    return order.n - int(order.sa[lo]) if lo == hi else order.lce(int(order.sa[lo]), int(order.sa[hi]))


def with_sentinel(codes: np.ndarray) -> np.ndarray:
    """Codes shifted by 2 with a unique least 0 at the end (1 is kept for separators)."""
    return np.r_[codes + 2, 0]


def bwt(text, sentinel: bool = True) -> np.ndarray:
    """Codes before each suffix in rank order. With sentinel: of text+$ (code 0, others +2). Without: of the sorted rotations."""
    codes = codes_of(text)
    if sentinel:
        full = with_sentinel(codes)
        sa = SuffixOrder(full).sa
        return full[sa - 1]
    n = len(codes)
    if not n:
        return codes
    sa = SuffixOrder(np.r_[codes, codes]).sa
    rows = sa[sa < n]
    return codes[rows - 1]


def inverse_bwt(last: np.ndarray) -> np.ndarray:
    """Text codes from a BWT with sentinel 0 (see bwt)."""
    lf, out, row = lf_mapping(last), np.empty(len(last) - 1, np.int64), 0
    for k in range(len(last) - 2, -1, -1):
        out[k] = last[row]
        row = lf[row]
    return out - 2


def lf_mapping(last: np.ndarray) -> np.ndarray:
    """LF as an array: the row of the suffix one position to the left."""
    order = np.argsort(last, kind="stable")
    lf = np.empty(len(last), np.int64)
    lf[order] = np.arange(len(last))
    return lf


def runs_of(last: np.ndarray) -> list[tuple[int, int, int]]:
    """(symbol, first row, last row) of the maximal runs."""
    if not len(last):
        return []
    first = np.flatnonzero(np.r_[True, last[1:] != last[:-1]])
    ends = np.r_[first[1:], len(last)] - 1
    return [(int(last[a]), int(a), int(b)) for a, b in zip(first, ends, strict=True)]


def run_count(text, sentinel: bool = True) -> int:
    return len(runs_of(bwt(text, sentinel)))


def lcp_intervals(order: SuffixOrder) -> list[tuple[int, int, int]]:
    """Inner nodes of the suffix tree as (lo, hi, depth), by a stack over the LCP array."""
    lcp, out, stack = [*order.lcp().tolist(), 0], [], [(0, 0)]
    for r in range(1, order.n + 1):
        left = r - 1
        h = lcp[r] if r < order.n else -1
        while stack and stack[-1][1] > h:
            left, depth = stack.pop()
            out.append((left, r - 1, depth))
        if not stack or stack[-1][1] < h:
            stack.append((left, h))
    return [(lo, hi, d) for lo, hi, d in out if hi > lo]


def distinct_counts(order: SuffixOrder) -> np.ndarray:
    """d[q] for q = 0..n: distinct substrings of length q, from the LCP histogram."""
    n = order.n
    shorter = np.bincount(order.lcp(), minlength=n + 1)[: n + 1]
    ends = np.arange(n + 1)  # suffixes shorter than q don't hold a q-gram
    holders = n - ends + 1
    repeated = np.cumsum(shorter[::-1])[::-1]  # ranks whose lcp is >= q
    d = holders - repeated
    d[0] = 1
    return d


def delta(text) -> float:
    """Substring complexity: max over q of d[q] / q."""
    order = SuffixOrder(text)
    if not order.n:
        return 0.0
    d = distinct_counts(order)
    return float((d[1:] / np.arange(1, order.n + 1)).max())
