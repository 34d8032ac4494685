"""Problems answered from suffix order and run boundaries: common substrings, unique matches, repeats, Lyndon factors, q-grams."""

from __future__ import annotations

from collections import Counter

import numpy as np

from textfactor.kernels.cost import gallop
from textfactor.kernels.suffix import SuffixOrder, codes_of, runs_of, symbols_of


class _Two:
    """Suffix order of a # b $ with $ < # < all symbols."""

    def __init__(self, a, b):
        ca, cb = codes_of(a), codes_of(b)
        self.na, self.nb = len(ca), len(cb)
        self.codes = np.r_[ca + 2, 1, cb + 2, 0]
        self.order = SuffixOrder(self.codes)
        self.sa, self.last = self.order.sa, self.codes[self.order.sa - 1]
        self.first_text = self.sa <= self.na
        self.lcp = self.order.lcp()


def longest_common_substring(a, b) -> tuple[int, int, int]:
    """(start in a, start in b, length): the longest match lies across a boundary of BWT runs. Ties: smallest starts."""
    two = _Two(a, b)
    heads = np.array([first for _, first, _ in runs_of(two.last)][1:], np.int64)
    mixed = heads[two.first_text[heads] != two.first_text[heads - 1]]
    if not len(mixed) or not two.lcp[mixed].max(initial=0):
        return 0, 0, 0
    size = int(two.lcp[mixed].max())
    s, t = symbols_of(a), symbols_of(b)
    if not (isinstance(a, str) and isinstance(b, str)):
        both = symbols_of(np.r_[codes_of(a), codes_of(b)])
        s, t = both[: two.na], both[two.na :]
    grams = {t[j : j + size] for j in range(len(t) - size + 1)}
    i = next(i for i in range(len(s) - size + 1) if s[i : i + size] in grams)
    return i, t.find(s[i : i + size]), size


def maximal_unique_matches(a, b, least: int = 1) -> list[tuple[int, int, int]]:
    """(start in a, start in b, length) of matches that occur once in each text and extend in neither direction."""
    two = _Two(a, b)
    lcp, n = [*two.lcp.tolist(), 0], len(two.sa)
    out = []
    for r in range(1, n):
        size = lcp[r]
        if size < least or two.first_text[r] == two.first_text[r - 1] or two.last[r] == two.last[r - 1]:
            continue
        if lcp[r - 1] < size and lcp[r + 1] < size:
            i, j = sorted((int(two.sa[r - 1]), int(two.sa[r])))
            out.append((i, j - two.na - 1, size))
    return sorted(out)


def _gram_prints(codes: np.ndarray, size: int) -> np.ndarray:
    """A 64-bit print of every gram of `size` symbols."""
    out = np.zeros(max(0, len(codes) - size + 1), np.uint64)
    c = codes.astype(np.uint64)
    for k in range(size):
        out = out * np.uint64(0x9E3779B97F4A7C15) + c[k : k + len(out)]
    return out * np.uint64(0xD6E8FEB86659FD93)


def unique_match_sizes(texts: list[str], pairs, least: int):
    """(x, y, (number, longest)) of the maximal unique matches of at least `least` symbols of each pair of places in texts.

    Such a match lies on grams of `least` symbols that both texts hold, so only grams of two texts are kept, with their places. Matches that extend in neither
    direction are the longest runs of grams that go on in step; a run is compared as text, since prints may collide, and looked for at the other places of
    its first gram. Pairs with a collision, or with more combinations of places than symbols, go through the suffix order."""
    prints = [_gram_prints(codes_of(t), least) for t in texts]
    every = np.sort(np.concatenate([np.unique(p) for p in prints])) if prints else np.empty(0, np.uint64)
    shared = np.unique(every[1:][every[1:] == every[:-1]])
    places: list[dict[int, list[int]]] = []
    for p in prints:
        near = np.minimum(np.searchsorted(shared, p), max(0, len(shared) - 1))
        held: dict[int, list[int]] = {}
        for i in (np.flatnonzero(shared[near] == p) if len(shared) else near[:0]).tolist():
            held.setdefault(int(near[i]), []).append(i)
        places.append(held)
    for x, y in pairs:
        found = _runs_in_step(texts[x], texts[y], places[x], places[y], least)
        if found is None:
            sizes = [m for _, _, m in maximal_unique_matches(texts[x], texts[y], least)]
            found = len(sizes), max(sizes, default=0)
        yield x, y, found


def _runs_in_step(x: str, y: str, in_x: dict, in_y: dict, least: int) -> tuple[int, int] | None:
    """(number, longest) of the runs whose text is once in x and once in y; None if a run differs as text or there are too many combinations of places."""
    cells, most = [], len(x) + len(y)
    for g in in_x.keys() & in_y.keys():
        cells += [(b - a, a, g) for a in in_x[g] for b in in_y[g]]
        if len(cells) > most:
            return None
    cells.sort()
    count = longest = k = 0
    while k < len(cells):
        shift, p, g = cells[k]
        size = least
        k += 1
        while k < len(cells) and cells[k][0] == shift and cells[k][1] == p + size - least + 1:
            k, size = k + 1, size + 1
        run = x[p : p + size]
        if not y.startswith(run, p + shift):
            return None
        if all(len(at) == 1 or sum(t.startswith(run, i) for i in at) == 1 for t, at in ((x, in_x[g]), (y, in_y[g]))):
            count, longest = count + 1, max(longest, size)
    return count, longest


def longest_repeat(text) -> tuple[int, int]:
    """(leftmost start, length) of the longest substring with two occurrences; length 0 if none."""
    s = symbols_of(text)
    order = SuffixOrder(s)
    size = int(order.lcp().max(initial=0))
    if not size:
        return 0, 0
    rows = np.flatnonzero(order.lcp() == size)
    return int(min(order.sa[rows].min(), order.sa[rows - 1].min())), size


def shortest_unique(text) -> tuple[int, int]:
    """(leftmost start, length) of the shortest substring with one occurrence; (0, 0) for the empty text."""
    order = SuffixOrder(symbols_of(text))
    if not order.n:
        return 0, 0
    lcp = order.lcp()
    need = np.maximum(lcp, np.r_[lcp[1:], 0]) + 1
    fits = order.sa + need <= order.n
    size = int(need[fits].min())
    return int(order.sa[fits & (need == size)].min()), size


def lyndon(text) -> list[tuple[int, int]]:
    """(start, length) of the non-increasing Lyndon factors: strict prefix minima of the inverse suffix array, galloped."""
    order = SuffixOrder(symbols_of(text))
    n, out, i = order.n, [], 0
    isa = order.isa
    low = np.minimum.accumulate(isa) if n else isa
    while i < n:
        size = gallop(lambda m, i=i: low[i + m - 1] == isa[i], 1, n - i)
        out.append((i, size))
        i += size
    return out


def duval(text) -> list[tuple[int, int]]:
    s, out, i = symbols_of(text), [], 0
    while i < len(s):
        j, k = i + 1, i
        while j < len(s) and s[k] <= s[j]:
            k = i if s[k] < s[j] else k + 1
            j += 1
        while i <= k:
            out.append((i, j - k))
            i += j - k
    return out


def qgram_freq(text, q: int) -> list[tuple[int, int]]:
    """(start of one occurrence, frequency) of every q-gram, galloping from one to the next in suffix order."""
    order = SuffixOrder(symbols_of(text))
    sa, lcp, out, r = order.sa, order.lcp(), [], 0
    reach = np.minimum.accumulate
    while r < order.n:
        if order.n - sa[r] < q:
            r += 1
            continue
        size = gallop(lambda m, r=r: reach(lcp[r + 1 : r + m])[-1] >= q if m > 1 else True, 1, order.n - r)
        out.append((int(sa[r : r + size].min()), size))
        r += size
    return out


def with_recovered_text(phrases, function):
    """Any string problem on a factorized text: decode, then compute."""
    from textfactor.kernels.lz import decode

    return function(decode(phrases))


def qgram_counter(text: str, q: int) -> Counter:
    return Counter(text[i : i + q] for i in range(len(text) - q + 1))
