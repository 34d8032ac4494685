"""Factorizations of one text. A phrase is (start, length, source, symbol), 0-based; source -1 marks a fresh symbol.

greedy: longest previous factor, overlap allowed or not. phrase_end: sources end where an earlier phrase ends. grid: sources may also end
at every tau-th position; tau = 1 is the greedy form without overlap, tau >= n the phrase-end form.
"""

from __future__ import annotations

import bisect
import functools
import math

import numpy as np

from textfactor.kernels.cost import Ledger, gallop
from textfactor.kernels.suffix import SuffixOrder, codes_of, symbols_of

Phrase = tuple[int, int, int, int]


def previous_factors(order: SuffixOrder) -> tuple[np.ndarray, np.ndarray]:
    """(length, source) of the longest factor at each position that also starts earlier (overlap allowed)."""
    n = order.n
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    before, after = [-1] * n, [-1] * n  # neighbours in suffix order among smaller positions
    sa = order.sa.tolist()
    for r in range(n):
        before[sa[r]] = sa[r - 1] if r else -1
        after[sa[r]] = sa[r + 1] if r + 1 < n else -1
    prev, nxt = before[:], after[:]
    for i in range(n - 1, -1, -1):  # positions leave from the right; what remains is smaller
        p, q = prev[i], nxt[i]
        before[i], after[i] = p, q
        if p >= 0:
            nxt[p] = q
        if q >= 0:
            prev[q] = p
    p, q = np.array(before), np.array(after)
    here = np.arange(n)
    lp = np.where(p >= 0, order.lce(here, np.maximum(p, 0)), 0)
    lq = np.where(q >= 0, order.lce(here, np.maximum(q, 0)), 0)
    return np.maximum(lp, lq), np.where(lp >= lq, p, q)


def lz77(text, source: str = "leftmost", overlap: bool = True) -> list[Phrase]:
    s, codes = symbols_of(text), codes_of(text)
    length, _ = previous_factors(SuffixOrder(s))
    out, i, n = [], 0, len(s)
    while i < n:
        most = int(length[i])
        if not overlap and most:
            most = gallop(lambda m, i=i: s.find(s[i : i + m], 0, i) >= 0 if m else True, 0, min(most, i))
        if most == 0:
            out.append((i, 1, -1, int(codes[i])))
            i += 1
            continue
        piece = s[i : i + most]
        stop = i + most - 1 if overlap else i
        out.append((i, most, s.find(piece, 0, stop) if source == "leftmost" else s.rfind(piece, 0, stop), -1))
        i += most
    return out


def prefix_phrases(s: str, limit: int) -> list[int]:
    """End positions of at most `limit` greedy phrases of s, read from the left only as far as needed."""
    ends, i = [], 0
    while i < len(s) and len(ends) < limit:
        m = gallop(lambda k, i=i: k == 0 or s.find(s[i : i + k], 0, i + k - 1) >= 0, 0, len(s) - i)
        i += max(1, m)
        ends.append(i)
    return ends


def lz_size(text, overlap: bool = True) -> int:
    """Number of greedy phrases; sources are not looked for."""
    if not overlap:
        return len(lz77(text, overlap=False))
    length, _ = previous_factors(SuffixOrder(symbols_of(text)))
    steps, i, count = np.maximum(length, 1).tolist(), 0, 0
    while i < len(steps):
        i, count = i + steps[i], count + 1
    return count


def read_all(text, ledger: Ledger) -> list[Phrase]:
    """The baseline that reads every symbol once and factorizes classically."""
    ledger.oracle_reads += len(text)
    return lz77(text)


class DynamicLce:
    """A growing text with common extensions: symbols are appended one by one or as a copy of an earlier fragment. Fingerprints of all prefixes stand in for
    the persistent structure: an append costs a step per symbol, an extension a binary search."""

    # fixed values: modulus and base of the rolling fingerprint
    MODULUS, BASE = (1 << 61) - 1, 911_382_323

    def __init__(self):
        self.codes: list[int] = []
        self.prefix, self.power = [0], [1]

    def __len__(self) -> int:
        return len(self.codes)

    def push_symbol(self, code: int) -> None:
        self.codes.append(code)
        self.prefix.append((self.prefix[-1] * self.BASE + code + 1) % self.MODULUS)
        self.power.append(self.power[-1] * self.BASE % self.MODULUS)

    def push_copy(self, start: int, size: int) -> None:
        """Appends text[start : start + size]; the fragment may run into what is being appended."""
        for k in range(start, start + size):
            self.push_symbol(self.codes[k])

    def print_of(self, lo: int, hi: int) -> int:
        return (self.prefix[hi] - self.prefix[lo] * self.power[hi - lo]) % self.MODULUS

    def lce(self, i: int, j: int) -> int:
        """Longest common prefix of the suffixes at i and j."""
        return gallop(lambda m: m == 0 or self.print_of(i, i + m) == self.print_of(j, j + m), 0, len(self) - max(i, j))

    def lcs(self, a: int, b: int) -> int:
        """Longest common suffix of the prefixes of lengths a and b."""
        return gallop(lambda m: m == 0 or self.print_of(a - m, a) == self.print_of(b - m, b), 0, min(a, b))


def common_suffixes(s: str) -> list[list[int]]:
    """[a][b]: longest common suffix of the prefixes of lengths a and b."""
    codes, row, out = codes_of(s), np.zeros(len(s) + 1, np.int64), []
    out.append(row.tolist())
    for c in codes:
        row = np.r_[0, np.where(codes == c, row[:-1] + 1, 0)]
        out.append(row.tolist())
    return out


class PrefixRanks:
    """What the co-lexicographic order of a text's prefixes needs to know of the text; every factorization of the text can use it."""

    TABLE = 256  # a text of up to so many symbols has all its common suffixes in a table

    def __init__(self, s: str):
        self.reverse = SuffixOrder(s[::-1])
        self.rank = np.r_[-1, self.reverse.isa[::-1]].tolist()  # of the prefix of each length
        self.end_of_rank = {r: e for e, r in enumerate(self.rank)}
        self.table = common_suffixes(s) if len(s) <= self.TABLE else None


class PrefixOrder:
    """Allowed source ends in co-lexicographic order of their prefixes, kept sorted as ends are inserted."""

    FEW = 24  # fixed value: comparing ranks is charged nowhere, so a selection may sort its last few elements

    def __init__(self, s: str, ledger: Ledger | None = None, ranks: PrefixRanks | None = None):
        ranks = ranks or PrefixRanks(s)
        self.n, self.reverse, self.rank, self.end_of_rank, self.table = len(s), ranks.reverse, ranks.rank, ranks.end_of_rank, ranks.table
        self.ledger = ledger or Ledger()
        self.keys: list = []
        self.ends: list[int] = []
        self.members: set[int] = set()

    def key(self, end: int):
        """What orders the prefix of this length among the others."""
        return self.rank[end]

    def end_of(self, key) -> int:
        return self.end_of_rank[key]

    def read(self, start: int, size: int, source: int, code: int) -> None:
        """A phrase was factorized; nothing to do for an order of the whole text."""

    def insert(self, end: int) -> None:
        if end in self.members:
            return
        key = self.key(end)
        at = bisect.bisect_left(self.keys, key)
        self.ledger.comparisons += max(1, len(self.keys)).bit_length()
        self.keys.insert(at, key)
        self.ends.insert(at, end)
        self.members.add(end)

    def common(self, a: int, b: int) -> int:
        """Longest common suffix of the prefixes of lengths a and b."""
        self.ledger.lce_calls += 1
        if self.table is not None:
            return self.table[a][b]
        return a if a == b else int(self.reverse.lce(self.n - a, self.n - b))

    def holder(self, start: int, end: int) -> int | None:
        """An allowed end whose prefix has text[start:end] as a suffix."""
        at, need, ends = bisect.bisect_left(self.keys, self.key(end)), end - start, self.ends
        if at and self.common(ends[at - 1], end) >= need:
            return ends[at - 1]
        return ends[at] if at < len(ends) and self.common(ends[at], end) >= need else None

    def range_with_suffix(self, start: int, end: int) -> tuple[int, int]:
        """Half-open range of the allowed ends whose prefixes have text[start:end] as a suffix."""
        need = end - start
        if need <= 0:
            return 0, len(self.ends)
        at = bisect.bisect_left(self.keys, self.key(end))
        lo = bisect.bisect_left(range(at), True, key=lambda k: self.common(self.ends[k], end) >= need)
        hi = bisect.bisect_left(range(at, len(self.ends)), True, key=lambda k: self.common(self.ends[k], end) < need) + at
        return lo, hi


@functools.total_ordering
class _Prefix:
    """Co-lexicographic order of prefixes by their common suffix and the symbols before it."""

    def __init__(self, order: DynamicPrefixOrder, end: int):
        self.order, self.end = order, end

    def __eq__(self, other) -> bool:
        return self.end == other.end

    def __lt__(self, other) -> bool:
        a, b = self.end, other.end
        k = self.order.common(a, b)
        return a < b if k == min(a, b) else self.order.s[a - k - 1] < self.order.s[b - k - 1]


class DynamicPrefixOrder(PrefixOrder):
    """The same order over what has been factorized only: extensions of the read part come from DynamicLce, which phrases extend by copies; symbols
    further right are compared by a search that is charged."""

    FEW = 0

    def __init__(self, s: str, ledger: Ledger | None = None, ranks: PrefixRanks | None = None):
        self.s, self.n, self.ledger, self.dynamic = s, len(s), ledger or Ledger(), DynamicLce()
        self.keys, self.ends, self.members = [], [], set()

    def key(self, end: int) -> _Prefix:
        return _Prefix(self, end)

    def end_of(self, key: _Prefix) -> int:
        return key.end

    def read(self, start: int, size: int, source: int, code: int) -> None:
        if source < 0:
            self.dynamic.push_symbol(code)
        else:
            self.dynamic.push_copy(source, size)

    def common(self, a: int, b: int) -> int:
        self.ledger.lce_calls += 1
        if a == b:
            return a
        ahead = min(max(a, b) - len(self.dynamic), a, b)
        if ahead > 0:  # the unread part first
            self.ledger.search(ahead)
            k = next((k for k in range(ahead) if self.s[a - k - 1] != self.s[b - k - 1]), ahead)
            if k < ahead:
                return k
            return ahead + (self.common(a - ahead, b - ahead) if a > ahead and b > ahead else 0)
        return self.dynamic.lcs(a, b)


class _Shifted:
    """A range of the sorted ends, each `cut` symbols shorter: still sorted, and never copied."""

    def __init__(self, prefixes: PrefixOrder, lo: int, hi: int, cut: int):
        self.prefixes, self.lo, self.size, self.cut = prefixes, lo, hi - lo, cut

    def __len__(self) -> int:
        return self.size

    def __getitem__(self, k: int):
        return self.prefixes.key(self.prefixes.ends[self.lo + k] - self.cut)


def select_in_sorted(arrays: list[list], x: int, few: int = 0):
    """The x-th smallest (0-based) of sorted arrays that are never merged: weighted medians halve what is left, until at most `few` are left that are sorted."""
    arrays = [a for a in arrays if len(a)]
    left, right = [0] * len(arrays), [len(a) for a in arrays]
    while True:
        passed = sum(left)
        if sum(right) - passed <= few:
            return sorted([a[k] for a, lo, hi in zip(arrays, left, right, strict=True) for k in range(lo, hi)])[x - passed]
        spans = [(arrays[k][(left[k] + right[k]) // 2], right[k] - left[k], k) for k in range(len(arrays)) if left[k] < right[k]]
        spans.sort(key=lambda t: t[0])
        half, run = sum(w for _, w, _ in spans) / 2, 0
        for pivot, w, _ in spans:
            run += w
            if run >= half:
                break
        below = [bisect.bisect_left(a, pivot, left[k], right[k]) for k, a in enumerate(arrays)]
        upto = [bisect.bisect_right(a, pivot, left[k], right[k]) for k, a in enumerate(arrays)]
        if x < sum(below):
            right = below
        elif x < sum(upto):
            return pivot
        else:
            left = upto


class GridState:
    """State of the grid factorization: allowed ends, and the far test with its three search modes. order: static (of the whole text, built beforehand) or
    dynamic (of what is read)."""

    def __init__(self, text, tau: int, grid: str = "one", mode: str = "merged", ledger: Ledger | None = None, order: str = "static", ranks: PrefixRanks | None = None):
        self.s, self.tau, self.grid, self.mode = symbols_of(text), max(1, tau), grid, mode
        self.ledger = ledger or Ledger()
        self.prefixes = {"static": PrefixOrder, "dynamic": DynamicPrefixOrder}[order](self.s, self.ledger, ranks)

    def on_grid(self, end: int) -> bool:
        return (end - 1) % self.tau == 0 if self.grid == "one" else end % self.tau == 0

    def advance(self, old: int, new: int) -> None:
        for end in range(old + 1, new + 1):
            if self.on_grid(end) or end == new:
                self.prefixes.insert(end)

    def good(self, i: int, h: int) -> int | None:
        """h is the exclusive end of a candidate phrase starting at i; i itself stands for the empty phrase."""
        return i if h == i else self.prefixes.holder(i, h)

    def holds(self, i: int, j: int) -> bool:
        """Whether some h in [j - tau, j] is a potential phrase end."""
        return self._merged(i, j) if self.mode == "merged" else self.far(i, j) is not None

    def far(self, i: int, j: int) -> int | None:
        """Largest h in [j - tau, j] that is a potential phrase end, or None."""
        low = max(i, j - self.tau)
        if self.mode == "merged":
            return next((h for h in range(j, low - 1, -1) if self.good(i, h) is not None), None)
        reach = j  # least start of a held fragment so far; a fragment that ends further left starts no earlier unless it holds text[reach:h]
        for h in range(j, low - 1, -1):
            if h == i:
                return h
            start = min(reach, h)
            if start < h and self.prefixes.holder(start, h) is None:  # charged as common suffix calls
                continue
            reach = start - self._extend(i, start, h)
            if reach == i:
                return h
        return None

    def _extend(self, i: int, start: int, h: int) -> int:
        """By how many symbols text[start:h] can be extended to the left, not beyond i, and still be held; each one is read, or they are searched."""

        def held(m: int) -> bool:
            if self.mode == "linear":
                self.ledger.oracle_reads += 1
            else:
                self.ledger.search(m)
            return self.prefixes.holder(start - m, h) is not None

        if self.mode == "linear":
            m = 0
            while m < start - i and held(m + 1):
                m += 1
            return m
        return gallop(held, 0, start - i)

    def _merged(self, i: int, j: int) -> bool:
        """Each h keeps the ends that share text[low:h]; stripped of it they form one virtual sorted list that is searched once for text[i:low]."""
        low, prefixes, lists = max(i, j - self.tau), self.prefixes, []
        need, wanted = low - i, prefixes.key(low)
        for h in range(j, low - 1, -1):
            if h == i:
                return True  # the empty phrase
            lists.append(_Shifted(prefixes, *prefixes.range_with_suffix(low, h), h - low))
        total = sum(map(len, lists))
        if not total:
            return False
        self.ledger.search(need)
        lo, hi = 0, total  # first place in the virtual list that is not below the wanted prefix
        while lo < hi:
            mid = (lo + hi) // 2
            self.ledger.comparisons += 1
            if select_in_sorted(lists, mid, prefixes.FEW) < wanted:
                lo = mid + 1
            else:
                hi = mid
        near = (select_in_sorted(lists, k, prefixes.FEW) for k in (lo - 1, lo) if 0 <= k < total)
        return any(prefixes.common(prefixes.end_of(key), low) >= need for key in near)


def lz_end_grid(text, tau: int | str, grid: str = "one", mode: str = "merged", ledger: Ledger | None = None, limit: int | None = None, order: str = "static", z: int | None = None, ranks: PrefixRanks | None = None) -> list[Phrase] | None:
    """Grid factorization; None if more than `limit` phrases would be needed. tau "opt" is the best step for a known phrase count z. ranks: of the text, if
    several factorizations share them."""
    if tau == "opt":
        tau = math.ceil(math.sqrt(max(1, len(text)) / max(1, z or lz_size(text))))
    state, codes = GridState(text, tau, grid, mode, ledger, order, ranks), codes_of(text)
    s, out, i = state.s, [], 0
    n = len(s)
    while i < n:
        j = gallop(lambda v, i=i: state.holds(i, v), i, n)
        h = state.far(i, j)
        if h is None or h == i:
            out.append((i, 1, -1, int(codes[i])))
            h = i + 1
        else:
            out.append((i, h - i, state.good(i, h) - (h - i), -1))
        state.prefixes.read(*out[-1])
        state.advance(i, h)
        i = h
        if limit is not None and len(out) > limit:
            return None
    return out


def lz_end(text) -> list[Phrase]:
    """Phrase-end factorization."""
    return lz_end_direct(text, None)


def lz_end_direct(text, tau: int | None, grid: str = "one") -> list[Phrase]:
    """Phrase-end (tau None) or grid factorization by longest candidates, not metered; the length isn't monotone, so every length from the
    greedy bound down is looked at."""
    s, codes = symbols_of(text), codes_of(text)
    most, _ = previous_factors(SuffixOrder(s))
    prefixes, out, i = PrefixOrder(s), [], 0
    while i < len(s):
        size, src = 1, -1
        for m in range(min(int(most[i]), i), 0, -1):
            end = prefixes.holder(i, i + m)
            if end is not None:
                size, src = m, end - m
                break
        out.append((i, size, src, int(codes[i]) if src < 0 else -1))
        for end in range(i + 1, i + size):
            if tau and (end - (grid == "one")) % tau == 0:
                prefixes.insert(end)
        i += size
        prefixes.insert(i)
    return out


def lz_grid_auto(text, ledger: Ledger | None = None, mode: str = "merged") -> tuple[list[Phrase], int, int]:
    """(phrases, guess, tau): the guess of the phrase count doubles, tau = ceil(sqrt(n / guess)), each round stops beyond its guess."""
    n, guess, ledger, ranks = len(symbols_of(text)), 1, ledger or Ledger(), PrefixRanks(symbols_of(text))
    while True:
        tau = math.ceil(math.sqrt(max(1, n) / guess))
        out = lz_end_grid(text, tau, mode=mode, ledger=ledger, limit=guess, ranks=ranks)
        if out is not None:
            return out, guess, tau
        guess *= 2
        ledger.restarts += 1


def decode(phrases: list[Phrase]) -> list[int]:
    """Symbol codes of the factorized text; sources may overlap their phrase."""
    out: list[int] = []
    for _, size, src, sym in phrases:
        if src < 0:
            out.append(sym)
        else:
            for k in range(size):
                out.append(out[src + k])
    return out


def is_lz77_like(phrases: list[Phrase], text) -> bool:
    """Tiles the text, and every phrase with a source repeats what starts there, earlier."""
    s, at = symbols_of(text), 0
    for start, size, src, _ in phrases:
        if start != at or size < 1 or (src < 0 and size != 1):
            return False
        if src >= 0 and not (src < start and s[src : src + size] == s[start : start + size]):
            return False
        at += size
    return at == len(s)


class LeftmostIndex:
    """Leftmost start of any fragment of the factorized text: suffix range and sparse minimum table over it."""

    def __init__(self, phrases: list[Phrase]):
        self.codes = np.array(decode(phrases), np.int64)
        self.order = SuffixOrder(self.codes)
        self.lcp = self.order.lcp()
        self.low = [self.order.sa]
        k = 1
        while 2 * k <= self.order.n:
            a = self.low[-1]
            self.low.append(np.minimum(a[:-k], a[k:]))
            k *= 2
        self.lcp_min = [self.lcp]
        k = 1
        while 2 * k <= self.order.n:
            a = self.lcp_min[-1]
            self.lcp_min.append(np.minimum(a[:-k], a[k:]))
            k *= 2

    def first(self, lo: int, hi: int) -> int:
        r, need = int(self.order.isa[lo]), hi - lo
        left = right = r
        for t in range(len(self.lcp_min) - 1, -1, -1):  # widen while the minimum of the next 2^t lcp values suffices
            w = 1 << t
            if left - w >= 0 and self.lcp_min[t][left - w + 1] >= need:
                left -= w
            if right + w < self.order.n and self.lcp_min[t][right + 1] >= need:
                right += w
        t = (right - left + 1).bit_length() - 1
        return int(min(self.low[t][left], self.low[t][right - (1 << t) + 1]))


def to_lz77(phrases: list[Phrase]) -> list[Phrase]:
    """Exact greedy factorization from any LZ77-like one: each phrase is galloped over leftmost occurrences."""
    index = LeftmostIndex(phrases)
    out, i, n = [], 0, len(index.codes)
    while i < n:
        size = gallop(lambda m, i=i: m == 0 or index.first(i, i + m) < i, 0, n - i)
        out.append((i, size, index.first(i, i + size), -1) if size else (i, 1, -1, int(index.codes[i])))
        i += max(1, size)
    return out


def lz77_metered(text, ledger: Ledger | None = None) -> tuple[list[Phrase], Ledger]:
    """The whole route: grid factorization with unknown size, then conversion."""
    ledger = ledger or Ledger()
    phrases, _, _ = lz_grid_auto(text, ledger)
    ledger.lz_calls += 1
    return to_lz77(phrases), ledger


def lz_no_sorted_prefix(text, ledger: Ledger | None = None) -> list[Phrase]:
    """Greedy without overlap by neighbours among all earlier prefixes in co-lexicographic order (as grid with tau 1)."""
    s, codes, ledger = symbols_of(text), codes_of(text), ledger or Ledger()
    prefixes, out, i = PrefixOrder(s, ledger), [], 0
    while i < len(s):
        size = gallop(lambda m, i=i: m == 0 or prefixes.holder(i, i + m) is not None, 0, len(s) - i)
        ledger.search(max(1, size))
        out.append((i, size, prefixes.holder(i, i + size) - size, -1) if size else (i, 1, -1, int(codes[i])))
        for end in range(i + 1, i + max(1, size) + 1):
            prefixes.insert(end)
        i += max(1, size)
    return out


def lz_no_suffix_array(text, ledger: Ledger | None = None) -> list[Phrase]:
    """The same output over a growing suffix array of the reversed read prefix: linear updates, square-root searches."""
    s, codes, ledger = symbols_of(text), codes_of(text), ledger or Ledger()
    back, out, i, n = s[::-1], [], 0, len(s)
    ends: list[int] = []  # of the read prefix, in the order of back[n - end:]

    def holder(i: int, m: int) -> int | None:
        ledger.comparisons += max(1, len(ends)).bit_length()
        piece = back[n - i - m : n - i]
        at = bisect.bisect_left(ends, piece, key=lambda e: back[n - e : n - e + m])
        return ends[at] if at < len(ends) and back[n - ends[at] : n - ends[at] + m] == piece else None

    while i < n:
        size = gallop(lambda m, i=i: m == 0 or holder(i, m) is not None, 0, n - i)
        ledger.search(max(1, size))
        ledger.grover_time += max(1, size)
        out.append((i, size, holder(i, size) - size, -1) if size else (i, 1, -1, int(codes[i])))
        for end in range(i + 1, i + max(1, size) + 1):
            ledger.comparisons += max(1, len(ends)).bit_length()
            bisect.insort_left(ends, end, key=lambda e: back[n - e :])
        i += max(1, size)
    return out


@functools.lru_cache(maxsize=4)
def binary_strings(n: int) -> tuple[np.ndarray, np.ndarray]:
    """(bits, phrase counts) of all binary strings of length n."""
    bits = (np.arange(1 << n)[:, None] >> np.arange(n - 1, -1, -1)) & 1
    return bits, np.array([lz_size("".join(map(str, row))) for row in bits.tolist()])


def identify_by_halving(hidden: str, z_cap: int | None = None, ledger: Ledger | None = None) -> tuple[str, int]:
    """Recover a short binary string from mismatch searches: candidates are all strings of at most z_cap phrases; each search against the
    majority string removes at least half. Unknown size: the cap doubles until the string is confirmed. Returns (string, searches)."""
    n, ledger = len(hidden), ledger or Ledger()
    if n > 16:
        raise ValueError("exponential in the length")
    cap, rounds, (bits, sizes) = z_cap or 1, 0, binary_strings(n)
    own = np.array([c == "1" for c in hidden], np.int64)
    while True:
        left = bits[sizes <= cap]
        while len(left):
            majority = (2 * left.sum(0) >= len(left)).astype(np.int64)
            rounds += 1
            ledger.search(n)
            wrong = np.flatnonzero(majority != own)
            if not len(wrong):
                return "".join(map(str, majority.tolist())), rounds
            left = left[left[:, wrong[0]] == own[wrong[0]]]
        cap *= 2
        ledger.restarts += 1
