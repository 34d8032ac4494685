"""Edit anchors: compressible windows around a position, finding an anchor, testing one.

`compressed` takes the distances from the phrases of the window's fragments, whose symbols are then not read again; otherwise the fragments are
compared as they are, which costs less in Python."""

from __future__ import annotations

from textfactor.kernels.cost import Ledger
from textfactor.kernels.edit import Fragments, ed_diagonal, ed_prefixes, first_column
from textfactor.kernels.lz import lz77, prefix_phrases
from textfactor.kernels.suffix import symbols_of


def context_window(x, pos: int, k: int, const: int = 6, add: int = 2, ledger: Ledger | None = None) -> tuple[int, int, int, int]:
    """(lo, hi, phrases left, phrases right): the widest window whose halves have at most const*k+add phrases, read away from pos."""
    s, limit = symbols_of(x), const * k + add
    right, left = prefix_phrases(s[pos:], limit), prefix_phrases(s[:pos][::-1], limit)
    lo, hi = pos - (left[-1] if left else 0), pos + (right[-1] if right else 0)
    if ledger:
        ledger.lz_calls += 2
        ledger.grover_queries += (max(1, k) * (hi - lo)) ** 0.5
        ledger.grover_time += (max(1, k) * (hi - lo)) ** 0.5
    return lo, hi, len(left), len(right)


def phrase_bound(s: str) -> int:
    """No greedy factorization has more phrases: a word met before can be one phrase, a new one a phrase for each symbol, and the greedy one is the smallest."""
    words = s.split(" ")
    return min(len(s), len(words) + sum(map(len, set(words))) + len(set(words)))


def window_bounds(x, pos: int, k: int, const: int = 6, add: int = 2, ledger: Ledger | None = None) -> tuple[int, int]:
    """(lo, hi) of context_window; a half that can't have more phrases than the limit is taken whole without being factorized."""
    limit, n = const * k + add, len(x)
    s = symbols_of(x) if n - min(pos, n - pos) > limit else ""

    def reach(half: str) -> int:
        if phrase_bound(half) <= limit:
            return len(half)
        ends = prefix_phrases(half, limit)
        return ends[-1] if ends else 0

    lo = 0 if pos <= limit else pos - reach(s[:pos][::-1])
    hi = n if n - pos <= limit else pos + reach(s[pos:])
    if ledger:
        ledger.lz_calls += 2
        ledger.grover_queries += (max(1, k) * (hi - lo)) ** 0.5
        ledger.grover_time += (max(1, k) * (hi - lo)) ** 0.5
    return lo, hi


def _window_pair(x, y, lo: int, hi: int):
    end = hi + len(y) - len(x)
    return None if end < lo else (x[lo:hi], y[lo:end])


def _distance(x, y, k: int, compressed: bool, ledger: Ledger | None, script: bool = False):
    if not compressed:
        return ed_diagonal(x, y, k, script=script)
    from textfactor.kernels.grammar import ed_compressed

    if ledger:
        ledger.lz_calls += 2
    return ed_compressed(lz77(x), lz77(y), k, script)


def find_anchor(x, y, k: int, pos: int, const: int = 6, add: int = 2, ledger: Ledger | None = None, compressed: bool = False, known: Fragments | None = None) -> int:
    """y with (pos, y) an anchor, provided ed(x, y) <= k; 0 stands for the trivial answer. The smallest such y on the window's alignment."""
    lo, hi = window_bounds(x, pos, k, const, add, ledger)
    pair = _window_pair(x, y, lo, hi)
    if known is not None and pair and not compressed and known.takes(*pair):
        if ledger:
            ledger.grover_time += k * k
        return lo + known.crossing(*pair, pos - lo) if known.distance(*pair) <= k else 0
    found = _distance(*pair, k, compressed, ledger, script=True) if pair else None
    if ledger:
        ledger.grover_time += k * k
    if found is None:
        return 0
    return lo + first_column(found[1], pos - lo)


def test_anchor(x, y, k: int, pos: int, at: int | None, const: int = 6, add: int = 2, ledger: Ledger | None = None, compressed: bool = False, known: Fragments | None = None) -> bool:
    """Whether (pos, at) splits the distance, provided ed(x, y) <= k; without that promise any answer may come."""
    if at is None:
        return False
    lo, hi = window_bounds(x, pos, k, const, add, ledger)
    pair = _window_pair(x, y, lo, hi)
    if not pair or not lo <= at <= lo + len(pair[1]):
        return False
    short = known is not None and not compressed and known.takes(*pair)
    whole = known.distance(*pair) if short else _distance(*pair, k, compressed, ledger)
    if whole is None or whole > k:
        return False
    if short:
        if ledger:
            ledger.grover_time += 3 * k * k
        return known.distance(x[lo:pos], y[lo:at]) + known.distance(x[pos:hi], pair[1][at - lo :]) == whole
    left = _distance(x[lo:pos], y[lo:at], whole, compressed, ledger)
    right = None if left is None else _distance(x[pos:hi], pair[1][at - lo :], whole - left, compressed, ledger)
    if ledger:
        ledger.grover_time += 3 * k * k
    return right is not None and left + right == whole


def test_all_anchors(x, y, k: int, pos: int, const: int = 6, add: int = 2, ledger: Ledger | None = None) -> list[bool]:
    """test_anchor for every place 0..len(y): the window is the same for all of them, so the two sides' distances come from one table each."""
    lo, hi = window_bounds(x, pos, k, const, add, ledger)
    out, pair = [False] * (len(y) + 1), _window_pair(x, y, lo, hi)
    whole = ed_diagonal(*pair, k) if pair else None
    if whole is None:
        return out
    left, right = ed_prefixes(x[lo:pos], pair[1]), ed_prefixes(x[pos:hi][::-1], pair[1][::-1])
    for at in range(len(pair[1]) + 1):
        if lo + at <= len(y):
            out[lo + at] = left[at] + right[len(pair[1]) - at] == whole
    if ledger:
        ledger.grover_time += 3 * k * k
    return out


test_anchor.__test__ = test_all_anchors.__test__ = False
