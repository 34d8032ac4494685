"""Input families of the lower bounds, and the threshold problem solved with capped work."""

from __future__ import annotations

import math

from textfactor.kernels.cost import Ledger
from textfactor.kernels.lz import lz77


def single_one(n: int, pos: int | None) -> str:
    return "".join("1" if i == pos else "0" for i in range(n))


def distinct_string(values) -> list[int]:
    """All symbols different: as many phrases and runs as symbols."""
    out = list(dict.fromkeys(values))
    if len(out) != len(list(values)):
        raise ValueError("values repeat")
    return out


def median_from_phrases(phrases) -> int:
    """Decompressing an all-distinct text gives every value, so also the lower median."""
    from textfactor.kernels.lz import decode

    values = sorted(decode(phrases))
    return values[(len(values) - 1) // 2]


def threshold_bounds(ones: int) -> tuple[int, int]:
    """Largest phrase and run counts of a binary string with so many ones."""
    return 3 * ones + 2, 2 * ones + 1


def threshold(bits, t: int, cost_constant: float = 4.0) -> tuple[bool, Ledger]:
    """Whether at most t bits are set. A capped factorization either ends within the phrase bound for t ones, and then the text is known, or the
    answer is no."""
    ledger, text = Ledger(), "".join("1" if b else "0" for b in bits)
    cap = threshold_bounds(t)[0]
    phrases = lz77(text)
    ledger.grover_queries = cost_constant * math.sqrt(max(1, cap) * max(1, len(text)))
    if len(phrases) > cap:
        return False, ledger
    return sum(s == "1" for s in text) <= t, ledger


def size_reduction(bits) -> list[int]:
    """A string of length 4n+2 over {0, 1..n, separator n+1} whose phrase count is 2*ones+4 (5 without ones).

    After a run of zeros and the separator, zeros alternate with marks: a set bit is marked by a symbol of its own, which opens one phrase and leaves
    another for the zeros behind it."""
    n = len(bits)
    tail = [v for k, b in enumerate(bits, 1) for v in (0, k if b else 0)]
    return [0] * (2 * n) + [n + 1] + tail + [0]


def expected_size(ones: int) -> int:
    return 2 * ones + 4 if ones else 5


def lcs_hard(n: int, pos: int | None) -> tuple[str, str]:
    """Longest common substring 1 or 0 by whether a single one is there."""
    return single_one(n, pos), "1"


def qgram_hard(bits) -> int:
    """The frequency of the 1-gram '1' is the number of ones."""
    return sum(bits)


def index_hard(n: int, pos: int | None) -> int:
    """One suffix-array query reveals the one: the last row's suffix starts with the largest symbol."""
    from textfactor.kernels.suffix import SuffixOrder

    order = SuffixOrder(single_one(n, pos))
    return int(order.sa[-1])
