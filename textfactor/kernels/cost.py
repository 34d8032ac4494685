"""Metered primitives of the query model, simulated exactly.

Results are computed classically and are exact; a Ledger records what the query model would be charged. Charges follow the
formulas of CostModel (square-root search, logarithmic boosting); no random-access quantum memory is assumed, so classical
data structures are charged as time only.
"""

from __future__ import annotations

import functools
import math
from dataclasses import dataclass, field, fields

import numpy as np
import xxhash


@dataclass(frozen=True)
class CostModel:
    """boost_c: every search is repeated c*log2(n) times, so that a union bound over n^c calls holds. fail='seeded'
    makes a search miss with probability (1/3)^repetitions, drawn from a hash of the call number."""

    boost_c: float = 1.0
    fail: str = "none"
    seed: int = 0

    def repetitions(self, n: int) -> int:
        return max(1, math.ceil(self.boost_c * math.log2(max(2, n))))

    def search(self, n: int) -> float:
        return math.sqrt(max(0, n)) * self.repetitions(n)

    def qubits(self, n: int) -> int:
        return max(1, math.ceil(math.log2(max(2, n))))


@functools.lru_cache(maxsize=1 << 16)
def _search_charge(model: CostModel, n: int) -> tuple[float, float]:
    """(queries, time) of one search."""
    cost = model.search(n)
    return cost, cost * model.qubits(n)


@dataclass
class Ledger:
    model: CostModel = field(default_factory=CostModel)
    oracle_reads: int = 0
    grover_calls: int = 0
    grover_queries: float = 0.0
    grover_time: float = 0.0
    lce_calls: int = 0
    lz_calls: int = 0
    comparisons: int = 0
    q_tokens: float = 0.0
    t_tokens: float = 0.0
    restarts: int = 0
    paused: int = 0
    resumed: int = 0
    killed: int = 0
    q_useful: float = 0.0
    q_own: float = 0.0
    q_terminated: float = 0.0
    t_useful: float = 0.0
    t_own: float = 0.0
    t_terminated: float = 0.0

    def search(self, n: int) -> bool:
        """Charge one search over n places; False if the seeded model lets it fail."""
        self.grover_calls += 1
        queries, time = _search_charge(self.model, n)
        self.grover_queries += queries
        self.grover_time += time
        if self.model.fail != "seeded" or n <= 0:
            return True
        draw = xxhash.xxh3_64_intdigest(f"{self.model.seed}:{self.grover_calls}".encode()) / 2**64
        return draw >= (1 / 3) ** self.model.repetitions(n)

    def row(self) -> dict:
        return {f.name: getattr(self, f.name) for f in fields(self) if f.name != "model"}


class SymbolOracle:
    """read(i) is charged; span() gives the simulation what it needs to be exact and isn't."""

    def __init__(self, symbols, ledger: Ledger | None = None):
        self.symbols, self.ledger = symbols, ledger or Ledger()

    def __len__(self) -> int:
        return len(self.symbols)

    def read(self, i: int):
        self.ledger.oracle_reads += 1
        return self.symbols[i]

    def span(self, lo: int, hi: int):
        return self.symbols[lo:hi]


def grover_any(predicate, ledger: Ledger, leftmost: bool = False) -> int | None:
    """A place where the boolean vector holds, or None."""
    hits = np.flatnonzero(np.asarray(predicate))
    if not ledger.search(len(predicate)) or not len(hits):
        return None
    return int(hits[0] if leftmost else hits[len(hits) // 2])


def frag_equal(a: str, b: str, ledger: Ledger) -> bool:
    if len(a) != len(b):
        return False
    found = ledger.search(len(a))
    return a == b or not found  # a missed mismatch reads as equal


def gallop(holds, lo: int, hi: int) -> int:
    """Largest v in [lo, hi] with holds(v); holds(lo) is given and holds is monotone."""
    step, good = 1, lo
    while good + step <= hi and holds(good + step):
        good += step
        step *= 2
    top = min(hi, good + step - 1)
    while good < top:
        mid = (good + top + 1) // 2
        if holds(mid):
            good = mid
        else:
            top = mid - 1
    return good


def lcp_search(a: str, b: str, ledger: Ledger) -> int:
    """Longest common prefix by binary search on fragment equality."""
    return gallop(lambda m: frag_equal(a[:m], b[:m], ledger), 0, min(len(a), len(b)))


def lcs_search(a: str, b: str, ledger: Ledger) -> int:
    return gallop(lambda m: frag_equal(a[len(a) - m :], b[len(b) - m :], ledger), 0, min(len(a), len(b)))


def lex_cmp(a: str, b: str, ledger: Ledger) -> int:
    k = lcp_search(a, b, ledger)
    ledger.comparisons += 1
    return (len(a) > len(b)) - (len(a) < len(b)) if k == min(len(a), len(b)) else (a[k] > b[k]) - (a[k] < b[k])


def colex_cmp(a: str, b: str, ledger: Ledger) -> int:
    return lex_cmp(a[::-1], b[::-1], ledger)


def pattern_search(text: str, pattern: str, ledger: Ledger) -> int:
    """First occurrence (0-based) or -1; charged as one search over the text."""
    ledger.search(len(text))
    return text.find(pattern)


def hamming(a, b) -> int:
    if len(a) != len(b):
        raise ValueError("lengths differ")
    return int(sum(x != y for x, y in zip(a, b, strict=True)))


def min_rotation(s: str) -> int:
    """Start of the least rotation, by two competing candidates."""
    n, i, j, k = len(s), 0, 1, 0
    while i < n and j < n and k < n:
        x, y = s[(i + k) % n], s[(j + k) % n]
        if x == y:
            k += 1
            continue
        if x > y:
            i += k + 1
        else:
            j += k + 1
        j += i == j
        k = 0
    return min(i, j) if n else 0


def lower_bound(kind: str, **p) -> float:
    """Known lower bounds, as numbers without their constants."""
    forms = {
        "lz77": lambda: math.sqrt(p["z"] * p["n"]),
        "lz_size": lambda: math.sqrt(p["z"] * p["n"]),
        "rlbwt": lambda: math.sqrt(p["r"] * p["n"]),
        "sa_index": lambda: math.sqrt(p["r"] * p["n"]),
        "threshold": lambda: math.sqrt((p["t"] + 1) * p["n"]),
        "edit_zero": lambda: math.sqrt(p["k"] * p["n"]),
        "edit_unbounded": lambda: p["n"] ** 1.5,
    }
    return forms[kind]()


def cost_lce_dp(n: int, k: int) -> float:
    """The approach that meters one extension query per diagonal step: k * sqrt(n)."""
    return k * math.sqrt(n)


def cost_weighted_target(n: int, k: int) -> float:
    return k * math.sqrt(k * n)


def cost_halving(n: int, z: int, improved: bool = False) -> float:
    return math.sqrt(z * n) if improved else z * math.sqrt(n) * math.log2(max(2, n))
