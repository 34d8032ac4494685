"""Edit distance and alignments: table, diagonals with longest common extensions, scripts, products and inverses."""

from __future__ import annotations

import functools

import numpy as np

from textfactor.kernels.cost import Ledger
from textfactor.kernels.suffix import SuffixOrder, codes_of, dense, symbols_of

Path = list[tuple[int, int]]
Edit = tuple[str, int, int, int]  # operation D, I or S; position in x; position in y; new symbol code (-1 for D)


def _columns(a: np.ndarray) -> dict[int, int]:
    """The places of every symbol as the bits of one integer."""
    if len(a) < 512:
        out: dict[int, int] = {}
        for i, c in enumerate(a.tolist()):
            out[c] = out.get(c, 0) | 1 << i
        return out
    return {int(c): int.from_bytes(np.packbits(a == c, bitorder="little").tobytes(), "little") for c in np.unique(a)}


def ed_prefixes(x, y) -> list[int]:
    """Distances of x to every prefix of y, the empty one first: the last row of the quadratic table. A column is kept as two integers of len(x) bits that say
    where it rises and falls by one, so a step handles the whole column."""
    a, b = codes_of(x), codes_of(y)
    if not len(a):
        return list(range(len(b) + 1))
    places, every, top = _columns(a), (1 << len(a)) - 1, 1 << len(a) - 1
    rise, fall, score = every, 0, len(a)
    out = [score]
    for c in b.tolist():
        eq = places.get(c, 0)
        down = eq | fall
        diag = (((eq & rise) + rise) ^ rise) | eq
        up = fall | (every & ~(diag | rise))
        less = rise & diag
        if up & top:
            score += 1
        elif less & top:
            score -= 1
        up, less = up << 1 | 1, less << 1
        rise = (less | ~(down | up)) & every
        fall = up & down & every
        out.append(score)
    return out


def ed_dp(x, y) -> int:
    """The quadratic table, column by column."""
    return ed_prefixes(x, y)[-1] if len(x) <= len(y) else ed_prefixes(y, x)[-1]


def ed_short(x: str, y: str) -> int:
    """ed_dp of two strings, without arrays."""
    if len(x) > len(y):
        x, y = y, x
    if not x:
        return len(y)
    places: dict[str, int] = {}
    for i, c in enumerate(x):
        places[c] = places.get(c, 0) | 1 << i
    every, top, score = (1 << len(x)) - 1, len(x) - 1, len(x)
    rise, fall = every, 0
    for c in y:
        eq = places.get(c, 0)
        diag = (((eq & rise) + rise) ^ rise) | eq | fall
        up, less = fall | (every & ~(diag | rise)), rise & diag
        score += (up >> top & 1) - (less >> top & 1)
        up = up << 1 | 1
        rise, fall = (less << 1 | ~(diag | up)) & every, up & diag & every
    return score


class Fragments:
    """Distances of short fragments and the places where their alignments cross a row, each worked out once: calls on one pair ask for the same fragments in
    every round and under every setting. The waves' furthest points on the way to the goal don't depend on the bound, so an answer holds for all bounds."""

    def __init__(self, longest: int = 256):
        self.longest, self.distances, self.crossings, self.straight = longest, {}, {}, set()

    def takes(self, x, y) -> bool:
        return len(x) <= self.longest and len(y) <= self.longest and isinstance(x, str) and isinstance(y, str)

    def distance(self, x: str, y: str) -> int:
        found = self.distances.get((x, y))
        if found is None:
            if len(x) == len(y) and (places := _substitutions(x, y, len(x))[1]) is not None:
                found = len(places)
                self.straight.add((x, y))
            elif len(x) > 64 and (few := ed_diagonal(x, y, 3)) is not None:
                found = few
            else:
                found = ed_short(x, y)
            self.distances[x, y] = found
        return found

    def crossing(self, x: str, y: str, row: int) -> int:
        """The smallest column in which the alignment of ed_diagonal is in this row."""
        distance, found = self.distance(x, y), self.crossings.get((x, y, row))
        if (x, y) in self.straight:
            return row
        if found is None:
            found = self.crossings[x, y, row] = first_column(ed_diagonal(x, y, distance, script=True)[1], row)
        return found


def first_column(edits: list[Edit], row: int) -> int:
    """The smallest b with (row, b) on the path of a script, without walking its match steps."""
    if row <= 0:
        return 0
    i = j = 0
    for op, x, y, _ in edits:
        if x >= row:
            break
        i, j = x + (op != "I"), y + (op != "D")
        if i >= row:
            return j
    return j + row - i


class Extensions:
    """Common extensions of x from i and y from j through one suffix order of x # y."""

    def __init__(self, x, y, ledger: Ledger | None = None):
        a, b = codes_of(x), codes_of(y)
        both = dense(np.r_[a, b]) + 1
        self.nx, self.ny, self.ledger = len(a), len(b), ledger or Ledger()
        self.order = SuffixOrder(np.r_[both[: len(a)], 0, both[len(a) :]])

    def lce(self, i: int, j: int) -> int:
        self.ledger.lce_calls += 1
        if i >= self.nx or j >= self.ny:
            return 0
        return min(self.order.lce(i, self.nx + 1 + j), self.nx - i, self.ny - j)


class DirectExtensions:
    """The same by comparing slices: needs no index. `work` counts the symbols compared."""

    def __init__(self, x, y, ledger: Ledger | None = None):
        both = symbols_of(np.r_[codes_of(x), codes_of(y)]) if not (isinstance(x, str) and isinstance(y, str)) else x + y
        self.x, self.y = both[: len(x)], both[len(x) :]
        self.ledger, self.work = ledger or Ledger(), 0

    def lce(self, i: int, j: int) -> int:
        self.ledger.lce_calls += 1
        x, y, k, step = self.x, self.y, 0, 16
        most = min(len(x) - i, len(y) - j)
        if most <= 0 or x[i] != y[j]:
            return 0
        while k < most:
            if k + step <= most and x[i + k : i + k + step] == y[j + k : j + k + step]:
                k, step = k + step, step * 2
            elif step == 1 or most - k == 1:
                k += x[i + k] == y[j + k] and k + 1 == most
                break
            else:
                step = max(1, min(step, most - k) // 2)
        self.work += k
        return k


def _substitutions(x, y, k: int) -> tuple[int, list[int] | None]:
    """(bound, places) for texts of equal length: substituting every place that differs bounds the distance by their number. Each edit changes the counts of
    symbols by at most one that y has too many and one that x has; if the counts at those places leave no less, the distance is that number (places, else None)."""
    if len(x) > 48 and isinstance(x, str) and isinstance(y, str):
        a, b = (np.frombuffer(t.encode("utf-32-le"), np.uint32) for t in (x, y))
        at = (a != b).nonzero()[0].tolist()
    else:
        at = [i for i, (p, q) in enumerate(zip(x, y, strict=True)) if p != q]
    if len(at) > k:
        return k, None
    counts: dict = {}
    for i in at:
        counts[x[i]] = counts.get(x[i], 0) + 1
        counts[y[i]] = counts.get(y[i], 0) - 1
    return len(at), at if sum(c for c in counts.values() if c > 0) == len(at) else None


def ed_diagonal(x, y, k: int, lce=None, script: bool = False):
    """Distance if at most k, else None; with script=True (distance, edits). Furthest points per diagonal, one wave per edit; a diagonal from which the goal
    can't be reached with the edits left is not followed."""
    n, m = len(x), len(y)
    if abs(n - m) > k:
        return None
    ext, goal = lce, m - n
    if ext is None:
        if n == m:
            k, places = _substitutions(x, y, k)
            if places is not None:
                return (len(places), [("S", i, i, ord(y[i]) if isinstance(y, str) else int(y[i])) for i in places]) if script else len(places)
        ext = DirectExtensions(x, y)
    # a wave: its lowest diagonal, and the furthest points between two entries of -2 (not reached) on either side
    waves: list[tuple[int, list[int]]] = [(0, [-2, -2, ext.lce(0, 0), -2, -2])]
    while True:
        low, last = waves[-1]
        if low <= goal < low + len(last) - 4 and last[goal - low + 2] >= n:
            break
        e = len(waves)
        if e > k:
            return None
        if lce is None and n + m >= 4000 and isinstance(ext, DirectExtensions) and ext.work > 64 * (n + m):
            ext = Extensions(x, y)  # repetitive texts: an index pays
        get, wave = ext.lce, [-2, -2]
        first, stop = max(-e, goal - k + e, -n), min(e, goal + k - e, m)
        for d in range(first, stop + 1):  # diagonal d: j = i + d
            t = d - low + 2
            i = max(last[t] + 1, last[t - 1], last[t + 1] + 1)
            i = min(i, n, m - d)
            wave.append(-2 if i < 0 or i + d < 0 else i + get(i, i + d))
        waves.append((first, [*wave, -2, -2]))
    if not script:
        return len(waves) - 1
    codes, edits, d, i = codes_of(y), [], goal, n
    for e in range(len(waves) - 1, 0, -1):
        low, points = waves[e - 1]
        last = {v: points[v - low + 2] for v in (d - 1, d, d + 1) if 0 <= v - low + 2 < len(points) and points[v - low + 2] >= 0}
        options = []
        if d in last:
            options.append((min(last[d] + 1, n, m - d), "S", last[d], d))
        if d - 1 in last:
            options.append((min(last[d - 1], n, m - d), "I", last[d - 1], d - 1))
        if d + 1 in last:
            options.append((min(last[d + 1] + 1, n, m - d), "D", last[d + 1], d + 1))
        valid = [o for o in options if (o[1] == "S" and o[2] < n and o[2] + d < m) or (o[1] == "I" and 0 <= o[2] + d - 1 < m) or (o[1] == "D" and o[2] < n)]
        _, op, at, d_old = max(valid, key=lambda o: o[0])
        edits.append((op, at, at + d_old, int(codes[at + d_old]) if op != "D" else -1))
        d = d_old
    return len(waves) - 1, edits[::-1]


@functools.lru_cache(maxsize=1024)
def gram_counts(x: str) -> np.ndarray:
    """How many grams of three symbols fall into each of 1,024 classes."""
    c = codes_of(x)
    return np.bincount((c[:-2] * 961 + c[1:-1] * 31 + c[2:]) & 1023, minlength=1024) if len(c) > 2 else np.zeros(1024, np.int64)


def ed_near(x: str, y: str, k: int) -> int | None:
    """ed_diagonal for texts of which most pairs are far apart: an edit takes away at most three grams and adds three, so the counts of grams differ by no more
    than six for each edit."""
    if abs(len(x) - len(y)) > k or np.abs(gram_counts(x) - gram_counts(y)).sum() > 6 * k:
        return None
    return ed_diagonal(x, y, k) if max(len(x), len(y)) > 256 else d if (d := ed_short(x, y)) <= k else None


def ed_diagonal_auto(x, y, script: bool = False, lce=None):
    """Without a bound: no distance is larger than the longer text, and the waves end at the distance."""
    return ed_diagonal(x, y, max(len(x), len(y)), lce, script)


def apply_edits(x, edits: list[Edit]) -> list[int]:
    """Replay a script on x; returns symbol codes."""
    codes, out, at = codes_of(x).tolist(), [], 0
    for op, i, _, symbol in edits:
        out += codes[at:i]
        at = i + (op != "I")
        if op != "D":
            out.append(symbol)
    return out + codes[at:]


def path_of(n: int, m: int, edits: list[Edit]) -> Path:
    """The lattice path of a script, with its match steps."""
    path, i, j = [(0, 0)], 0, 0
    for op, x, y, _ in [*edits, ("end", n, m, -1)]:
        while i < x and j < y:
            i, j = i + 1, j + 1
            path.append((i, j))
        if op != "end":
            i, j = i + (op != "I"), j + (op != "D")
            path.append((i, j))
    return path


def align_is_valid(path: Path, n: int, m: int) -> bool:
    steps = zip(path, path[1:], strict=False)
    return path[0] == (0, 0) and path[-1] == (n, m) and all((b[0] - a[0], b[1] - a[1]) in ((0, 1), (1, 0), (1, 1)) for a, b in steps)


def align_ops(path: Path, x, y) -> list[str]:
    out = []
    for (a, b), (c, d) in zip(path, path[1:], strict=False):
        out.append("I" if c == a else "D" if d == b else "M" if x[a] == y[b] else "S")
    return out


def align_cost(path: Path, x, y) -> int:
    return sum(op != "M" for op in align_ops(path, x, y))


def align_inverse(path: Path) -> Path:
    return [(b, a) for a, b in path]


def align_product(first: Path, second: Path) -> Path:
    """x to z through y: walk both paths in step over y; its cost is at most the sum of the two."""
    out, i, k, p, q = [(0, 0)], 0, 0, 0, 0
    while p + 1 < len(first) or q + 1 < len(second):
        if p + 1 < len(first) and first[p + 1][1] == first[p][1]:  # a step in x only
            p, i = p + 1, first[p + 1][0]
        elif q + 1 < len(second) and second[q + 1][0] == second[q][0]:  # a step in z only
            q, k = q + 1, second[q + 1][1]
        else:
            p, q = p + 1, q + 1
            i, k = first[p][0], second[q][1]
        if (i, k) != out[-1]:
            out.append((i, k))
    return out


def is_anchor_exact(x, y, a: int, b: int) -> bool:
    """Definition: the distance splits at (a, b)."""
    return ed_dp(x[:a], y[:b]) + ed_dp(x[a:], y[b:]) == ed_dp(x, y)


def disjoint_bound(shift: int, ed1: int, ed2: int) -> int:
    """Phrases of a fragment that two alignments with disjoint matches at the given shift allow."""
    return abs(shift) + 2 * ed1 + 2 * ed2 + 1


def count_ones_as_ed(bits) -> int:
    """ed(X, 0^n) = number of non-zero symbols."""
    return ed_dp(list(bits), [0] * len(bits))
