"""Balanced straight-line programs from factorizations, with fingerprints: expansion, extraction, extension queries."""

from __future__ import annotations

from textfactor.kernels.lz import Phrase

# fixed values: modulus and base of the rolling fingerprint
MODULUS, BASE = (1 << 61) - 1, 911_382_323


class Grammar:
    """Height-balanced rules: a phrase is cut out of what is built so far and joined on, so z phrases need O(z log n) rules."""

    def __init__(self):
        self.left, self.right, self.size, self.height, self.sym, self.print = [], [], [], [], [], []
        self._leaf: dict[int, int] = {}
        self._pair: dict[tuple[int, int], int] = {}
        self._power = [1]
        self.root: int | None = None

    def power(self, n: int) -> int:
        """BASE ** n by table of what was used; sizes of rules repeat."""
        return pow(BASE, n, MODULUS)

    def _add(self, left, right, size, height, sym, value) -> int:
        for column, v in zip((self.left, self.right, self.size, self.height, self.sym, self.print), (left, right, size, height, sym, value), strict=True):
            column.append(v)
        return len(self.size) - 1

    def leaf(self, sym: int) -> int:
        if sym not in self._leaf:
            self._leaf[sym] = self._add(-1, -1, 1, 1, sym, (sym + 1) % MODULUS)
        return self._leaf[sym]

    def pair(self, a: int, b: int) -> int:
        if (a, b) not in self._pair:
            value = (self.print[a] * self.power(self.size[b]) + self.print[b]) % MODULUS
            self._pair[a, b] = self._add(a, b, self.size[a] + self.size[b], max(self.height[a], self.height[b]) + 1, -1, value)
        return self._pair[a, b]

    def _balanced(self, a: int, b: int) -> int:
        if self.height[a] > self.height[b] + 1:
            if self.height[self.left[a]] >= self.height[self.right[a]]:
                return self.pair(self.left[a], self.pair(self.right[a], b))
            m = self.right[a]
            return self.pair(self.pair(self.left[a], self.left[m]), self.pair(self.right[m], b))
        if self.height[b] > self.height[a] + 1:
            if self.height[self.right[b]] >= self.height[self.left[b]]:
                return self.pair(self.pair(a, self.left[b]), self.right[b])
            m = self.left[b]
            return self.pair(self.pair(a, self.left[m]), self.pair(self.right[m], self.right[b]))
        return self.pair(a, b)

    def join(self, a: int | None, b: int | None) -> int | None:
        if a is None or b is None:
            return b if a is None else a
        if self.height[a] > self.height[b] + 1:
            return self._balanced(self.left[a], self.join(self.right[a], b))
        if self.height[b] > self.height[a] + 1:
            return self._balanced(self.join(a, self.left[b]), self.right[b])
        return self.pair(a, b)

    def cut(self, node: int | None, lo: int, hi: int) -> int | None:
        """Rule for symbols lo..hi of the node's expansion."""
        if node is None or lo >= hi:
            return None
        if lo == 0 and hi == self.size[node]:
            return node
        middle = self.size[self.left[node]]
        a = self.cut(self.left[node], lo, min(hi, middle)) if lo < middle else None
        b = self.cut(self.right[node], max(0, lo - middle), hi - middle) if hi > middle else None
        return self.join(a, b)

    def expand(self, node: int | None = None) -> list[int]:
        node, out, stack = self.root if node is None else node, [], []
        stack = [] if node is None else [node]
        while stack:
            v = stack.pop()
            if self.left[v] < 0:
                out.append(self.sym[v])
            else:
                stack += [self.right[v], self.left[v]]
        return out

    def extract(self, lo: int, size: int) -> list[int]:
        part = self.cut(self.root, lo, min(lo + size, self.size[self.root])) if self.root is not None else None
        return [] if part is None else self.expand(part)

    def fingerprint(self, lo: int, hi: int, node: int | None = None) -> int:
        node = self.root if node is None else node
        if node is None or lo >= hi:
            return 0
        if lo == 0 and hi == self.size[node]:
            return self.print[node]
        middle = self.size[self.left[node]]
        if hi <= middle:
            return self.fingerprint(lo, hi, self.left[node])
        if lo >= middle:
            return self.fingerprint(lo - middle, hi - middle, self.right[node])
        a, b = self.fingerprint(lo, middle, self.left[node]), self.fingerprint(0, hi - middle, self.right[node])
        return (a * self.power(hi - middle) + b) % MODULUS


def grammar_from_lz(phrases: list[Phrase]) -> Grammar:
    g = Grammar()
    for _, size, src, sym in phrases:
        if src < 0:
            g.root = g.join(g.root, g.leaf(sym))
            continue
        left = size
        while left:  # an overlapping source is copied as far as it is written, again and again
            have = g.size[g.root] - src
            take = min(left, have)
            g.root = g.join(g.root, g.cut(g.root, src, src + take))
            src, left = src + take, left - take
    return g


def rules_of(g: Grammar) -> list[tuple[int, int, int, int, int, int]]:
    """(rule, left, right, length, height, symbol), used rules only."""
    used, stack = set(), [] if g.root is None else [g.root]
    while stack:
        v = stack.pop()
        if v not in used:
            used.add(v)
            stack += [c for c in (g.left[v], g.right[v]) if c >= 0]
    return [(v, g.left[v], g.right[v], g.size[v], g.height[v], g.sym[v]) for v in sorted(used)]


def run_length_rules(g: Grammar) -> list[tuple[int, int, int, int, int]]:
    """(rule, left, right, times, symbol): rules that repeat one base are a single rule base^times (right -1); only used rules."""
    form: dict[int, tuple[int, int]] = {}
    for v in range(len(g.size)):  # parts come before what they make
        l, r = g.left[v], g.right[v]
        same = l >= 0 and form[l][0] == form[r][0]
        form[v] = (form[l][0], form[l][1] + form[r][1]) if same else (v, 1)
    rules, stack = {}, [] if g.root is None else [g.root]
    while stack:
        v = stack.pop()
        if v in rules:
            continue
        base, times = form[v]
        if times > 1:
            rules[v] = (v, base, -1, times, -1)
            stack.append(base)
        else:
            rules[v] = (v, g.left[v], g.right[v], 1, g.sym[v])
            stack += [c for c in (g.left[v], g.right[v]) if c >= 0]
    return [rules[v] for v in sorted(rules)]


def expand_run_length(rules: list[tuple[int, int, int, int, int]]) -> list[int]:
    done: dict[int, list[int]] = {}
    for v, left, right, times, sym in rules:
        done[v] = done[left] * times if right < 0 <= left else [sym] if left < 0 else done[left] + done[right]
    return done[rules[-1][0]] if rules else []


class PhraseLce:
    """Longest common extensions on factorized texts, without expanding them: binary search over fingerprints."""

    def __init__(self, x: list[Phrase], y: list[Phrase]):
        self.gx, self.gy = grammar_from_lz(x), grammar_from_lz(y)
        self.nx = self.gx.size[self.gx.root] if x else 0
        self.ny = self.gy.size[self.gy.root] if y else 0
        self.calls = 0

    def lce(self, i: int, j: int) -> int:
        self.calls += 1
        lo, hi = 0, min(self.nx - i, self.ny - j)
        while lo < hi:
            mid = (lo + hi + 1) // 2
            if self.gx.fingerprint(i, i + mid) == self.gy.fingerprint(j, j + mid):
                lo = mid
            else:
                hi = mid - 1
        return lo


def ed_compressed(x: list[Phrase], y: list[Phrase], k: int, script: bool = False):
    """Distance of two factorized texts if at most k: the diagonal method over PhraseLce; the texts are not read."""
    from textfactor.kernels import edit

    ext = PhraseLce(x, y)
    if script:
        out = edit.ed_diagonal(_Sized(ext.nx), _Sized(ext.ny, ext.gy), k, ext, script=False)
        return None if out is None else edit.ed_diagonal([0] * ext.nx, ext.gy.expand() if y else [], k, ext, script=True)
    return edit.ed_diagonal(_Sized(ext.nx), _Sized(ext.ny), k, ext)


class _Sized:
    def __init__(self, n: int, grammar: Grammar | None = None):
        self.n = n

    def __len__(self) -> int:
        return self.n


def attractor_from_lz(phrases: list[Phrase]) -> list[int]:
    """Last positions of the phrases: every substring has an occurrence that holds one of them."""
    return [start + size - 1 for start, size, _, _ in phrases]
