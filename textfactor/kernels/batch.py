"""The distance kernels of `edit` for many short pairs at a time: the same tables and waves, with one array element per pair.

Texts beyond `LONGEST` symbols go to the kernels of single pairs; what a chunk holds is bounded whatever the texts' alphabet is.
"""

from __future__ import annotations

import numpy as np

from textfactor.kernels import edit

LONGEST = 255
CELLS = 1 << 22
FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


def _padded(texts: list[str], pad: int) -> tuple[np.ndarray, np.ndarray]:
    """(code points with `pad` behind each text's end, lengths)."""
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    wide = max(1, int(size.max(initial=0)))
    codes = np.array(texts, dtype=f"<U{wide}").view(np.int32).reshape(len(texts), wide)
    return np.where(np.arange(wide) < size[:, None], codes, pad), size


def _by_length(a: list[str], b: list[str], cells, many, one) -> np.ndarray:
    """Distances in chunks of pairs of about the same length; cells(x, y): what a pair of the largest lengths holds."""
    out = np.zeros(len(a), np.int64)
    longest = [max(len(x), len(y)) for x, y in zip(a, b, strict=True)]
    order = sorted(range(len(a)), key=longest.__getitem__)
    while order and longest[order[-1]] > LONGEST:
        k = order.pop()
        out[k] = one(a[k], b[k])
    at = 0
    while at < len(order):
        step = max(1, CELLS // cells(max(1, longest[order[min(len(order), at + 4096) - 1]])))
        mine = order[at : at + min(step, 4096)]
        out[mine] = many([a[k] for k in mine], [b[k] for k in mine])
        at += len(mine)
    return out


def ed_dp(a: list[str], b: list[str]) -> np.ndarray:
    """edit.ed_dp of every pair: a column of the quadratic table is some words of bits that say where it rises and falls."""
    return _by_length(a, b, lambda n: 16 * n, _table, edit.ed_dp)


def _table(a: list[str], b: list[str]) -> np.ndarray:
    (x, nx), (y, ny) = _padded(a, -1), _padded(b, -2)
    symbols, dense = np.unique(y, return_inverse=True)
    dense = dense.reshape(y.shape)
    n, words = len(a), -(-x.shape[1] // 64)
    bits = np.zeros((n, 64 * words), bool)
    held = max(1, CELLS // max(1, n * words * 8))  # symbols whose places are held at a time
    if len(symbols) > held and n > 1:  # a large alphabet: fewer pairs at a time
        half = n // 2
        return np.r_[_table(a[:half], b[:half]), _table(a[half:], b[half:])]
    places = np.empty((len(symbols), words, n), np.uint64)
    for k, c in enumerate(symbols.tolist()):
        bits[:, : x.shape[1]] = x == c
        places[k] = np.packbits(bits, axis=1, bitorder="little").view(np.uint64).T
    rise = [np.full(n, FULL) for _ in range(words)]
    fall = [np.zeros(n, np.uint64) for _ in range(words)]
    score, last, top = nx.copy(), np.maximum(nx - 1, 0) >> 6, (np.maximum(nx - 1, 0) & 63).astype(np.uint64)
    one, high, each = np.uint64(1), np.uint64(63), np.arange(n)
    for j in range(y.shape[1]):
        live, own = j < ny, dense[:, j]
        up_in, less_in = np.ones(n, np.uint64), np.zeros(n, np.uint64)  # the row above the text rises in every column
        for w in range(words):
            eq, p, m = places[own, w, each], rise[w], fall[w]
            down = eq | m
            eq |= less_in
            diag = (((eq & p) + p) ^ p) | eq
            up, less = m | ~(diag | p), p & diag
            mine = live & (last == w)
            score += mine * (((up >> top) & one).astype(np.int64) - ((less >> top) & one).astype(np.int64))
            up_out, less_out = up >> high, less >> high
            up, less = up << one | up_in, less << one | less_in
            rise[w], fall[w] = less | ~(down | up), up & down
            up_in, less_in = up_out, less_out
    return np.where(nx == 0, ny, score)


def ed_diagonal_auto(a: list[str], b: list[str]) -> np.ndarray:
    """edit.ed_diagonal_auto of every pair: furthest points per diagonal, one wave per edit."""
    return _by_length(a, b, lambda n: n * (2 * min(n, 64) + 1), _waves, edit.ed_diagonal_auto)


def _extensions(x: np.ndarray, y: np.ndarray, k: int) -> np.ndarray:
    """[i, k + d, pair]: how long x from i on is equal to y from i + d on, for the diagonals d from -k to k."""
    n, pairs = x.shape
    wide = np.full((max(y.shape[0], n) + 2 * k + 1, pairs), -2, np.int32)
    wide[k : k + y.shape[0]] = y
    out = np.zeros((n + 1, 2 * k + 1, pairs), np.uint8)
    for i in range(n - 1, -1, -1):
        np.multiply(out[i + 1] + np.uint8(1), wide[i : i + 2 * k + 1] == x[i], out=out[i])
    return out


def _waves(a: list[str], b: list[str]) -> np.ndarray:
    (x, nx), (y, ny) = _padded(a, -1), _padded(b, -2)
    out, most = np.full(len(a), -1, np.int64), max(x.shape[1], y.shape[1])
    x, y, nx, ny = np.ascontiguousarray(x.T), np.ascontiguousarray(y.T), nx.astype(np.int16), ny.astype(np.int16)
    mine, k, e = np.arange(len(a)), 0, 0
    points = np.empty((0, 0), np.int16)
    while len(mine):
        if e == k + 1 or not e:  # diagonals and their extensions, for twice as many waves as before
            wider = min(most, max(16, 2 * k)) if e else min(most, 64)
            points = np.pad(points, ((wider - k, wider - k), (0, 0)), constant_values=-2) if e else np.full((2 * wider + 3, len(mine)), -2, np.int16)
            k = wider
            same = _extensions(x, y, k).reshape(-1)
        pairs = len(mine)
        low, high = k - e, k + e + 1  # diagonal d is row k + d of an extension and row k + d + 1 of the points
        if e:
            before, here, after = points[low:high], points[low + 1 : high + 1], points[low + 2 : high + 2]
            i = np.maximum(np.maximum(here, after) + np.int16(1), before)
        else:
            i = np.zeros((1, pairs), np.int16)
        d = np.arange(-e, e + 1, dtype=np.int16)[:, None]
        np.minimum(np.minimum(i, nx), ny - d, out=i)
        off = (i < 0) | (i + d < 0)
        at = np.maximum(i, 0).astype(np.int64) * ((2 * k + 1) * pairs)
        at += np.arange(low * pairs, high * pairs).reshape(2 * e + 1, pairs)
        i += same[at]
        i[off] = -2
        points[low + 1 : high + 1] = i
        goal = ny - nx
        done = (np.abs(goal) <= e) & (points[np.clip(goal + k + 1, 0, 2 * k + 2), np.arange(pairs)] >= nx) & (out[mine] < 0)
        out[mine[done]] = e
        left = out[mine] < 0
        if not left.any():
            break
        if left.sum() * 2 < pairs and pairs > 64:
            mine, nx, ny, x, y = mine[left], nx[left], ny[left], np.ascontiguousarray(x[:, left]), np.ascontiguousarray(y[:, left])
            points = np.ascontiguousarray(points[:, left])
            same = np.ascontiguousarray(same.reshape(-1, pairs)[:, left]).reshape(-1)
        e += 1
    return out
