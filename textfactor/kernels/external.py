"""Greedy phrase counts of one text that lies in a file: suffixes are told apart range by range of their first bytes, so memory follows the range, not the text.

Positions that share a gram form a group; the group's gram grows until its members differ. A position's longest previous factor ends where it stops sharing a
group with a smaller position. A group whose members all have the same symbol in front needs no further work: the longest match of each member is that of the position
in front of it, less one, so a running maximum of the ends finds it. Works on UTF-8 bytes; ends are taken back to the last whole symbol, which gives the phrases of symbols."""

from __future__ import annotations

import mmap
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

# fixed values: positions of a block, widest window compared at once (also the zeros behind the text), bytes of a word, bytes told apart in the first and in later rounds
BLOCK, PAD, WORD, FIRST, NEXT = 1 << 16, 4096, 8, 5, 4
#: Depth from which groups are compared by windows, as copies are long.
DEEP = FIRST + 11 * NEXT
_SYMBOL = np.ones(256, np.int64)
_SYMBOL[0x80:0xC0], _SYMBOL[0xC0:0xE0], _SYMBOL[0xE0:0xF0], _SYMBOL[0xF0:0xF8] = 0, 2, 3, 4
_NO_ZERO = bytes([0xFF, *range(1, 256)])


class TextFile:
    """Pieces joined by a separator in an unnamed temporary file. Zero bytes, which end the text, become 0xFF, which UTF-8 does not have."""

    def __init__(self, separator: bytes):
        self.file, self.separator, self.n, self.pieces = tempfile.TemporaryFile(), separator, 0, 0  # noqa: SIM115

    def add(self, piece: bytes) -> None:
        if self.pieces:
            self.n += self.file.write(self.separator)
        self.n += self.file.write(piece.translate(_NO_ZERO) if b"\0" in piece else piece)
        self.pieces += 1

    def close(self) -> None:
        self.file.close()

    def view(self) -> _View:
        self.file.write(bytes(PAD + WORD))
        self.file.flush()
        return _View(mmap.mmap(self.file.fileno(), 0, access=mmap.ACCESS_READ), self.n)


class _View:
    def __init__(self, text: mmap.mmap, n: int):
        self.text, self.n = text, n
        self.bytes = np.frombuffer(text, np.uint8)
        self.four = np.ndarray((n,), ">u4", text, strides=(1,))
        self.eight = np.ndarray((n + PAD,), ">u8", text, strides=(1,))

    def before(self, pos: np.ndarray) -> np.ndarray:
        """Bytes in front of positions; 256 at the start."""
        out = self.bytes[np.maximum(pos, 1) - 1].astype(np.int16)
        out[pos == 0] = 256
        return out

    def same(self, a: np.ndarray, b: np.ndarray, width: int) -> np.ndarray:
        if width == WORD:
            return self.eight[a] == self.eight[b]
        windows = np.lib.stride_tricks.as_strided(self.bytes, (self.n + PAD - width + 1, width), (1, 1))
        rows = max(1, (8 << 20) // width)
        return np.concatenate([(windows[a[k : k + rows]] == windows[b[k : k + rows]]).all(axis=1) for k in range(0, len(a), rows)])


def ranges(view: _View, most: int) -> list[tuple[int, int]]:
    """Ranges of the first four bytes with about `most` positions each; the same for every caller."""
    count = -(-view.n // most)
    seen = np.sort(view.four[:: max(1, view.n // (256 * count))].astype(np.int64))
    cuts = np.unique(seen[np.arange(1, count) * len(seen) // count]) if count > 1 else np.empty(0, np.int64)
    return list(zip([0, *cuts.tolist()], [*cuts.tolist(), 1 << 32], strict=True))


def longest_previous(view: _View, lo: int, hi: int, slice_size: int = 1 << 17) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(positions, lengths of the longest previous factors in bytes) for the positions whose first four bytes lie in lo..hi-1, without those that follow from
    the position in front."""
    step = 1 << 20
    found = []
    for a in range(0, view.n, step):
        k = view.four[a : a + step].astype(np.uint32)
        k -= np.uint32(lo)  # what is below lo becomes large
        found.append(np.flatnonzero(k <= np.uint32(hi - 1 - lo)) + a)
    pos = np.concatenate(found)
    if not len(pos):
        return
    left = view.before(pos)
    key, order = _sorted(view.eight[pos].astype(np.uint64) >> np.uint64(8 * (WORD - FIRST)), 8 * FIRST)
    pos, left = pos[order], left[order]
    starts, sizes = _groups(key)
    least, key = np.minimum.reduceat(pos, starts), key[starts]
    gain = np.zeros(len(least), np.int64)
    for m in range(1, FIRST):
        heads, members = _groups(key >> np.uint64(8 * (FIRST - m)))
        low = np.minimum.reduceat(least, heads)
        if m < 4:  # the range may cut these groups
            for edge in (0, -1):
                at = int(least[heads[edge]])
                low[edge] = view.text.find(view.text[at : at + m])
        gain += least > np.repeat(low, members)
    yield least, gain
    keep, group = _going(left, starts, sizes)
    pos, left = pos[keep], left[keep]
    del key, order, keep, least, gain
    deep = []
    for a, b in _slices(group, slice_size):
        p, c, g, depth = pos[a:b], left[a:b], group[a:b], FIRST
        while len(p) and depth < DEEP:
            (p, c, g, _), out = _split(view, p, c, g, depth)
            yield out
            depth += NEXT
        if len(p):
            deep.append((p, c, g))
    if deep:
        yield from _deep(view, *_joined(deep), slice_size)


def _sorted(key: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys of so many bits, and their order; where it fits, the number of a row is put behind its key, as numbers alone sort faster."""
    more = np.uint64(len(key).bit_length())
    if bits + int(more) > 64:
        order = np.argsort(key)
        return key[order], order
    packed = key << more | np.arange(len(key), dtype=np.uint64)
    packed.sort()
    return packed >> more, (packed & ((np.uint64(1) << more) - np.uint64(1))).astype(np.int64)


def _groups(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    return starts, np.diff(np.r_[starts, len(key)])


def _going(left: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the groups of several members with different symbols in front, and their groups."""
    going = (sizes > 1) & (np.minimum.reduceat(left, starts) != np.maximum.reduceat(left, starts))
    return np.flatnonzero(np.repeat(going, sizes)), np.repeat(np.arange(np.count_nonzero(going)), sizes[going])


def _slices(group: np.ndarray, size: int) -> Iterator[tuple[int, int]]:
    """Spans of about `size` rows that cut no group."""
    a = 0
    while a < len(group):
        b = min(len(group), a + size)
        b = int(np.searchsorted(group, group[b - 1], "right"))
        yield a, b
        a = b


def _joined(parts: list[tuple]) -> tuple:
    """Parts one behind the other, with groups numbered anew."""
    offset, out = 0, []
    for pos, left, group, *rest in parts:
        out.append((pos, left, group + offset, *rest))
        offset += int(group[-1]) + 1
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _split(view: _View, pos: np.ndarray, left: np.ndarray, group: np.ndarray, depth: np.ndarray | int) -> tuple[tuple, tuple]:
    """Groups split by their next bytes: ((pos, left, group, row) of what goes on, newly found positions and lengths). The least position of a group is known before and
    stays in it for the others."""
    starts, sizes = _groups(group)
    number = np.repeat(np.arange(len(starts), dtype=np.uint64), sizes)
    key, order = _sorted(number << np.uint64(8 * NEXT) | view.eight[pos + depth].astype(np.uint64) >> np.uint64(8 * (WORD - NEXT)), len(starts).bit_length() + 8 * NEXT)
    pos, left = pos[order], left[order]
    starts, sizes = _groups(key)
    least, key = np.minimum.reduceat(pos, starts), key[starts]
    gain = np.zeros(len(least), np.int64)
    for m in range(NEXT):
        heads, members = _groups(key >> np.uint64(8 * (NEXT - m)))
        later = least > np.repeat(np.minimum.reduceat(least, heads), members)
        if m:
            gain += later
        else:
            new = np.flatnonzero(later)
    keep, group = _going(left, starts, sizes)
    before = depth[order[starts[new]]] if isinstance(depth, np.ndarray) else depth
    return (pos[keep], left[keep], group, order[keep]), (least[new], before + gain[new])


def _deep(view: _View, pos: np.ndarray, left: np.ndarray, group: np.ndarray, slice_size: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Long common parts in windows: twice as wide after each that a whole group shares, half as wide after each other one. Whenever a group's depth has doubled,
    it is looked at for runs."""
    depth, width, check = np.full(len(pos), DEEP), np.full(len(pos), 2 * WORD), np.full(len(pos), DEEP)
    while len(pos):
        parts, rest = [], np.ones(len(pos), bool)
        due = np.flatnonzero(depth >= check)
        if len(due):
            due = due[np.lexsort((pos[due], group[due]))]
            check[due] = 2 * depth[due]
            starts, sizes = _groups(group[due])
            period = _least_gap(pos[due], starts)
            due = due[np.repeat(period <= depth[due[starts]] // 2, sizes)]
            if len(due):
                rest[due] = False
                (p, c, g, h), out = _runs(view, pos[due], left[due], group[due], depth[due])
                yield out
                if len(p):
                    parts.append((p, c, g, h, np.full(len(p), 2 * WORD), 2 * h))
        for w in np.unique(width[rest]).tolist():
            at = np.flatnonzero(rest & (width == w))
            starts, sizes = _groups(group[at])
            here = pos[at] + depth[at]
            same = view.same(here, np.repeat(here[starts], sizes), w)
            whole = np.repeat(np.logical_and.reduceat(same, starts), sizes)
            depth[at[whole]] += w
            width[at[whole]] = min(2 * w, PAD)
            at = at[~whole]
            if w > WORD:
                width[at] = w // 2
                continue
            rest[at] = False
            for a, b in _slices(group[at], slice_size):
                k = at[a:b]
                (p, c, g, row), out = _split(view, pos[k], left[k], group[k], depth[k])
                yield out
                if len(p):
                    parts.append((p, c, g, depth[k][row] + NEXT, np.full(len(p), WORD), check[k][row]))
        if not rest.all():
            if rest.any():
                parts.append(tuple(c[rest] for c in (pos, left, group, depth, width, check)))
            if not parts:
                return
            pos, left, group, depth, width, check = _joined(parts)


def _least_gap(pos: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Least distance of neighbours in groups of at least two ascending positions."""
    gap = np.diff(pos, prepend=0)
    gap[starts] = np.iinfo(np.int64).max
    return np.minimum.reduceat(gap, starts)


def _runs(view: _View, pos: np.ndarray, left: np.ndarray, group: np.ndarray, depth: np.ndarray) -> tuple[tuple, tuple]:
    """As _split, for groups (in the order of their positions) two members of which are at most half the depth apart. That distance is a period of the gram. Members whose
    periods end at different distances share all up to the nearer end, so the ends split the group at once, however long the runs are."""
    starts, sizes = _groups(group)
    period = np.repeat(_least_gap(pos, starts), sizes)
    gap = np.diff(pos, prepend=0)
    gap[starts] = np.iinfo(np.int64).max
    heads = np.flatnonzero(gap > depth - period)
    members = np.diff(np.r_[heads, len(pos)])
    last = heads + members - 1
    ends = pos[last] + depth[last]
    run = np.repeat(ends + _extension(view, ends, ends - period[last]), members) - pos
    number = np.repeat(np.arange(len(starts)), sizes) * (view.n + 1)
    before = np.r_[0, np.maximum.accumulate(run + number)[:-1]] - number
    before[starts] = 0
    known = np.zeros(len(pos), bool)
    known[starts] = True
    order = np.lexsort((pos, run, number))
    pos, left, run, before, number, known = (c[order] for c in (pos, left, run, before, number, known))
    starts, sizes = _groups(number + run)
    new = starts[~known[starts]]
    keep, group = _going(left, starts, sizes)
    return (pos[keep], left[keep], group, run[keep]), (pos[new], np.minimum(run, before)[new])


def _extension(view: _View, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Common bytes behind positions a and b < a."""
    out, going, w = np.zeros(len(a), np.int64), np.arange(len(a)), PAD
    while len(going):
        going = going[view.same(a[going] + out[going], b[going] + out[going], w)]
        out[going] += w
    while w > 1:
        w //= 2
        hit = view.same(a + out, b + out, w)
        out[hit] += w
    return out


def steps(view: _View, lo: int, hi: int) -> Iterator[tuple[int, int, bytes, bytes]]:
    """(block, number of steps, packed offsets and steps, wide steps) of a range: how far the longest previous factor reaches in whole symbols, one symbol at least; a
    step of 255 stands for the next of the wide ones."""
    parts = list(longest_previous(view, lo, hi))
    if not parts:
        return
    pos, size = (np.concatenate(c) for c in zip(*parts, strict=True))
    del parts
    wide = np.flatnonzero(size >= 255)
    wide = size[wide[np.argsort(pos[wide])]]
    packed = pos << 8 | np.minimum(size, 255)
    packed.sort()
    pos, size = packed >> 8, packed & 255
    del packed
    size[size == 255] = wide
    ends = pos + size
    while (inside := (view.bytes[ends] & 0xC0) == 0x80).any():
        ends -= inside
    size = np.maximum(ends - pos, _SYMBOL[view.bytes[pos]])
    pos, size = pos[size > 0], size[size > 0]
    if not len(pos):
        return
    block = pos // BLOCK
    starts, sizes = _groups(block)
    gap = np.diff(pos, prepend=0)
    gap[starts] = pos[starts] % BLOCK
    planes = np.stack([gap & 255, gap >> 8, np.minimum(size, 255)]).astype(np.uint8)
    for a, n in zip(starts.tolist(), sizes.tolist(), strict=True):
        few = size[a : a + n]
        yield int(block[a]), n, pa.compress(planes[:, a : a + n].tobytes(), "zstd", asbytes=True), few[few >= 255].astype("<u8").tobytes()


class Chain:
    """Counts phrases from blocks of steps in the text's order; holds one block."""

    def __init__(self, n: int):
        self.n, self.at, self.reach, self.phrases = n, 0, 0, 0
        self.block, self.parts = -1, []

    def add(self, block: int, n: int, packed: bytes, wide: bytes) -> None:
        if block != self.block:
            self._walk()
            self.block, self.parts = block, []
        self.parts.append((n, packed, wide))

    def _skip(self, until: int) -> None:
        while self.at < until:  # no position up to there reaches further than the ones before
            if self.reach <= self.at:
                raise ValueError(f"no step at {self.at}")
            self.at, self.phrases = self.reach, self.phrases + 1

    def _walk(self) -> None:
        if self.block < 0:
            return
        base = self.block * BLOCK
        self._skip(base)
        step = np.zeros(min(BLOCK, self.n - base), np.int64)
        for n, packed, wide in self.parts:
            low, high, size = np.frombuffer(pa.decompress(packed, 3 * n, "zstd"), np.uint8).reshape(3, n).astype(np.int64)
            size[size == 255] = np.frombuffer(wide, "<u8")
            step[np.cumsum(low + 256 * high)] = size
        reach = step + np.arange(base, base + len(step))
        reach[0] = max(reach[0], self.reach)
        reach = np.maximum.accumulate(reach)
        self.reach = int(reach[-1])
        ends, k, count = (reach - base).tolist(), self.at - base, 0
        while k < len(ends):
            if ends[k] <= k:
                raise ValueError(f"no step at {base + k}")
            k, count = ends[k], count + 1
        self.at, self.phrases = base + k, self.phrases + count

    def close(self) -> int:
        self._walk()
        self._skip(self.n)
        return self.phrases


def phrase_count(view: _View, most: int = 1 << 22) -> int:
    """Number of greedy phrases of a text whose steps fit in memory."""
    chain = Chain(view.n)
    for row in sorted(r for lo, hi in ranges(view, most) for r in steps(view, lo, hi)):
        chain.add(*row)
    return chain.close()
