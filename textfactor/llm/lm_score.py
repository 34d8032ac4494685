"""Language-model scores from a log-frequency Bloom filter.

Unigrams and bigrams of all training texts are counted exactly: each partition counts its own share, shares are merged by shard of
the key's hash. A count c has the level 1 + floor(log2 c), and the filter holds the pairs (n-gram, 1) ... (n-gram, level), in one sub-filter
per shard. A count is read back by probing level after level until one is missing: it lies between 2^(level-1) and 2^level - 1.

Bigrams are interpolated with additive unigrams. A numerator is the least count of its level and the context below it the largest, so what a context
gives to all words adds up to one at most. A false probe can only raise a level; with 10 bits an entry it does so in under 1 % of probes.

Every n-gram is in the filter, whatever its size. While filter and exact unigram counts (for the base score) take up to `max_broadcast_bytes` they lie in one
file that every worker maps, so no process holds them in memory of its own; beyond that texts are packed into written units, a unit's distinct keys are shuffled to the shards that may hold them, and levels and
counts come back by unit. Scores are the same either way.

Cases: null and empty texts are one end token; without training rows every count is 0; repeated rows are scored each; extra columns are ignored.
"""

from __future__ import annotations

import os
import re
import tempfile
import uuid
from collections.abc import Callable
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import Scratch, mix64, word_keys

# fixed values: the keys of the end token and of the place before a text
END, BEGIN = np.uint64(0x1F83D9ABFB41BD6B), np.uint64(0x5BE0CD19137E2179)
LEFT, RIGHT = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
LAMBDA = 0.6
PIECE_KEYS = 1 << 18


def bigram_keys(keys: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Keys of (previous, own) for the joined token keys of many texts; starts: where each text begins."""
    before = np.empty_like(keys)
    before[1:] = keys[:-1]
    before[starts] = BEGIN
    with np.errstate(over="ignore"):
        return mix64(before * LEFT + keys * RIGHT + np.uint64(1))


def batch_keys(texts: list) -> tuple[np.ndarray, np.ndarray]:
    """(token keys of all texts, each with its end token; where each text begins)."""
    keys, at = word_keys(texts)
    return np.insert(keys, at[1:], END), at[:-1] + np.arange(len(texts))


def summed(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    if counts is None:
        return np.unique(keys, return_counts=True)
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.empty(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else counts


def shard_of(keys: np.ndarray, shards: int) -> np.ndarray:
    return (mix64(keys) % np.uint64(shards)).astype(np.int64)


def by_shard(keys: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray]:
    """(the order that sorts keys by shard, their shards in that order)."""
    shard = shard_of(keys, shards)
    order = np.argsort(shard, kind="stable")
    return order, shard[order]


SHARD = "shard long, size long, cells binary, keys binary, counts binary, words long, total long, entries long"


def count_and_build(train: DataFrame, shards: int, bits: int, probes: int, flush: int = 1_000_000) -> DataFrame:
    """One row per shard: its sub-filter (size, cells) over both kinds, its words' exact counts (keys, counts), and what it holds."""

    def emit(batches):
        held, size = ([], []), 0

        def out():
            for kind in (1, 2):
                keys, counts = summed(np.concatenate(held[kind - 1]))
                order, shard = by_shard(keys, shards)
                keys, counts = keys[order], counts[order].astype(np.uint32)
                first = np.flatnonzero(np.r_[True, shard[1:] != shard[:-1]])
                ends = np.r_[first[1:], len(shard)]
                blobs = [pa.array([x[a:b].tobytes() for a, b in zip(first, ends, strict=True)], pa.binary()) for x in (keys, counts)]
                yield pa.RecordBatch.from_arrays([pa.array(shard[first]), pa.array([kind] * len(first), pa.int32()), *blobs], ["shard", "kind", "keys", "counts"])

        for whole in batches:
            for low in range(0, whole.num_rows, 500):
                keys, starts = batch_keys(whole.slice(low, 500).column("text").to_pylist())
                held[0].append(keys)
                held[1].append(bigram_keys(keys, starts))
                size += len(keys)
                if size >= flush:
                    yield from out()
                    held, size = ([], []), 0
        if size:
            yield from out()

    def build(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        kind, merged = table.column("kind").to_numpy(), []
        keys, counts = table.column("keys").to_pylist(), table.column("counts").to_pylist()
        for wanted in (1, 2):
            rows = np.flatnonzero(kind == wanted).tolist()
            merged.append(summed(np.frombuffer(b"".join(keys[k] for k in rows), np.uint64), np.frombuffer(b"".join(counts[k] for k in rows), np.uint32).astype(np.uint64)))
        both, levels = np.concatenate([k for k, _ in merged]), np.concatenate([level_of(c) for _, c in merged])
        entries = int(levels.sum())
        size = max(64, -(-entries * bits // 64) * 64)
        cells = np.zeros(size, bool)
        for level in range(1, int(levels.max(initial=0)) + 1):
            for at in probe_places(both[levels >= level], level, np.uint64(size), probes):
                cells[at] = True
        own, exact = merged[0]
        values = [key[0].as_py(), size, np.packbits(cells, bitorder="little").tobytes(), own.tobytes(), exact.tobytes(), len(own), int(exact.sum()), entries]
        kinds = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.int64()]
        return pa.table([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], [c.split()[0] for c in SHARD.split(", ")])

    blobs = train.select(F.col("text").cast("binary").alias("text")).mapInArrow(emit, "shard long, kind int, keys binary, counts binary")
    return blobs.groupBy("shard").applyInArrow(build, SHARD)


def level_of(counts: np.ndarray) -> np.ndarray:
    return np.frexp(counts.astype(np.float64))[1]


def least_of(level: np.ndarray) -> np.ndarray:
    """The least count of a level: 0, 1, 2, 4, 8, ..."""
    return np.where(level > 0, np.exp2(level - 1.0), 0.0)


def most_of(level: np.ndarray) -> np.ndarray:
    """The largest count of a level: 0, 1, 3, 7, 15, ..."""
    return np.exp2(level.astype(np.float64)) - 1


def probe_places(keys: np.ndarray, level: int, sizes, probes: int):
    with np.errstate(over="ignore"):
        h = mix64(keys + np.uint64(level) * LEFT)
        a, b = h & np.uint64(0xFFFFFFFF), (h >> np.uint64(32)) | np.uint64(1)
        for i in range(probes):
            yield ((a + np.uint64(i) * b) % sizes).astype(np.int64)


class LogFrequencyFilter:
    def __init__(self, rows, shards: int, probes: int):
        self.shards, self.probes = shards, probes
        self.sizes, self.base = np.full(shards, 64, np.uint64), np.zeros(shards, np.int64)
        cells, at = [np.zeros(8, np.uint8)], 64  # shards without a row point to an empty cell block
        for shard, size, raw in rows:
            self.sizes[shard], self.base[shard] = size, at
            cells.append(np.frombuffer(raw, np.uint8))
            at += size
        self.cells = np.concatenate(cells)

    @classmethod
    def over(cls, cells: np.ndarray, sizes: np.ndarray, base: np.ndarray, probes: int) -> LogFrequencyFilter:
        """Over bytes that are there already: shard i has sizes[i] bits from bit base[i] on."""
        own = cls((), len(sizes), probes)
        own.cells, own.sizes, own.base = cells, sizes, base
        return own

    def levels(self, keys: np.ndarray) -> np.ndarray:
        """In pieces: what a probe holds at a time doesn't grow with the number of keys."""
        return np.concatenate([np.empty(0, np.int64), *(self._levels(keys[k : k + PIECE_KEYS]) for k in range(0, len(keys), PIECE_KEYS))])

    def _levels(self, keys: np.ndarray) -> np.ndarray:
        out, left = np.zeros(len(keys), np.int64), np.arange(len(keys))
        shard = shard_of(keys, self.shards)
        size, base = self.sizes[shard], self.base[shard]
        level = 1
        while len(left):
            k, s, b = keys[left], size[left], base[left]
            alive = np.arange(len(left))
            with np.errstate(over="ignore"):
                h = mix64(k + np.uint64(level) * LEFT)
            x, y = h & np.uint64(0xFFFFFFFF), (h >> np.uint64(32)) | np.uint64(1)
            for i in range(self.probes):
                with np.errstate(over="ignore"):
                    at = b[alive] + ((x[alive] + np.uint64(i) * y[alive]) % s[alive]).astype(np.int64)
                alive = alive[(self.cells[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1]
                if not len(alive):
                    break
            left = left[alive]
            out[left] = level
            level += 1
        return out


class ExactCounts:
    """Counts of keys. Shard i has its `held[i]` sorted keys from words[first[i]] on, and their counts right behind them."""

    def __init__(self, words: np.ndarray, first: np.ndarray, held: np.ndarray):
        self.words, self.first, self.held = words, first, held

    def of(self, keys: np.ndarray) -> np.ndarray:
        shard = shard_of(keys, len(self.first))
        end = self.first[shard] + self.held[shard]
        low, high = self.first[shard], end.copy()
        for _ in range(int(self.held.max(initial=0)).bit_length()):  # the first place whose key is not smaller
            mid = (low + high) >> 1
            less = (low < high) & (self.words[np.minimum(mid, len(self.words) - 1)] < keys)
            low, high = np.where(less, mid + 1, low), np.where(less, high, mid)
        at = np.minimum(low, len(self.words) - 1)
        known = (low < end) & (self.words[at] == keys)
        out = np.zeros(len(keys), np.uint64)
        out[known] = self.words[low[known] + self.held[shard[known]]]
        return out


class Held(NamedTuple):
    """What workers look up."""

    levels: LogFrequencyFilter
    exact: ExactCounts

    def words(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return self.levels.levels(keys), self.exact.of(keys)

    def pairs(self, keys: np.ndarray) -> np.ndarray:
        return self.levels.levels(keys)


class Places(NamedTuple):
    """Where the shards lie in 64-bit words: the filter's bits, then the sorted keys, then their counts. Word 0 is empty, for shards without a row."""

    sizes: np.ndarray
    cells: np.ndarray
    first: np.ndarray
    held: np.ndarray

    @classmethod
    def none(cls, shards: int) -> Places:
        return cls(np.full(shards, 64, np.uint64), *(np.zeros(shards, np.int64) for _ in range(3)))

    def put(self, at: int, shard: int, size: int, cells: bytes, keys: bytes, counts: bytes) -> tuple[int, tuple[bytes, ...]]:
        """(the next free word, what to write from word `at` on)."""
        order = np.argsort(own := np.frombuffer(keys, np.uint64), kind="stable")
        self.sizes[shard], self.cells[shard], self.first[shard], self.held[shard] = size, at, at + size // 64, len(own)
        return at + size // 64 + 2 * len(own), (cells, own[order].tobytes(), np.frombuffer(counts, np.uint64)[order].tobytes())

    def over(self, words: np.ndarray, probes: int) -> Held:
        return Held(LogFrequencyFilter.over(words.view(np.uint8), self.sizes, self.cells * 64, probes), ExactCounts(words, self.first, self.held))


_mapped: dict[str, np.ndarray] = {}


def mapped(path: str) -> np.ndarray:
    """The file's 64-bit words, once a process. The pages belong to the file: the workers of a machine share them, and they can be given up at any time."""
    if path not in _mapped:
        _mapped.clear()
        _mapped[path] = np.memmap(path, np.uint64, "r").view(np.ndarray)
    return _mapped[path]


def write_held(scratch: Scratch, table: DataFrame, shards: int) -> tuple[Places, Callable[[], str]]:
    """Filter and exact counts in one file, read from the table file by file; (places, what gives the file's path on a worker). A shared folder that is
    mounted holds the only copy; else every executor gets one."""
    shared = scratch.root.startswith(("/", "file:"))
    folder = re.sub("^file:/*", "/", scratch.root) if shared else tempfile.mkdtemp(prefix="textfactor-lm-")
    os.makedirs(folder, exist_ok=True)
    path, places, at = f"{folder}/held-{uuid.uuid4().hex}", Places.none(shards), 1
    with open(path, "wb") as out:
        out.write(bytes(8))
        for r in table.select("shard", "size", "cells", "keys", "counts").toLocalIterator():
            at, parts = places.put(at, r["shard"], r["size"], r["cells"], r["keys"], r["counts"])
            out.writelines(parts)
    if shared:
        return places, lambda: path
    table.sparkSession.sparkContext.addFile(path)
    name = os.path.basename(path)
    return places, lambda: SparkFiles.get(name)


class Answered:
    """The same from the shards' answers for one unit's sorted distinct keys."""

    def __init__(self, one: np.ndarray, two: np.ndarray, shards: int, answers: pa.Table):
        order = np.argsort(answers.column("shard").to_numpy())

        def read(name: str, kind) -> np.ndarray:
            blobs = answers.column(name).to_pylist()
            return np.frombuffer(b"".join(blobs[k] for k in order), kind)

        self.one, self.two = one, two
        self.word_levels, self.word_counts, self.pair_levels = np.empty(len(one), np.int64), np.empty(len(one), np.uint64), np.empty(len(two), np.int64)
        mine = by_shard(one, shards)[0]
        self.word_levels[mine], self.word_counts[mine] = read("word_levels", np.uint8), read("word_counts", np.uint64)
        self.pair_levels[by_shard(two, shards)[0]] = read("pair_levels", np.uint8)

    def words(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(self.one, keys)
        return self.word_levels[at], self.word_counts[at]

    def pairs(self, keys: np.ndarray) -> np.ndarray:
        return self.pair_levels[np.searchsorted(self.two, keys)]


def pack_units(docs: DataFrame, unit_bytes: int) -> DataFrame:
    """(unit, ids, texts): runs of texts of one partition, cut once they pass unit_bytes."""

    def pack(batches):
        ids, texts, part, held, number = [], [], 0, 0, 0

        def out():
            kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.binary())]
            return pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip((part << 32 | number, ids, texts), kinds, strict=True)], ["unit", "ids", "texts"])

        for batch in batches:
            for i, text, part in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), batch.column("part").to_pylist(), strict=True):
                ids.append(i)
                texts.append(text)
                held += len(text or b"")
                if held >= unit_bytes or len(ids) >= 20_000:
                    yield out()
                    number += 1
                    ids, texts, held = [], [], 0
        if ids:
            yield out()

    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"), F.spark_partition_id().alias("part"))
    return kept.mapInArrow(pack, "unit long, ids array<bigint>, texts array<binary>")


def distinct_keys(texts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(token keys, where texts begin, sorted distinct word keys, sorted distinct bigram keys)."""
    keys, starts = batch_keys(texts)
    return keys, starts, np.unique(keys), np.unique(bigram_keys(keys, starts))


def routed_answers(units: DataFrame, table: DataFrame, shards: int, probes: int, salts: int) -> DataFrame:
    """(unit, shard, word_levels, word_counts, pair_levels) for each unit's distinct keys. A shard is sent to `salts` groups."""

    def ask(batches):
        for batch in batches:
            for unit, texts in zip(batch.column("unit").to_pylist(), batch.column("texts").to_pylist(), strict=True):
                _, _, one, two = distinct_keys(texts)
                (o1, s1), (o2, s2) = by_shard(one, shards), by_shard(two, shards)
                one, two, here = one[o1], two[o2], np.unique(np.concatenate((s1, s2)))
                cut = lambda keys, of: [keys[a:b].tobytes() for a, b in zip(np.searchsorted(of, here, "left"), np.searchsorted(of, here, "right"), strict=True)]
                salt = int(mix64(np.array([unit], np.uint64))[0] % np.uint64(salts))
                same = [pa.array(np.full(len(here), v, np.int64)) for v in (salt, unit)]
                yield pa.RecordBatch.from_arrays([pa.array(here), *same, pa.array(cut(one, s1), pa.binary()), pa.array(cut(two, s2), pa.binary())], ["shard", "salt", "unit", "words", "pairs"])

    def answer(key: tuple[pa.Scalar, ...], asked: pa.Table, held: pa.Table) -> pa.Table:
        words, pairs = ([np.frombuffer(x, np.uint64) for x in asked.column(c).to_pylist()] for c in ("words", "pairs"))
        places, blobs, at = Places.none(1), [bytes(8)], 1
        for row in zip(*(held.column(c).to_pylist() for c in ("size", "cells", "keys", "counts")), strict=True):
            at, parts = places.put(at, 0, *row)
            blobs += parts
        own = places.over(np.frombuffer(b"".join(blobs), np.uint64), probes)
        parts = lambda values, like: pa.array([x.tobytes() for x in np.split(values, np.cumsum([len(x) for x in like])[:-1])] if like else [], pa.binary())
        joined = lambda x: np.concatenate(x) if x else np.empty(0, np.uint64)
        levels, counts = own.words(joined(words))
        return pa.table({"unit": asked.column("unit"), "shard": asked.column("shard"), "word_levels": parts(levels.astype(np.uint8), words), "word_counts": parts(counts, words), "pair_levels": parts(own.pairs(joined(pairs)).astype(np.uint8), pairs)})

    asked = units.select("unit", "texts").mapInArrow(ask, "shard long, salt long, unit long, words binary, pairs binary")
    sent = table.select("shard", "size", "cells", "keys", "counts", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))).alias("salt"))
    return asked.groupBy("shard", "salt").cogroup(sent.groupBy("shard", "salt")).applyInArrow(answer, "unit long, shard long, word_levels binary, word_counts binary, pair_levels binary")


class Scorer(NamedTuple):
    tokens: int
    distinct: int
    texts: int

    def judge(self, ids, keys: np.ndarray, starts: np.ndarray, look) -> pa.RecordBatch:
        floor = np.log10(self.tokens + 1.0 * (self.distinct + 1))
        unique, back = np.unique(keys, return_inverse=True)
        level, count = look.words(unique)
        base = np.add.reduceat((np.log10(count + 1.0) - floor)[back], starts)
        n_known = np.add.reduceat((count > 0).astype(np.int64)[back], starts)
        p1 = ((least_of(level) + 1) / (self.tokens + self.distinct + 1))[back]
        most, before = most_of(level)[back], np.empty(len(keys))
        before[1:] = most[:-1]
        before[starts] = self.texts
        two = np.minimum(least_of(look.pairs(bigram_keys(keys, starts))), before)
        p = np.where(before > 0, LAMBDA * two / np.maximum(before, 1) + (1 - LAMBDA) * p1, p1)
        total = np.add.reduceat(np.log10(p), starts)
        n_tokens = np.diff(np.r_[starts, len(keys)])
        return pa.RecordBatch.from_arrays([ids, pa.array(n_tokens), pa.array(n_known), pa.array(base), pa.array(total)], ["doc_id", "n_tokens", "n_known", "base_score", "score"])


def score(docs: DataFrame, training, bits: int = 10, probes: int = 7, max_broadcast_bytes: int = 4 << 30, shard_bytes: int = 4 << 20, unit_bytes: int = 4 << 20) -> DataFrame:
    """training: boolean column. (doc_id, n_tokens, n_known, train_tokens, base_score, score) of every row of docs."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "lm")
    weight = F.octet_length("text")
    size = docs.agg(F.sum(F.when(training, weight)).alias("b"), F.count_if(training).alias("n"), F.sum(weight).alias("every")).first()
    shards = max(16, (size.b or 0) // shard_bytes)
    table = scratch.write(count_and_build(docs.where(training), shards, bits, probes), "shards")
    sums = table.agg(F.sum("words").alias("words"), F.sum("total").alias("total"), F.sum("entries").alias("entries")).first()
    distinct, tokens, entries = sums.words or 0, sums.total or 0, sums.entries or 0
    scorer, columns = Scorer(tokens, distinct, size.n), "doc_id long, n_tokens long, n_known long, base_score double, score double"
    if entries * bits // 8 + distinct * 16 <= max_broadcast_bytes:
        places, where = write_held(scratch, table, shards)

        def judge(batches):
            look = places.over(mapped(where()), probes)
            for whole in batches:
                for low in range(0, whole.num_rows, 500):
                    batch = whole.slice(low, 500)
                    yield scorer.judge(batch.column("doc_id"), *batch_keys(batch.column("text").to_pylist()), look)

        judged = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text")).mapInArrow(judge, columns)
    else:

        def judge_unit(key: tuple[pa.Scalar, ...], unit: pa.Table, answers: pa.Table) -> pa.Table:
            keys, starts, one, two = distinct_keys(unit.column("texts")[0].as_py())
            return pa.Table.from_batches([scorer.judge(pa.array(unit.column("ids")[0].as_py(), pa.int64()), keys, starts, Answered(one, two, shards, answers))])

        units = scratch.write(pack_units(docs, unit_bytes), "units")
        salts = max(1, -(-(size.every or 0) // (16 * max(1, size.b or 0))))
        judged = units.groupBy("unit").cogroup(routed_answers(units, table, shards, probes, salts).groupBy("unit")).applyInArrow(judge_unit, columns)
    return judged.select("doc_id", "n_tokens", "n_known", F.lit(int(tokens)).cast("long").alias("train_tokens"), "base_score", "score")
