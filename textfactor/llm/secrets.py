"""Secret scan: three base patterns, and character Markov models for what no pattern names.

Base spans (leftmost, non-overlapping per kind; matches that fail the length rule are dropped after they
were consumed): assign, access, hex. The method adds `random` spans: candidate strings of 20 or more symbols
in which an order-2 Markov model of random strings beats one of ordinary identifiers by a log-likelihood ratio per
symbol. Both models are trained from labelled samples: values of base matches with seeded random strings against words of
sampled texts. The threshold is calibrated on a held-out quarter of both. At most `sample_docs` documents of at most `sample_chars` characters are
sampled, those with the smallest hash of their id; every text is scanned whole.

Offsets are code points. Cases: null text is empty; a table without rows gives no rows; overlapping kinds are all reported; a
candidate that overlaps a base span is left out.
"""

from __future__ import annotations

import hashlib
import math
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import bound_batches, hash_sample

KINDS = ("assign", "access", "hex", "random")
# fixed values: the patterns of the three base kinds, and of what the models look at
ASSIGN = re.compile(rb"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I)
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
HEX = re.compile(rb"[0-9a-f]{16,}")
CANDIDATE = re.compile(rb"[A-Za-z0-9+/_=-]{20,}")
SYMBOLS = b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
CODE = np.full(256, len(SYMBOLS), np.int64)
CODE[list(SYMBOLS)] = np.arange(len(SYMBOLS))
WIDTH = len(SYMBOLS) + 1


def base_spans(text: bytes) -> list[tuple[int, int, int]]:
    """(start, end, kind) in bytes."""
    out = [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 12]
    if b"AKIA" in text:
        out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    out += [(m.start(), m.end(), 2) for m in HEX.finditer(text)]  # runs are maximal, so {16,} finds those of 16 or more
    return sorted(out)


class MarkovModel:
    """Order-2 character model over the candidate alphabet, additive smoothing towards order 1 and uniform."""

    def __init__(self, samples: list[bytes]):
        one, two = np.zeros((WIDTH, WIDTH)), np.zeros((WIDTH, WIDTH, WIDTH))
        for s in samples:
            c = CODE[np.frombuffer(s, np.uint8)]
            if len(c) > 2:
                np.add.at(two, (c[:-2], c[1:-1], c[2:]), 1)
            if len(c) > 1:
                np.add.at(one, (c[:-1], c[1:]), 1)
        base = (one.sum(0) + 1) / (one.sum() + WIDTH)
        p1 = (one + 8 * base) / (one.sum(1, keepdims=True) + 8)
        self.log = np.log((two + 8 * p1[None]) / (two.sum(2, keepdims=True) + 8))

    def per_symbol(self, s: bytes, piece: int = 1 << 16) -> float:
        total = 0.0
        for at in range(0, len(s) - 2, piece):  # candidates can be whole encoded files
            c = CODE[np.frombuffer(s[at : at + piece + 2], np.uint8)]
            total += float(self.log[c[:-2], c[1:-1], c[2:]].sum())
        return total / (len(s) - 2)


def seeded_random_strings(n: int, seed: int = 7) -> list[bytes]:
    rng = random.Random(seed)
    kinds = [SYMBOLS[:62], SYMBOLS[:62] + b"+/", b"0123456789abcdef", SYMBOLS[26:62], SYMBOLS[:62] + b"-_"]
    return [bytes(rng.choices(kinds[i % len(kinds)], k=rng.randint(20, 64))) for i in range(n)]


def calibrated_cut(high: list[float], low: list[float]) -> float:
    """Middle of the cuts with the largest balanced accuracy; 0.5 if a side has no sample."""
    if not high or not low:
        return 0.5
    a, b = np.sort(high), np.sort(low)
    marks = np.unique(np.concatenate((a, b)))
    cuts = (marks[1:] + marks[:-1]) / 2 if len(marks) > 1 else marks
    gain = 1 - np.searchsorted(a, cuts) / len(a) + np.searchsorted(b, cuts) / len(b)
    best = cuts[gain >= gain.max() - 1e-12]
    return float((best[0] + best[-1]) / 2)


def train(docs: DataFrame, sample_docs: int = 2000, sample_chars: int = 200_000) -> tuple[MarkovModel, MarkovModel, float]:
    """(random strings, ordinary identifiers, least ratio per symbol)."""
    some = hash_sample(docs.where(F.length("text") <= sample_chars).select("doc_id", "text"), sample_docs)
    secret, plain = seeded_random_strings(2000), []
    for _, _, text in sorted((r.h, r.doc_id, r.text) for r in some.select("h", "doc_id", "text").toLocalIterator()):
        raw, at = text.encode(), 0
        for start, end, kind in base_spans(raw):
            if start >= at:
                plain += re.findall(rb"[A-Za-z0-9+/_=-]{3,}", raw[at:start])
                at = end
                secret += [v for v in re.findall(CANDIDATE, raw[start:end])] if kind == 0 else [raw[start:end]]
        plain += re.findall(rb"[A-Za-z0-9+/_=-]{3,}", raw[at:])
    held = lambda x: [s for k, s in enumerate(x) if k % 4 == 3]
    noisy, ordinary = (MarkovModel([s for k, s in enumerate(x) if k % 4 != 3]) for x in (secret, plain))
    ratio = lambda x, least: [noisy.per_symbol(s) - ordinary.per_symbol(s) for s in x if len(s) >= least]
    names = [b"_".join(x) for x in zip(*(held(plain)[k::3] for k in range(3)), strict=False)]  # ordinary words joined as identifiers are
    return noisy, ordinary, calibrated_cut(ratio(held(secret), 20), ratio(names, 20))


def scan_text(text: bytes | None, models: tuple[MarkovModel, MarkovModel, float]) -> tuple[list[int], str, str]:
    """(counts per base kind, base digest text, all spans) with offsets in code points."""
    if not text:
        return [0, 0, 0], "", ""
    base = base_spans(text)
    found = list(base)
    noisy, plain, least = models
    taken: list[list[int]] = []  # where base spans lie, merged; candidates come in order too
    for s, e, _ in base:
        if taken and s <= taken[-1][1]:
            taken[-1][1] = max(taken[-1][1], e)
        else:
            taken.append([s, e])
    k = 0
    for m in CANDIDATE.finditer(text):
        while k < len(taken) and taken[k][1] <= m.start():
            k += 1
        if k < len(taken) and taken[k][0] < m.end():
            continue
        if noisy.per_symbol(m.group()) - plain.per_symbol(m.group()) > least:
            found.append((m.start(), m.end(), 3))
    if not found:
        return [0, 0, 0], "", ""
    at = {x: 0 for s, e, _ in found for x in (s, e)}
    last = chars = 0
    for x in sorted(at):
        chars += len(text[last:x].decode())
        last, at[x] = x, chars
    shown = [(at[s], k, at[e]) for s, e, k in found]
    shown.sort()
    write = lambda rows: ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in rows)
    return [sum(k == kind for _, _, k in base) for kind in range(3)], write(x for x in shown if x[1] < 3), write(shown)


def scan(docs: DataFrame, models: tuple[MarkovModel, MarkovModel, float]) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, n_random, base_spans, spans) of every document; a map without shuffle."""
    bound_batches(docs.sparkSession)
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    sent = docs.sparkSession.sparkContext.broadcast(models)  # two arrays of the alphabet's size cubed

    def look(batches):
        for batch in batches:
            found = [scan_text(x, sent.value) for x in batch.column("text").to_pylist()]
            counts = [pa.array([f[0][k] for f in found], pa.int64()) for k in range(3)]
            extra = pa.array([f[2].count("random:") for f in found], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *counts, extra, pa.array([f[1] for f in found], pa.string()), pa.array([f[2] for f in found], pa.string())], ["doc_id", "n_assign", "n_access", "n_hex", "n_random", "base_spans", "spans"])

    return kept.mapInArrow(look, "doc_id long, n_assign long, n_access long, n_hex long, n_random long, base_spans string, spans string")


def sha256_text(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()
