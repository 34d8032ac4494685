"""Shared helpers of the training-data operators: tables, scratch space, word keys.

Every intermediate that must outlive a job is a Parquet table below the shared folder that the
session names in ``spark.checkpoint.dir``; nothing is kept on an executor's own disk.
"""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid
from itertools import chain

import numpy as np
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_own_dirs: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share. Where the session names none, a private temporary one in local mode, and an error on a cluster."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.partition("[")[0] == "local":
        raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own_dirs:
        _own_dirs[app] = tempfile.mkdtemp(prefix="textfactor-")
    return f"file://{_own_dirs[app]}"


def _remove(spark: SparkSession, path: str) -> None:
    try:
        hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
    except Exception:  # the session may be gone by then; scratch folders are harmless
        pass


ARROW_BYTES = 8 << 20
ROW_GROUP_BYTES = 32 << 20


def bound_batches(spark: SparkSession) -> None:
    """Keeps Arrow batches to a few MB whatever a row weighs; a runtime setting, only ever lowered."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(key, None)
    size = int(now.rstrip("b")) if now and now.rstrip("b").isdigit() else None
    if size is None or size > ARROW_BYTES:
        spark.conf.set(key, f"{ARROW_BYTES}b")


class Scratch:
    """Written intermediates of one operator call, removed when the interpreter ends, on close(), or by close_since()."""

    made: list[Scratch] = []

    def __init__(self, spark: SparkSession, operator: str):
        bound_batches(spark)
        self.spark = spark
        self.root = f"{shared_dir(spark)}/textfactor-{operator}-{uuid.uuid4().hex[:12]}"
        atexit.register(_remove, spark, self.root)
        Scratch.made.append(self)

    @classmethod
    def close_since(cls, mark: int) -> None:
        """Removes the intermediates of all operator calls after the first `mark`; for callers that have written the results."""
        for scratch in cls.made[mark:]:
            scratch.close()
        del cls.made[mark:]

    def write(self, df: DataFrame, name: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
        path = f"{self.root}/{name}"
        writer = df.write.option("compression", "zstd").option("parquet.block.size", ROW_GROUP_BYTES)  # what a task holds while it writes
        (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, name: str) -> None:
        _remove(self.spark, f"{self.root}/{name}")

    def close(self) -> None:
        _remove(self.spark, self.root)


def release(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of plans that nothing refers to any more: an iterative job would else keep those of all its rounds, since
    Spark's cleaner follows the garbage collection of the driver."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def bounded_broadcast(df: DataFrame, row_bytes: int, bytes_bound: int = 32 << 20) -> DataFrame:
    """Broadcast hint if the counted rows are under the bound; the plain frame (a shuffle join) beyond it. For written tables, where counting is cheap."""
    return F.broadcast(df) if df.count() * row_bytes <= bytes_bound else df


# Word keys: every byte has a seeded 64-bit value, a word's key is their polynomial in an odd base modulo 2^64, finalised with the length.
# Prefix sums give all words of a joined buffer at once; the base has an inverse, so a word's place in the buffer drops out.
BYTE_VALUES = np.random.default_rng(20).integers(0, 2**64, 256, dtype=np.uint64)
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
BASE, INVERSE = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 2**64)
PIECE = 1 << 20
LONG_WORD = 256  # polynomials modulo 2^64 have known collisions between long words: those are hashed one by one
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_tables(n: int) -> list[np.ndarray]:
    if len(_powers[0]) < n:
        for k, base in enumerate((BASE, INVERSE)):
            steps = np.full(max(n, PIECE), base, np.uint64)
            steps[0] = 1
            _powers[k] = np.cumprod(steps, dtype=np.uint64)
    return _powers


def _buffer_keys(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(keys, first bytes) of the words in a lower-cased buffer."""
    data = np.frombuffer(raw, np.uint8)
    inside = np.r_[False, ~SPACE[data], False]
    edges = np.flatnonzero(inside[1:] != inside[:-1])
    first, end = edges[::2], edges[1::2]
    power, inverse = _power_tables(len(data) + 1)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_VALUES[data] * power[: len(data)], out=sums[1:])
    keys = (sums[end] - sums[first]) * inverse[first]
    for k in np.flatnonzero(end - first > LONG_WORD).tolist():
        keys[k] = xxhash.xxh3_64_intdigest(raw[first[k] : end[k]])
    return mix64(keys + (end - first).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), first


def word_keys(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit keys of the words (A-Z lower-cased, cut at ASCII white space) of all texts, and where each text's keys begin (one more entry for the end)."""
    keys, counts, held, size = [], [], [], 0

    def flush():
        nonlocal held, size
        if held:
            found, first = _buffer_keys(b" ".join(held).lower())
            at = np.cumsum([0, *(len(t) + 1 for t in held)])
            keys.append(found)
            counts.extend(np.diff(np.searchsorted(first, at)).tolist())
            held, size = [], 0

    for text in texts:
        text = text or b""
        if len(text) > PIECE:  # a very long text goes in pieces that end at white space
            flush()
            total, at = 0, 0
            while at < len(text):
                stop = at + PIECE
                cut = max((text.rfind(c, at, stop) for c in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c")), default=-1) if stop < len(text) else len(text)
                if cut <= at:  # one word fills the piece: take it whole
                    cut = next((k for k in range(stop, len(text)) if SPACE[text[k]]), len(text))
                found, _ = _buffer_keys(text[at:cut].lower())
                keys.append(found)
                total += len(found)
                at = cut
            counts.append(total)
            continue
        held.append(text)
        size += len(text) + 1
        if size >= PIECE:
            flush()
    flush()
    return (np.concatenate(keys) if keys else np.empty(0, np.uint64)), np.cumsum([0, *counts])


def hash_sample(df: DataFrame, k: int, id_col: str = "doc_id", by: str | None = None) -> DataFrame:
    """The min(k, all) rows per group with the smallest hash of their id (column `h`), ties by id. A cut that follows from the group's count
    leaves about 4 k rows before any are sorted, so no task reads more than its own partition and that."""
    group = F.col(by) if by else F.lit(0)
    sizes = df.where(group.isNotNull()).groupBy(group.alias("g")).agg(F.count(F.lit(1)).alias("n")).collect()
    if not sizes:
        return df.where("false").withColumn("h", F.lit(0).cast("long"))
    highest = lambda n: (1 << 63) - 1 if 4 * k >= n else int(-(2**63) + 4 * k / n * 2**64)
    cuts = F.create_map(*chain.from_iterable((F.lit(r.g), F.lit(highest(r.n)).cast("long")) for r in sizes))
    some = df.where(group.isNotNull()).withColumn("h", F.xxhash64(F.col(id_col).cast("string"))).where(F.col("h") <= cuts[group])
    order = Window.partitionBy(group).orderBy("h", id_col)
    return some.withColumn("_nth", F.row_number().over(order)).where(F.col("_nth") <= k).drop("_nth")


def words_of(text: bytes | None) -> list[bytes]:
    """Words ``[^\\x20\\x09-\\x0D]+`` after lower-casing A-Z: what bytes.lower and bytes.split do."""
    return text.lower().split() if text else []


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (fixed multipliers) that spreads every input bit."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))
