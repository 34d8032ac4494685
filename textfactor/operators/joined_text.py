"""Factorization of texts that are joined from many rows. No row and no object holds a joined text: it lies in a temporary file of the task that works on it."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from textfactor.kernels import external
from textfactor.operators.scratch import Scratch
from textfactor.sources.tables import SEPARATOR

#: Stands for the block of a text that was factorized in one task; its number of steps is that of its phrases.
WHOLE = -1


def phrase_counts(df: DataFrame, by: str, order: str, text: str, range_size: int = 1 << 22, least: int = 1 << 25) -> DataFrame:
    """by, n, z, n_over_z: symbols and greedy phrases of each group's texts, joined by a separator in the given order.

    The suffixes of a text of more than `least` bytes are dealt by ranges of their first bytes to as many tasks as its share of all bytes asks for (two thirds of the
    session's parallelism in all, since each of these reads the group's texts once into a file). Longest previous factors go on packed by blocks of the text, and one
    task a group chains them block by block; a text of one task that is small enough is chained there."""
    spark = df.sparkSession
    docs = df.select(F.col(by).alias("k"), F.col(order).alias("o"), F.col(text).alias("t")).where("t is not null")
    joints = F.count(F.lit(1)) - 1
    sizes = docs.groupBy("k").agg((F.sum(F.length("t").cast("long")) + joints).alias("n"), (F.sum(F.octet_length("t").cast("long")) + joints).alias("bytes"))
    sizes = Scratch(spark, "joined").write(sizes, "sizes")
    whole = sizes.agg(F.sum("bytes")).first()[0] or 0
    share = max(least, 3 * whole // (2 * spark.sparkContext.defaultParallelism))
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    parts = sizes.where("bytes > 0").select(F.col("k").alias("of"), F.ceil(F.col("bytes") / share).cast("int").alias("parts"))
    dealt = docs.join(parts, F.col("k").eqNullSafe(F.col("of"))).select("k", "parts", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), "o", "t")
    dealt = dealt.repartition(tasks, "k", "part").sortWithinPartitions("k", "part", "o", "t").select("k", "parts", "part", F.col("t").cast("binary").alias("t"))
    arrow, kind = to_arrow_schema(docs.select("k").schema).field(0).type, f"k {docs.schema['k'].dataType.simpleString()}"
    found = dealt.mapInArrow(_steps(range_size, 4 * least, arrow), f"{kind}, bytes long, block long, steps long, packed binary, wide binary")
    chained = found.repartition(tasks, "k").sortWithinPartitions("k", "block").mapInArrow(_chain(arrow), f"{kind}, z long")
    ends = chained.select(F.col("k").alias("of"), "z")
    out = sizes.join(ends, F.col("k").eqNullSafe(F.col("of")), "left").select(F.col("k").alias(by), "n", F.coalesce("z", F.lit(0).cast("long")).alias("z"))
    return out.withColumn("n_over_z", F.when(F.col("z") > 0, F.col("n") / F.col("z")))


def _steps(range_size: int, small: int, kind: pa.DataType):
    names = ["k", "bytes", "block", "steps", "packed", "wide"]
    types = [kind, pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]

    def batch(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    def work(key, text: external.TextFile) -> Iterator[pa.RecordBatch]:
        k, parts, part = key
        if text.n and parts == 1 and text.n <= small:
            yield batch([(k, text.n, WHOLE, external.phrase_count(text.view(), range_size), b"", b"")])
        elif text.n:
            view, rows = text.view(), []
            for lo, hi in external.ranges(view, range_size)[part::parts]:
                for found in external.steps(view, lo, hi):
                    rows.append((k, view.n, *found))
                    if len(rows) == 2000:
                        yield batch(rows)
                        rows = []
            if rows:
                yield batch(rows)
        text.close()

    def run(batches):
        key = text = None
        for b in batches:
            for k, parts, part, piece in zip(*(b.column(c) for c in ("k", "parts", "part", "t")), strict=True):
                now = (k.as_py(), parts.as_py(), part.as_py())
                if text is None or now != key:
                    if text is not None:
                        yield from work(key, text)
                    key, text = now, external.TextFile(SEPARATOR.encode())
                text.add(piece.as_py())
        if text is not None:
            yield from work(key, text)

    return run


def _chain(kind: pa.DataType):
    def result(k, chain: external.Chain | int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([k], kind), pa.array([chain if isinstance(chain, int) else chain.close()], pa.int64())], names=["k", "z"])

    def run(batches):
        key = chain = None
        for b in batches:
            for k, n, block, *found in zip(*(b.column(c) for c in ("k", "bytes", "block", "steps", "packed", "wide")), strict=True):
                now, at = k.as_py(), block.as_py()
                if at == WHOLE:
                    yield result(now, found[0].as_py())
                    continue
                if chain is None or now != key:
                    if chain is not None:
                        yield result(key, chain)
                    key, chain = now, external.Chain(n.as_py())
                chain.add(at, *(v.as_py() for v in found))
        if chain is not None:
            yield result(key, chain)

    return run
