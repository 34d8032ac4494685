"""Operators over one text spread over many rows (pos, sym), pos from 0 without gaps: nothing holds the text as a whole.

Suffix ranks by doubling with equi-joins on pos + 2^t, global dense ranks by range partitions with carry-ins, BWT and runs by joins and
running sums, and the greedy factorization from previous/next smaller positions in rank order: blocks of positions are
walked independently for every possible entry, and the driver only chains one entry per block.
"""

from __future__ import annotations

import bisect

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.operators.joins import dense_ranks, global_running
from textfactor.operators.scratch import Scratch


def suffix_ranks(symbols: DataFrame, max_rounds: int = 48) -> DataFrame:
    """(pos, sym, rank, level): 0-based suffix ranks; each round is written, and stops when all ranks differ."""
    scratch = Scratch(symbols.sparkSession, "ranks")
    now = scratch.write(dense_ranks(symbols.select(F.col("pos").cast("long"), "sym"), ["sym"], "rank"), "rank0")
    n = now.count()
    width = 1
    for _ in range(max_rounds):
        top = now.agg(F.max("rank")).first()[0]
        if top is None or top == n - 1:
            break
        ahead = now.select((F.col("pos") - width).alias("pos"), F.col("rank").alias("after"))
        pair = now.join(ahead, "pos", "left").withColumn("after", F.coalesce("after", F.lit(-1))).withColumnRenamed("rank", "first")
        now = scratch.write(dense_ranks(pair, ["first", "after"], "rank").select("pos", "sym", "rank"), f"rank{width}")
        width *= 2
    return now


def bwt_table(ranks: DataFrame) -> DataFrame:
    """(row, pos, bwt) with the sentinel's row 0; bwt null stands for the sentinel."""
    before = ranks.select((F.col("pos") + 1).alias("pos"), F.col("sym").alias("bwt"))
    rows = ranks.select((F.col("rank") + 1).alias("row"), "pos").join(before, "pos", "left")
    n = ranks.agg(F.count(F.lit(1)).alias("n"))
    end = ranks.join(F.broadcast(n), F.col("pos") == F.col("n") - 1).select(F.lit(0).cast("long").alias("row"), F.col("n").alias("pos"), F.col("sym").alias("bwt"))
    return rows.select("row", "pos", "bwt").unionByName(end)


def runs_table(bwt: DataFrame) -> DataFrame:
    """(run_no, bwt, row_start, row_end): gaps and islands; the neighbour above comes by an equi-join, the numbering by a global running sum."""
    above = bwt.select((F.col("row") + 1).alias("row"), F.col("bwt").alias("above"), F.lit(True).alias("has"))
    marked = bwt.join(above, "row", "left").withColumn("new", F.when(F.col("has") & F.col("above").eqNullSafe(F.col("bwt")), 0).otherwise(1).cast("bigint"))
    numbered = global_running(marked.select("row", "bwt", "new"), ["row"], F.col("new"), "sum", "run_no")
    return numbered.groupBy("run_no").agg(F.first("bwt").alias("bwt"), F.min("row").alias("row_start"), F.max("row").alias("row_end"))


def lyndon_starts(ranks: DataFrame) -> DataFrame:
    """(start): strict prefix minima of the ranks, by a global running minimum."""
    low = global_running(ranks.select("pos", "rank"), ["pos"], F.col("rank"), "min", "low", inclusive=True)
    return low.where("low = rank").select(F.col("pos").alias("start"))


def qgram_counts(symbols: DataFrame, q: int) -> DataFrame:
    """(gram, n) of one long text: q - 1 equi-joins on shifted positions would shuffle q times, so blocks overlap by q - 1 symbols instead."""
    block = 4096
    own = symbols.select(F.floor(F.col("pos") / block).alias("b"), "pos", "sym", F.lit(True).alias("own"))
    over = symbols.where((F.col("pos") % block < q - 1) & (F.col("pos") >= block)).select((F.floor(F.col("pos") / block) - 1).alias("b"), "pos", "sym", F.lit(False).alias("own"))

    def grams(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("pos").to_numpy())
        sym, mine = table.column("sym").to_numpy()[order], table.column("own").to_numpy(zero_copy_only=False)[order]
        count: dict[str, int] = {}
        for i in range(min(int(mine.sum()), len(sym) - q + 1)):
            g = ",".join(map(str, sym[i : i + q].tolist()))
            count[g] = count.get(g, 0) + 1
        return pa.table({"gram": pa.array(list(count), pa.string()), "n": pa.array(list(count.values()), pa.int64())})

    return own.unionByName(over).groupBy("b").applyInArrow(grams, "gram string, n long").groupBy("gram").agg(F.sum("n").alias("n"))


def pattern_positions(symbols: DataFrame, pattern: list[int], block: int = 65536) -> DataFrame:
    """(pos) of the occurrences of a short pattern: blocks overlap by the pattern's length."""
    m = len(pattern)
    own = symbols.select(F.floor(F.col("pos") / block).alias("b"), "pos", "sym")
    over = symbols.where((F.col("pos") % block < m - 1) & (F.col("pos") >= block)).select((F.floor(F.col("pos") / block) - 1).alias("b"), "pos", "sym")

    def scan(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("pos").to_numpy())
        pos, sym = table.column("pos").to_numpy()[order], table.column("sym").to_numpy()[order]
        hit = np.ones(max(0, len(sym) - m + 1), bool)
        for k, s in enumerate(pattern):
            hit &= sym[k : k + len(hit)] == s
        return pa.table({"pos": pa.array(pos[: len(hit)][hit], pa.int64())})

    return own.unionByName(over).groupBy("b").applyInArrow(scan, "pos long").where(F.col("pos").isNotNull()).distinct()


def _neighbours(ranks: DataFrame, block: int) -> DataFrame:
    """(pos, before, after): the nearest smaller positions above and below in rank order, -1 if none.

    Blocks of ranks are scanned alone with a stack; what a block can't answer itself waits for the nearest block whose minimum is smaller. The
    block minima (one per block) are on the driver; the waiting rows are joined to the blocks that hold their answer."""
    spark = ranks.sparkSession
    scratch = Scratch(spark, "neighbours")
    rows = ranks.select("pos", "rank", F.floor(F.col("rank") / block).alias("b"))
    minima = dict(sorted((r.b, r.m) for r in rows.groupBy("b").agg(F.min("pos").alias("m")).collect()))
    sent = spark.sparkContext.broadcast(minima)

    def inside(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("rank").to_numpy())
        pos = table.column("pos").to_numpy()[order].tolist()
        out = {}
        for side, line in (("before", range(len(pos))), ("after", range(len(pos) - 1, -1, -1))):
            stack, got = [], [-1] * len(pos)
            for i in line:
                while stack and stack[-1] > pos[i]:
                    stack.pop()
                got[i] = stack[-1] if stack else -1
                stack.append(pos[i])
            out[side] = got
        b, mins = key[0].as_py(), sent.value
        ids = sorted(mins)
        at = bisect.bisect_left(ids, b)
        ask_before, ask_after = [], []
        for p, x, y in zip(pos, out["before"], out["after"], strict=True):
            ask_before.append(next((c for c in reversed(ids[:at]) if mins[c] < p), -1) if x < 0 else -1)
            ask_after.append(next((c for c in ids[at + 1 :] if mins[c] < p), -1) if y < 0 else -1)
        return pa.table({"pos": pa.array(pos, pa.int64()), "before": pa.array(out["before"], pa.int64()), "after": pa.array(out["after"], pa.int64()), "ask_before": pa.array(ask_before, pa.int64()), "ask_after": pa.array(ask_after, pa.int64())})

    local = scratch.write(rows.groupBy("b").applyInArrow(inside, "pos long, before long, after long, ask_before long, ask_after long"), "inside")
    ask = local.where("ask_before >= 0").select("pos", F.col("ask_before").alias("ask"), F.lit(0).alias("side")).unionByName(local.where("ask_after >= 0").select("pos", F.col("ask_after").alias("ask"), F.lit(1).alias("side")))

    def answer(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        order = np.argsort(right.column("rank").to_numpy())
        line = right.column("pos").to_numpy()[order].tolist()
        found = []
        for p, side in zip(left.column("pos").to_pylist(), left.column("side").to_pylist(), strict=True):
            seq = reversed(line) if side == 0 else line
            found.append(next(v for v in seq if v < p))
        return pa.table({"pos": left.column("pos"), "side": left.column("side"), "found": pa.array(found, pa.int64())})

    held = rows.select(F.col("b").alias("of_b"), F.col("pos").alias("pos"), "rank")
    known = ask.groupBy("ask").cogroup(held.groupBy("of_b")).applyInArrow(answer, "pos long, side int, found long")
    found = known.groupBy("pos").agg(F.max(F.when(F.col("side") == 0, F.col("found"))).alias("fb"), F.max(F.when(F.col("side") == 1, F.col("found"))).alias("fa"))
    return local.join(found, "pos", "left").select("pos", F.coalesce("fb", "before").alias("before"), F.coalesce("fa", "after").alias("after"))


def lz77_lengths(symbols: DataFrame, levels: list[DataFrame] | None = None, block: int = 4096) -> DataFrame:
    """(start, len, src) of the greedy factorization of one long text (src -1: fresh symbol).

    Longest previous factors come from the two neighbours in rank order, with extensions by descending doubling levels (one equi-join per level). Every block of positions
    then maps each entry offset to its exit, the driver chains the blocks (one row per block), and the blocks emit their phrases."""
    spark = symbols.sparkSession
    scratch = Scratch(spark, "lz")
    levels = levels if levels is not None else doubling_levels(symbols)
    ranks = levels[-1]
    near = scratch.write(_neighbours(ranks, block), "near")
    best = None
    for side in ("before", "after"):
        pairs = near.where(F.col(side) >= 0).select("pos", F.col(side).alias("src"), F.lit(0).cast("long").alias("l"))
        for t in range(len(levels) - 1, -1, -1):
            for _ in range(2 if t == len(levels) - 1 else 1):
                level = levels[t].select(F.col("pos").alias("p"), F.col("rank").alias("r"))
                a = level.select(F.col("p").alias("pa"), F.col("r").alias("ra"))
                b = level.select(F.col("p").alias("pb"), F.col("r").alias("rb"))
                pairs = pairs.join(a, F.col("pos") + F.col("l") == F.col("pa"), "left").join(b, F.col("src") + F.col("l") == F.col("pb"), "left")
                pairs = pairs.select("pos", "src", (F.col("l") + F.when(F.col("ra") == F.col("rb"), 1 << t).otherwise(0)).alias("l"))
            pairs = scratch.write(pairs, f"ext-{side}-{t}")
        best = pairs if best is None else best.unionByName(pairs)
    top = best.groupBy("pos").agg(F.max(F.struct("l", "src")).alias("m")).select("pos", F.col("m.l").alias("l"), F.col("m.src").alias("src"))
    factors = scratch.write(symbols.select(F.col("pos").cast("long")).join(top, "pos", "left").select("pos", F.floor(F.col("pos") / block).alias("b"), F.coalesce("l", F.lit(0)).alias("l"), F.when(F.col("l") > 0, F.col("src")).otherwise(-1).alias("src")), "factors")

    def exits(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("pos").to_numpy())
        pos, size = table.column("pos").to_numpy()[order], np.maximum(table.column("l").to_numpy()[order], 1)
        out = pos + size
        first = int(pos[0])
        for i in range(len(pos) - 1, -1, -1):
            k = int(out[i]) - first
            if k < len(pos):
                out[i] = out[k]
        return pa.table({"b": pa.array([key[0].as_py()], pa.int64()), "first": pa.array([first], pa.int64()), "exits": pa.array([out.tolist()], pa.list_(pa.int64()))})

    table = scratch.write(factors.groupBy("b").applyInArrow(exits, "b long, first long, exits array<long>"), "exits")
    entries, at = [], 0
    for r in table.orderBy("b").toLocalIterator():  # one block at a time; only the entry is kept
        if at - r.first < len(r.exits):
            entries.append((r.b, at))
            at = r.exits[at - r.first]
    entry = spark.createDataFrame(entries, "of_b long, entry long")

    def emit(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        rows = []
        if right.num_rows:
            order = np.argsort(left.column("pos").to_numpy())
            pos, size, src = (left.column(c).to_numpy()[order] for c in ("pos", "l", "src"))
            i = int(right.column("entry")[0].as_py()) - int(pos[0])
            while i < len(pos):
                step = max(1, int(size[i]))
                rows.append((int(pos[i]), step, int(src[i])))
                i += step
        a, b, c = zip(*rows, strict=True) if rows else ((), (), ())
        return pa.table({"start": pa.array(a, pa.int64()), "len": pa.array(b, pa.int64()), "src": pa.array(c, pa.int64())})

    return factors.groupBy("b").cogroup(entry.groupBy("of_b")).applyInArrow(emit, "start long, len long, src long")


def doubling_levels(symbols: DataFrame, max_rounds: int = 48) -> list[DataFrame]:
    """All doubling levels (pos, rank), the last being the suffix ranks; each is a written table."""
    scratch = Scratch(symbols.sparkSession, "levels")
    now = scratch.write(dense_ranks(symbols.select(F.col("pos").cast("long"), "sym"), ["sym"], "rank").select("pos", "rank"), "l0")
    n, out, width = now.count(), [now], 1
    for _ in range(max_rounds):
        top = now.agg(F.max("rank")).first()[0]
        if top is None or top == n - 1:
            break
        ahead = now.select((F.col("pos") - width).alias("pos"), F.col("rank").alias("after"))
        pair = now.join(ahead, "pos", "left").withColumn("after", F.coalesce("after", F.lit(-1))).withColumnRenamed("rank", "first")
        now = scratch.write(dense_ranks(pair, ["first", "after"], "rank").select("pos", "rank"), f"l{width}")
        out.append(now)
        width *= 2
    return out


