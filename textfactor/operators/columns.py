"""Operators that are plain Catalyst expressions over short texts: everything stays inside whole-stage codegen."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def mean_of_copies(value: Column | str, name: str | None = None, copies: str = "copies") -> Column:
    """Mean over all rows of a table whose equal rows were run once, `copies` being how often a row is there."""
    value, name = (F.col(value), name or value) if isinstance(value, str) else (value, name)
    return (F.sum(value * F.col(copies)) / F.sum(F.when(value.isNotNull(), F.col(copies)))).alias(name)


def suffix_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (pos, suffix), 1-based, for non-empty texts."""
    spread = df.where(F.length(text) > 0).select(*keep, F.col(text).alias("t"), F.explode(F.sequence(F.lit(1), F.length(text))).alias("pos"))
    return spread.select(*keep, "t", "pos", F.expr("substr(t, pos)").alias("suffix"))


def suffix_ranks(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (pos, rank), both 1-based; the order is by code point, a prefix before what it is a prefix of."""
    return suffix_rows(df, text, keep).withColumn("rank", F.row_number().over(Window.partitionBy(*keep).orderBy("suffix"))).drop("suffix")


def bwt_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (rank, pos, bwt): text + sentinel; rank 0 is the sentinel's row, the sentinel itself the empty string."""
    ranks = suffix_ranks(df, text, keep)
    before = F.when(F.col("pos") == 1, F.lit("")).otherwise(F.expr("substr(t, pos - 1, 1)"))
    rows = ranks.select(*keep, "rank", "pos", before.alias("bwt"))
    end = df.where(F.length(text) > 0).select(*keep, F.lit(0).alias("rank"), (F.length(text) + 1).alias("pos"), F.right(text, F.lit(1)).alias("bwt"))
    return rows.unionByName(end)


def bwt_run_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (run_no, bwt, row_start, row_end) by gaps and islands."""
    order = Window.partitionBy(*keep).orderBy("rank")
    new = F.when(F.lag("bwt").over(order).eqNullSafe(F.col("bwt")), 0).otherwise(1)
    island = F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0))
    runs = bwt_rows(df, text, keep).withColumn("new", new).withColumn("run_no", island)
    return runs.groupBy(*keep, "run_no").agg(F.first("bwt").alias("bwt"), F.min("rank").alias("row_start"), F.max("rank").alias("row_end"))


def lf_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (rank, lf): rank of the suffix one position to the left."""
    rows = bwt_rows(df, text, keep)
    by = Window.partitionBy(*keep).orderBy("bwt", "rank")
    return rows.select(*keep, "rank", (F.row_number().over(by) - 1).alias("lf"))


def lcp_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (rank, pos, lcp) with the suffix before in rank order."""
    order = Window.partitionBy(*keep).orderBy("suffix")
    rows = suffix_rows(df, text, keep).select(*keep, "pos", "suffix", F.row_number().over(order).alias("rank"), F.lag("suffix").over(order).alias("above"))
    fits = F.expr("size(filter(sequence(1, greatest(least(length(suffix), length(above)), 1)), m -> left(suffix, m) = left(above, m)))")
    return rows.select(*keep, "rank", "pos", F.when(F.col("above").isNull(), 0).otherwise(fits).alias("lcp"))


def dsa_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (rank, delta): difference to the suffix-array value before, the first to 0."""
    order = Window.partitionBy(*keep).orderBy("rank")
    return suffix_ranks(df, text, keep).select(*keep, "rank", (F.col("pos") - F.lag("pos", 1, 0).over(order)).alias("delta"))


def lyndon_rows(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (start): 1-based starts of the Lyndon factors, strict prefix minima of the ranks."""
    before = F.min("rank").over(Window.partitionBy(*keep).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1))
    return suffix_ranks(df, text, keep).withColumn("low", before).where("low is null or rank < low").select(*keep, F.col("pos").alias("start"))


def qgram_rows(df: DataFrame, text: str, keep: list[str], q: int) -> DataFrame:
    """keep + (gram): every q-gram occurrence. The text is split into symbols once, so the cost is linear in its length."""
    symbols = df.where(F.length(text) >= q).select(*keep, F.split(text, "").alias("c"))
    if q == 1:
        return symbols.select(*keep, F.explode("c").alias("gram"))
    return symbols.select(*keep, F.explode(F.expr(f"transform(sequence(1, size(c) - {int(q) - 1}), i -> array_join(slice(c, i, {int(q)}), ''))")).alias("gram"))


def qgram_counts(df: DataFrame, text: str, keep: list[str], q: int) -> DataFrame:
    """keep + (gram, n): two-stage hash aggregation, combined before the shuffle."""
    return qgram_rows(df, text, keep, q).groupBy(*keep, "gram").agg(F.count(F.lit(1)).alias("n"))


def distinct_qgrams(df: DataFrame, text: str, keep: list[str], qs: list[int], approximate: bool = False) -> DataFrame:
    """keep + (q, d_q); exact by a distinct aggregation, or a sketch."""
    rows = None
    for q in qs:
        part = qgram_rows(df, text, keep, q).select(*keep, F.lit(q).alias("q"), "gram")
        rows = part if rows is None else rows.unionByName(part)
    count = F.approx_count_distinct("gram") if approximate else F.countDistinct("gram")
    return rows.groupBy(*keep, "q").agg(count.alias("d_q"))


def delta_rows(df: DataFrame, text: str, keep: list[str], max_q: int) -> DataFrame:
    """keep + (delta): max of d_q / q for texts of at most max_q symbols."""
    spread = df.where(F.length(text) > 0).select(*keep, F.col(text).alias("t"), F.explode(F.sequence(F.lit(1), F.least(F.length(text), F.lit(max_q)))).alias("q"))
    grams = spread.select(*keep, "q", F.expr("explode(transform(sequence(1, length(t) - q + 1), p -> substr(t, p, q)))").alias("gram"))
    return grams.groupBy(*keep, "q").agg(F.countDistinct("gram").alias("d")).groupBy(*keep).agg(F.max(F.col("d") / F.col("q")).alias("delta"))


def pattern_positions(texts: DataFrame, text: str, patterns: DataFrame, keep: list[str]) -> DataFrame:
    """keep + (pattern, pos): 1-based occurrences by direct comparison; patterns is a small table with column pattern."""
    from textfactor.plans.rewrite import checked_broadcast

    pairs = texts.select(*keep, F.col(text).alias("t")).join(checked_broadcast(patterns.select("pattern").distinct()), F.expr("instr(t, pattern) > 0"))
    # symbols are split once per hit text, so that looking at a position doesn't walk to it
    at = F.expr("filter(sequence(1, size(c) - length(pattern) + 1), p -> element_at(c, p) = left(pattern, 1) and array_join(slice(c, p, length(pattern)), '') = pattern)")
    pairs = pairs.withColumn("c", F.split("t", ""))
    return pairs.select(*keep, "pattern", F.explode(at).alias("pos"))
