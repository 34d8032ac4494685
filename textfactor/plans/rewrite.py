"""Plan builders: what Catalyst can't derive about texts, written out as ordinary columns and exchanges."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def prefilter_pairs(df: DataFrame, a: str, b: str, k: int | None) -> DataFrame:
    """Adds `decided`: 0 for equal pairs, -1 where the length gap passes k, null where a kernel has to look."""
    gap = F.abs(F.length(a) - F.length(b))
    decided = F.when(F.col(a) == F.col(b), F.lit(0))
    if k is not None:
        decided = decided.when(gap > k, F.lit(-1))
    return df.withColumn("decided", decided)


def balance_by_cost(df: DataFrame, cost: Column, partitions: int | None = None) -> DataFrame:
    """Deals rows so that each power-of-two cost class is spread over all partitions: long texts don't gather in one task."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    klass = F.floor(F.log2(F.greatest(cost, F.lit(1)) + 1))
    return df.repartition(n, klass, F.xxhash64(*df.columns))


def choose_tau(n: int, z: int) -> int:
    """Grid step that balances n/tau against tau*z."""
    return max(1, math.ceil(math.sqrt(max(1, n) / max(1, z))))


def choose_power(n: int, r: int) -> int:
    """Power of two next to sqrt(n / r)."""
    return 1 << max(0, round(math.log2(max(1.0, math.sqrt(n / max(1, r))))))


def work_formula(n: Column, z: Column, tau: Column, roots: Column | None = None) -> Column:
    """n / tau + z + tau z + the sum of the roots of phrase lengths (sqrt(zn) bounds it)."""
    return n / tau + z + tau * z + (F.sqrt(z * n) if roots is None else roots)


def checked_broadcast(df: DataFrame, bytes_bound: int = 64 << 20) -> DataFrame:
    """Broadcast hint only if the optimizer's own size estimate is under the bound; the plain frame (shuffle join) beyond it."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(df) if size <= bytes_bound else df


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
