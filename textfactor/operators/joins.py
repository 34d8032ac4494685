"""Joins and scans Spark has no operator for: interval joins, as-of joins, edit-distance joins, scans over one global order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, point: str, spans: DataFrame, lo: str, hi: str, width: int, on: tuple[str, ...] = ()) -> DataFrame:
    """points joined to spans with lo <= point <= hi (and equal `on` columns): spans are exploded into bins of `width`, so the join is an equi-join with
    a residual; a plain BETWEEN would be a nested loop. Choose width near the median span; long spans cost one row per bin."""
    bins = spans.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    left = points.withColumn("_bin", F.floor(F.col(point) / width))
    return left.join(bins, [*on, "_bin"]).where((F.col(point) >= F.col(lo)) & (F.col(point) <= F.col(hi))).drop("_bin")


def asof_join(rows: DataFrame, at: str, marks: DataFrame, mark: str, values: list[str], by: list[str]) -> DataFrame:
    """Each row with the values of the last mark <= at in its `by` group: one union, one window, no join blow-up. by is not empty (a key, or a bin)."""
    empty = [F.lit(None).cast(marks.schema[v].dataType).alias(v) for v in values]
    left = rows.select("*", F.col(at).alias("_at"), F.lit(1).alias("_row"), F.lit(None).cast(marks.schema[mark].dataType).alias("_mark"), *empty)
    missing = [F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in rows.columns if c not in by]
    right = marks.select(*by, *missing, F.col(mark).alias("_at"), F.lit(0).alias("_row"), F.col(mark).alias("_mark"), *values)
    order = Window.partitionBy(*by).orderBy("_at", "_row").rowsBetween(Window.unboundedPreceding, 0)
    last = [F.last(v, ignorenulls=True).over(order).alias(v) for v in [*values, "_mark"]]
    both = left.unionByName(right.select(left.columns))
    return both.select(*rows.columns, "_row", *last).where("_row = 1").drop("_row").withColumnRenamed("_mark", mark)


def similarity_join(left: DataFrame, right: DataFrame, l_id: str, r_id: str, l_text: str, r_text: str, k: int, self_join: bool = False, count_q: int | None = None) -> DataFrame:
    """(l_id, r_id, distance) of all pairs with edit distance <= k.

    Pigeonhole: cut the left text into k+1 segments; k edits leave one of them untouched, and shifted by at most k in the right text. So pairs meet on
    (segment number, left length, segment text). Texts of at most k symbols have empty segments and meet by length instead. With count_q, pairs that share
    too few distinct q-grams fall out: an edit touches at most q of them. Verification is the bounded built-in distance, once per pair.

    With k = 1 a segment that most texts share would make all of them candidates of each other, so there pairs meet on what one edit leaves (see one_edit_join)."""
    if k == 1:
        return one_edit_join(left, right, l_id, r_id, l_text, r_text, self_join)
    a = left.select(F.col(l_id).alias("l_id"), F.col(l_text).alias("lt")).where("lt is not null")
    b = right.select(F.col(r_id).alias("r_id"), F.col(r_text).alias("rt")).where("rt is not null")
    parts = k + 1
    number = F.explode(F.sequence(F.lit(0), F.lit(k)))
    la = a.withColumn("n", F.length("lt")).where(F.col("n") > k).select("*", number.alias("i"))
    la = la.select("l_id", "lt", "n", "i", F.expr(f"substr(lt, cast(floor(n * i / {parts}) as int) + 1, cast(floor(n * (i + 1) / {parts}) as int) - cast(floor(n * i / {parts}) as int))").alias("seg"))
    # each right text is probed for every left length within k, every segment and every shift within k
    rb = b.withColumn("m", F.length("rt")).select("*", F.explode(F.sequence(F.greatest(F.lit(k + 1), F.col("m") - k), F.col("m") + k)).alias("n")).select("*", number.alias("i"))
    rb = rb.where(F.col("n") > k).withColumn("p0", F.floor(F.col("n") * F.col("i") / parts).cast("int")).withColumn("size", F.floor(F.col("n") * (F.col("i") + 1) / parts).cast("int") - F.col("p0"))
    rb = rb.select("*", F.explode(F.sequence(F.greatest(F.lit(0), F.col("p0") - k), F.greatest(F.lit(0), F.col("p0") + k))).alias("at")).where(F.col("at") + F.col("size") <= F.col("m"))
    rb = rb.select("r_id", "rt", "n", "i", F.expr("substr(rt, at + 1, size)").alias("seg")).distinct()
    met = la.join(rb, ["n", "i", "seg"]).select("l_id", "r_id", "lt", "rt")
    short = a.where(F.length("lt") <= k).withColumn("n", F.length("lt")).select("*", F.explode(F.sequence(F.lit(0), F.col("n") + k)).alias("m")).join(b.withColumn("m", F.length("rt")), "m").select("l_id", "r_id", "lt", "rt")
    pairs = met.unionByName(short)
    if self_join:
        pairs = pairs.where("l_id < r_id")
    pairs = pairs.dropDuplicates(["l_id", "r_id"])
    if count_q:
        grams = lambda c: F.expr(f"array_distinct(transform(sequence(1, greatest(length({c}) - {count_q - 1}, 1)), i -> substr({c}, i, {count_q})))")
        pairs = pairs.withColumn("lg", grams("lt")).withColumn("rg", grams("rt"))
        pairs = pairs.where(F.size(F.array_intersect("lg", "rg")) >= F.greatest(F.size("lg"), F.size("rg")) - k * count_q)
    return pairs.select("l_id", "r_id", F.levenshtein(F.col("lt"), F.col("rt"), k).alias("distance")).where("distance >= 0")


def one_edit_join(left: DataFrame, right: DataFrame, l_id: str, r_id: str, l_text: str, r_text: str, self_join: bool = False) -> DataFrame:
    """(l_id, r_id, distance) of all pairs with edit distance <= 1, as one equi-join whose matches are the pairs, each once.

    A substitution: equal texts without the symbol at one place, equal place, other symbols there. Otherwise one text is the other one without at most one
    symbol; only the first symbol of a run of equal ones is left out, so a text has each shorter form once."""

    def keys(df, key, text, name, mine, other):
        t = df.select(F.col(key).alias(name), F.col(text).alias("t")).where("t is not null")
        places = "filter(sequence(0, length(t)), p -> p > 0)"
        without = "concat(left(t, p - 1), substr(t, p + 1))"
        forms = f"""concat(array(struct({mine} as p, t as v, '' as c), struct({other} as p, t as v, '' as c)),
            transform({places}, p -> struct(p as p, {without} as v, substr(t, p, 1) as c)),
            transform(filter({places}, p -> p = 1 or substr(t, p, 1) <> substr(t, p - 1, 1)), p -> struct({other} as p, {without} as v, substr(t, p, 1) as c)))"""
        return t.select(name, F.expr(f"inline({forms})"))

    # place -1: the left text as it is; -2: the right text as it is; equal texts meet at -1 only
    a = keys(left, l_id, l_text, "l_id", -1, -2).withColumnRenamed("c", "lc").where("p <> -2 or lc <> ''")
    b = keys(right, r_id, r_text, "r_id", -2, -1).withColumnRenamed("c", "rc")
    met = a.join(b.hint("merge"), ["p", "v"]).where("p < 0 or lc <> rc")  # the estimate knows the files' size only, not that of the forms
    if self_join:
        met = met.where("l_id < r_id")
    return met.select("l_id", "r_id", F.when((F.col("lc") == "") & (F.col("rc") == ""), 0).otherwise(1).alias("distance"))


def similar_classes(df: DataFrame, key: str, text: str, k: int, count_q: int | None = None) -> DataFrame:
    """(l_id, r_id, distance): pairs within k of the representatives (smallest key) of different texts, and every copy with its representative at distance 0.
    So copies are not expanded into all pairs, and each link between rows follows from the two representatives' pair."""
    t = df.select(F.col(key).alias("r_id"), F.col(text).alias("t")).where("t is not null")
    first = t.groupBy("t").agg(F.min("r_id").alias("l_id"))
    pairs = similarity_join(first, first, "l_id", "l_id", "t", "t", k, self_join=True, count_q=count_q)
    copies = t.join(first.hint("merge"), "t").where("l_id <> r_id").select("l_id", "r_id", F.lit(0).alias("distance"))
    return pairs.unionByName(copies)


def global_running(df: DataFrame, order: list[str], value: Column, how: str, name: str, inclusive: bool = True) -> DataFrame:
    """df with a running sum or minimum of `value` over one global order, without a single-task window.

    Rows are range-partitioned by the order; every partition's total goes to the driver (one row each) as carry-ins, and a second pass runs inside the
    partitions. The partitioning is read back from a written table, so both passes see the same rows."""
    from textfactor.operators.scratch import Scratch

    spark = df.sparkSession
    kind = {"sum": F.sum, "min": F.min}[how]
    ranged = df.withColumn("_v", value).repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id())
    table = Scratch(spark, "running").write(ranged, "rows")
    totals = sorted((r["_part"], r["t"]) for r in table.groupBy("_part").agg(kind("_v").alias("t")).collect())
    carry, rows = None, []
    for part, total in totals:
        rows.append((part, carry))
        carry = total if carry is None else (carry + total if how == "sum" else min(carry, total))
    value_type = table.schema["_v"].dataType.simpleString()
    carries = spark.createDataFrame(rows, f"_part int, _carry {value_type if how == 'min' else 'bigint'}")
    inside = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0 if inclusive else -1)
    here = kind("_v").over(inside)
    joined = table.join(F.broadcast(carries), "_part")
    if how == "sum":
        out = F.coalesce(here, F.lit(0)) + F.coalesce("_carry", F.lit(0))
    else:
        out = F.least(here, F.col("_carry"))
    return joined.withColumn(name, out).drop("_v", "_part", "_carry")


def dense_ranks(df: DataFrame, key: list[str], name: str) -> DataFrame:
    """0-based dense rank of the key over the whole table: distinct keys are ranked by a global running sum and joined back."""
    keys = df.select(*key).distinct()
    ranked = global_running(keys, key, F.lit(1).cast("bigint"), "sum", name).withColumn(name, F.col(name) - 1)
    return df.join(ranked, key)


