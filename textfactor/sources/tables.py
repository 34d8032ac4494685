"""Inputs: the given tables, fixed-schema readers, and builders of strings from rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor import schema

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: A total order of lineitem; (orderkey, linenumber) alone repeats.
LINE_ORDER = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
SEPARATOR = "\x01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_text_files(spark: SparkSession, path: str) -> DataFrame:
    """(path, text): one row per file, whole."""
    return spark.read.text(path, wholetext=True).select(F.col("_metadata.file_path").alias("path"), F.col("value").alias("text"))


def read_json(spark: SparkSession, path: str, ddl: str = schema.DOCUMENT) -> DataFrame:
    return spark.read.schema(ddl).json(path)


def read_csv(spark: SparkSession, path: str, ddl: str) -> DataFrame:
    return spark.read.schema(ddl).option("header", True).option("multiLine", True).option("escape", '"').csv(path)


def write_partitioned(df: DataFrame, path: str, by: list[str], mode: str = "overwrite") -> None:
    df.write.mode(mode).partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table whose later joins on the key need no shuffle."""
    df.repartition(buckets, key).write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def ordered_string(df: DataFrame, by: list[str], order: list[str], symbol: Column, name: str = "s") -> DataFrame:
    """by + name: the group's symbols in the given total order. Sorted inside the row, since collect_list keeps no order."""
    rows = F.array_sort(F.collect_list(F.struct(*order, symbol.alias("_sym"))))
    return df.groupBy(*by).agg(F.array_join(F.transform(rows, lambda r: r["_sym"]), "").alias(name))


def ordered_array(df: DataFrame, by: list[str], order: list[str], symbol: str, name: str = "syms") -> DataFrame:
    rows = F.array_sort(F.collect_list(F.struct(*order, F.col(symbol).alias("_sym"))))
    return df.groupBy(*by).agg(F.transform(rows, lambda r: r["_sym"]).alias(name))


def event_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, s): first letters of the event types in time order (v, c, s, e, p)."""
    return ordered_string(table(spark, sf_dir, "events"), ["user_id"], ["ts", "event_id"], F.left("event_type", F.lit(1)))


def short_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, t): every benchmark text and every event sequence."""
    items = table(spark, sf_dir, "benchmark").select(F.concat(F.lit("b"), F.col("item_id").cast("string")).alias("id"), F.col("text").alias("t"))
    return items.unionByName(event_sequences(spark, sf_dir).select(F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("id"), F.col("s").alias("t")))


def sign_strings(spark: SparkSession, sf_dir: str, size: int) -> DataFrame:
    """(s): the different strings of the signs of the vectors' first components (1: positive)."""
    first = F.transform(F.slice("embedding", 1, size), lambda v: F.when(v > 0, "1").otherwise("0"))
    return table(spark, sf_dir, "embeddings").where(F.size("embedding") >= size).select(F.array_join(first, "").alias("s")).distinct()


def neighbour_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a_id, b_id, a, b): the sequences of users with consecutive ids."""
    s = event_sequences(spark, sf_dir)
    left = s.select(F.col("user_id").alias("a_id"), F.col("s").alias("a"))
    right = s.select((F.col("user_id") - 1).alias("a_id"), F.col("user_id").alias("b_id"), F.col("s").alias("b"))
    return left.join(right, "a_id").select("a_id", "b_id", "a", "b")


def flag_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pos, sym): return flag and line status over the whole of lineitem in its total order, as one long text of six symbols."""
    from textfactor.operators.joins import global_running

    rows = table(spark, sf_dir, "lineitem").select(*LINE_ORDER, F.concat("l_returnflag", "l_linestatus").alias("sym"))
    numbered = global_running(rows, list(LINE_ORDER), F.lit(1).cast("bigint"), "sum", "pos")
    return numbered.select((F.col("pos") - 1).alias("pos"), "sym")


def part_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pos, sym): part keys over lineitem in its total order: a large alphabet."""
    from textfactor.operators.joins import global_running

    rows = table(spark, sf_dir, "lineitem").select(*LINE_ORDER)
    numbered = global_running(rows, list(LINE_ORDER), F.lit(1).cast("bigint"), "sum", "pos")
    return numbered.select((F.col("pos") - 1).alias("pos"), F.col("l_partkey").alias("sym"))


def blocks(df: DataFrame, id_col: str, text: str, size: int, overlap: int = 0) -> DataFrame:
    """(id, block_no, start, piece): a text cut into blocks of `size` symbols that run on for `overlap` more; 0-based starts."""
    cut = df.where(F.length(text) > 0).select(id_col, F.col(text).alias("t"), F.posexplode(F.sequence(F.lit(0), F.length(text) - 1, F.lit(size))).alias("block_no", "start"))
    return cut.select(id_col, "block_no", "start", F.expr(f"substr(t, start + 1, {int(size) + int(overlap)})").alias("piece"))


def exact_groups(df: DataFrame, id_col: str, text: str) -> DataFrame:
    """(digest, first_id, n): groups of equal texts."""
    return df.groupBy(F.sha2(text, 256).alias("digest")).agg(F.min(id_col).alias("first_id"), F.count(F.lit(1)).alias("n"))


def edit_inject(df: DataFrame, id_col: str, text: str, k: int) -> DataFrame:
    """id, a, b: b is a with "~" put in k places that follow from the id. Each changed place adds one "~", so the distance is the number of changed places."""
    size = F.greatest(F.length(text), F.lit(1))
    places = F.array_distinct(F.transform(F.sequence(F.lit(1), F.lit(max(1, k))), lambda j: F.pmod(F.col(id_col) * 7919 + j * 104729, size) + 1)) if k else F.array().cast("array<bigint>")
    base = df.select(id_col, F.col(text).alias("a"), places.alias("_p"))
    edited = F.aggregate("_p", F.col("a"), lambda s, p: F.overlay(s, F.lit("~"), p.cast("int"), F.lit(1)))
    return base.select(id_col, "a", F.when(F.length("a") > 0, edited).otherwise(F.col("a")).alias("b"))


def html_text(html: str) -> Column:
    """Visible text of a page: scripts, styles and tags out, white space collapsed."""
    bare = F.regexp_replace(F.col(html), "(?is)<(script|style)[^>]*>.*?</\\1>", " ")
    bare = F.regexp_replace(bare, "(?s)<[^>]*>", " ")
    return F.trim(F.regexp_replace(bare, "\\s+", " "))
