"""Streaming forms: symbol strings per window, incremental factorization, bounded distance to a reference, deduplication, joins, sinks.

Every function takes and returns DataFrames of either kind where that is possible, so that a stream can be checked against its batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from textfactor import schema


def file_stream(spark: SparkSession, path: str, ddl: str = schema.EVENT, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(ddl).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def with_event_time(events: DataFrame, late: str = "2 days") -> DataFrame:
    """ts as a zoned timestamp (watermarks reject the zone-less kind) with a watermark; rows later than that are dropped."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def window_strings(events: DataFrame, span: str = "1 day", slide: str | None = None, session: bool = False) -> DataFrame:
    """(user_id, start, s): each user's symbol string per tumbling, sliding or session window."""
    when = F.session_window("ts", span) if session else F.window("ts", span, slide) if slide else F.window("ts", span)
    rows = F.array_sort(F.collect_list(F.struct("ts", "event_id", F.left("event_type", F.lit(1)).alias("sym"))))
    grouped = events.groupBy("user_id", when.alias("w")).agg(rows.alias("r"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.array_join(F.transform("r", lambda x: x["sym"]), "").alias("s"))


def incremental_phrases(events: DataFrame) -> DataFrame:
    """(user_id, phrase_no, start, len): greedy phrases of each user's growing string, emitted when they are final.

    State: the text, the start of the open phrase, and the phrase count. A phrase is final once the next symbol can't extend it, so what
    is emitted never changes; the open phrase stays in the state."""

    def update(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        text, start, count = state.get if state.exists else ("", 0, 0)
        new = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for symbol in new["event_type"].str[:1]:
            text += symbol
            if text.find(text[start:], 0, len(text) - 1) >= 0:
                continue
            size = max(1, len(text) - 1 - start)  # the new symbol broke the open phrase
            out.append((key[0], count, start, size))
            start, count = start + size, count + 1
            if start < len(text) and text.find(text[start:], 0, len(text) - 1) < 0:
                out.append((key[0], count, start, 1))  # a fresh symbol is a phrase of its own
                start, count = start + 1, count + 1
        state.update((text, start, count))
        yield pd.DataFrame(out, columns=["user_id", "phrase_no", "start", "len"])

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, phrase_no int, start int, len int", "text string, start int, count int", "append", GroupStateTimeout.NoTimeout)


def distance_to_reference(events: DataFrame, reference: str, k: int) -> DataFrame:
    """(user_id, n, distance): after each batch, the edit distance of the user's string to the reference, -1 above k. State: the band of one
    table row, so O(k) per user whatever was read."""

    def update(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, band = (state.get[0], list(state.get[1])) if state.exists else (0, [abs(d) if d >= 0 else k + 1 for d in range(-k, k + 1)])
        for symbol in pd.concat(list(frames)).sort_values(["ts", "event_id"])["event_type"].str[:1]:
            n += 1
            row = []
            for d in range(-k, k + 1):  # column j = n + d
                j = n + d
                if j < 0 or j > len(reference):
                    row.append(k + 1)
                    continue
                options = [band[d + k + 1] + 1 if d < k else k + 1]
                if j > 0:
                    options += [band[d + k] + (reference[j - 1] != symbol), row[-1] + 1 if d > -k else k + 1]
                row.append(min(k + 1, *options))
            band = row
        state.update((n, band))
        at = len(reference) - n
        found = band[at + k] if abs(at) <= k else k + 1
        yield pd.DataFrame([(key[0], n, found if found <= k else -1)], columns=["user_id", "n", "distance"])

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, n int, distance int", "n int, band array<int>", "update", GroupStateTimeout.NoTimeout)


def dedup(events: DataFrame, key: str = "event_id") -> DataFrame:
    return events.dropDuplicatesWithinWatermark([key])


def with_static(events: DataFrame, patterns: DataFrame, on: str) -> DataFrame:
    """Stream-static join: the static side is re-planned for each batch and broadcast only under a checked size."""
    from textfactor.plans.rewrite import checked_broadcast

    return events.join(checked_broadcast(patterns), on)


def interval_pairs(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join of one user's events within an interval; both sides carry a watermark, so state is dropped."""
    a = left.select(F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_event"))
    b = right.select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_event"))
    return a.join(b, F.expr(f"a_user = b_user and b_ts >= a_ts and b_ts <= a_ts + interval {within} and a_event <> b_event"))


def to_parquet(stream: DataFrame, path: str, checkpoint: str, mode: str = "append"):
    """Run what is there once, then stop; restarts go on from the checkpoint."""
    return stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).format("parquet").start(path)


def to_memory(stream: DataFrame, name: str, mode: str, checkpoint: str | None = None):
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).format("memory").queryName(name)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()


def to_batches(stream: DataFrame, path: str, checkpoint: str, mode: str = "append"):
    """Every batch in a folder of its own, so a batch that is run again replaces itself; run once over what is there."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(write).start()


def _numbered(spark: SparkSession, path: str, prefix: str) -> list[int]:
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    system = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    names = [f.getPath().getName() for f in system.listStatus(folder)] if system.exists(folder) else []
    return sorted(int(n.removeprefix(prefix)) for n in names if n.startswith(prefix))


def read_batches(spark: SparkSession, path: str, schema_, mode: str = "append") -> DataFrame:
    """What to_batches wrote: all batches, or in complete mode the last one, which holds everything."""
    numbers = _numbered(spark, path, "batch=")
    if not numbers:
        return spark.createDataFrame([], schema_)
    wanted = numbers[-1:] if mode == "complete" else numbers
    return spark.read.schema(schema_).parquet(*(f"{path}/batch={n}" for n in wanted))


def newest_version(spark: SparkSession, path: str) -> DataFrame:
    """The table that merge_into left."""
    return spark.read.parquet(f"{path}/v{_numbered(spark, path, 'v')[-1]}")


def merge_into(stream: DataFrame, path: str, keys: list[str], checkpoint: str):
    """Upsert by foreachBatch: each batch writes a version of the table in which its rows replace those with equal keys."""

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        try:
            old = spark.read.parquet(f"{path}/v{number - 1}")
            batch = old.join(batch.select(*keys), keys, "left_anti").unionByName(batch) if number else batch
        except Exception:
            if number:
                raise
        batch.write.mode("overwrite").parquet(f"{path}/v{number}")

    return stream.writeStream.outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(merge).start()
