"""Streams against their batch."""

from pyspark.sql import functions as F

from textfactor.kernels import edit, lz
from textfactor.sources import tables
from textfactor.streaming import streams


def _files(spark, sf, tmp_path, parts=3):
    events = tables.table(spark, sf, "events").orderBy("ts", "event_id").toPandas()
    folder = tmp_path / "in"
    folder.mkdir()
    size = -(-len(events) // parts)
    for k in range(parts):
        events.iloc[k * size : (k + 1) * size].to_parquet(folder / f"{k}.parquet", coerce_timestamps="us", allow_truncated_timestamps=True)
    return str(folder)


def _drain(query):
    query.awaitTermination(120)
    assert query.exception() is None


def test_incremental_phrases_equal_batch(spark, sf, tmp_path):
    stream = streams.file_stream(spark, _files(spark, sf, tmp_path))
    _drain(streams.to_memory(streams.incremental_phrases(stream), "phrases", "append", str(tmp_path / "cp")))
    got: dict[int, list] = {}
    for r in spark.table("phrases").orderBy("user_id", "phrase_no").collect():
        got.setdefault(r.user_id, []).append((r.start, r.len))
    for r in tables.event_sequences(spark, sf).collect():
        want = [p[:2] for p in lz.lz77(r.s)]
        mine = got.get(r.user_id, [])
        assert mine == want[: len(mine)] and len(mine) >= len(want) - 1


def test_distance_to_reference(spark, sf, tmp_path):
    reference, k = "vcsep" * 13, 60
    stream = streams.file_stream(spark, _files(spark, sf, tmp_path))
    _drain(streams.to_memory(streams.distance_to_reference(stream, reference, k), "distances", "update", str(tmp_path / "cp")))
    last = {r.user_id: r.distance for r in spark.table("distances").groupBy("user_id").agg(F.max_by("distance", "n").alias("distance")).collect()}
    for r in tables.event_sequences(spark, sf).collect():
        d = edit.ed_dp(r.s, reference)
        assert last[r.user_id] == (d if d <= k else -1)


def test_closed_windows_equal_batch(spark, sf, tmp_path):
    stream = streams.with_event_time(streams.file_stream(spark, _files(spark, sf, tmp_path)))
    out, cp = str(tmp_path / "out"), str(tmp_path / "cp")
    _drain(streams.to_parquet(streams.window_strings(stream), out, cp))
    got = {(r.user_id, r.start): r.s for r in spark.read.parquet(out).collect()}
    batch = {(r.user_id, r.start): r.s for r in streams.window_strings(tables.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))).collect()}
    assert got and all(batch[k] == v for k, v in got.items())
    _drain(streams.to_parquet(streams.window_strings(stream), out, cp))  # a restart finds nothing new
    assert spark.read.parquet(out).count() == len(got)


def test_dedup_and_merge(spark, sf, tmp_path):
    stream = streams.with_event_time(streams.file_stream(spark, _files(spark, sf, tmp_path)))
    _drain(streams.to_memory(streams.dedup(stream), "unique_events", "append", str(tmp_path / "cp1")))
    assert spark.table("unique_events").count() == tables.table(spark, sf, "events").count()
    counts = streams.file_stream(spark, str(tmp_path / "in")).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    _drain(streams.merge_into(counts, str(tmp_path / "merged"), ["user_id"], str(tmp_path / "cp2")))
    newest = max(int(p.name[1:]) for p in (tmp_path / "merged").iterdir() if p.name.startswith("v"))
    assert spark.read.parquet(str(tmp_path / "merged" / f"v{newest}")).agg(F.sum("n")).first()[0] == tables.table(spark, sf, "events").count()
