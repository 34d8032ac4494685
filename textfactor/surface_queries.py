"""Registered queries of the SQL surface, the readers and sinks, and the streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.operators import rows
from textfactor.operators.scratch import Scratch
from textfactor.queries import ENDS, PAIRS, RUN_STEPS, SEQ_TEXTS, SEQS, SUFFIX_STEPS, greedy
from textfactor.registry import query
from textfactor.sources import tables as src
from textfactor.streaming import streams


def _functions(spark: SparkSession) -> None:
    from textfactor.functions.udfs import register_all  # their types can only be read while a session is there

    register_all(spark)


def _views(spark: SparkSession, d: str) -> None:
    _functions(spark)
    src.event_sequences(spark, d).createOrReplaceTempView("tf_seqs")
    src.neighbour_pairs(spark, d).createOrReplaceTempView("tf_pairs")


# --- functions called from SQL -------------------------------------------------------------------------------------------------
_SPLIT = "levenshtein(left(a, cast(length(a) // 2 as int)), left(b, cast(length(b) // 2 as int))) + levenshtein(substr(a, cast(length(a) // 2 as int) + 1), substr(b, cast(length(b) // 2 as int) + 1)) = levenshtein(a, b)"


@query(f"with {PAIRS}, ga as (select distinct a_id, b_id, substr(a, cast(i as int), cast(l as int)) as g from pairs, lateral (select unnest(range(1, length(a) + 1)) as i), lateral (select unnest(range(1, length(a) - i + 2)) as l)), common as (select p.a_id, cast(max(case when contains(p.b, g) then length(g) else 0 end) as bigint) as len from pairs p join ga on p.a_id = ga.a_id group by p.a_id) select pairs.a_id, levenshtein(a, b) as distance, case when levenshtein(a, b) <= 45 then levenshtein(a, b) else -1 end as bounded, common.len as lcs_len, {_SPLIT} as is_anchor from pairs join common on common.a_id = pairs.a_id")
def sql_pair_functions(spark, d):
    _views(spark, d)
    return spark.sql("select a_id, tf_edit_distance(a, b) as distance, tf_edit_bounded(a, b, 45) as bounded, tf_lcs_len(a, b) as lcs_len, tf_is_anchor(a, b, cast(length(a) div 2 as int), cast(length(b) div 2 as int)) as is_anchor from tf_pairs")


_DELTA = "grams as (select id, q, count(distinct substr(t, cast(p as int), cast(q as int))) as dq from texts, lateral (select unnest(range(1, length(t) + 1)) as q), lateral (select unnest(range(1, length(t) - q + 2)) as p) group by id, q), deltas as (select id, round(max(dq / q), 6) as delta from grams group by id)"
_MIDDLE = "substr(t, cast(length(t) // 2 as int) + 1)"


@query(f"with recursive {SEQ_TEXTS}, {greedy('f')}, {greedy('g', False)}, {RUN_STEPS}, {_DELTA} select texts.id as user_id, z, z_one, r, delta, cast(coalesce(list_max(list_filter(range(1, length({_MIDDLE}) + 1), lambda l: left(t, cast(l as int)) = left({_MIDDLE}, cast(l as int)))), 0) as bigint) as extension from texts join (select id, count(*) as z from f group by id) x on x.id = texts.id join (select id, count(*) as z_one from g group by id) y on y.id = texts.id join (select id, count(distinct run_no) as r from numbered group by id) n on n.id = texts.id join deltas on deltas.id = texts.id")
def sql_text_functions(spark, d):
    _views(spark, d)
    return spark.sql("select user_id, tf_lz_size(s) as z, tf_grid_size(s, 1) as z_one, tf_bwt_runs(s) as r, round(tf_delta(s), 6) as delta, tf_lce(s, 0, cast(length(s) div 2 as int)) as extension from tf_seqs")


@query(ENDS.format(seqs=SEQS, cands="ends"))
def sql_phrase_end_function(spark, d):
    _views(spark, d)
    return spark.sql("select user_id, tf_lz_end_size(s) as phrases from tf_seqs")


@query(f"with recursive {SEQ_TEXTS}, {greedy()}, {RUN_STEPS}, {_DELTA} select texts.id as user_id, length(t) as n, z, r, delta from texts join (select id, count(*) as z from f group by id) x on x.id = texts.id join (select id, count(distinct run_no) as r from numbered group by id) y on y.id = texts.id join deltas on deltas.id = texts.id")
def sql_profile_struct(spark, d):
    _views(spark, d)
    return spark.sql("select user_id, p.n, p.z, p.r, round(p.delta, 6) as delta from (select user_id, tf_profile(s) as p from tf_seqs)")


@query(f"with {PAIRS} select a_id, levenshtein(a, b) as distance, levenshtein(a, b) as edits, true as charged from pairs where a <> b")
def sql_solve_struct(spark, d):
    _views(spark, d)
    return spark.sql("select a_id, r.distance, r.edits, r.q_tokens > 0 and r.t_tokens > 0 as charged from (select a_id, tf_solve(a, b) as r from tf_pairs where a <> b)")


@query(f"with recursive {SEQ_TEXTS}, {greedy()}, {SUFFIX_STEPS} select 'phrases' as what, id as user_id, count(*) as n, cast(sum(len) as bigint) as total from f group by id union all select 'suffixes', id, count(*), cast(sum(rank - 1) as bigint) from ranks group by id")
def sql_table_functions(spark, d):
    """Phrases and suffixes as lateral tables."""
    _views(spark, d)
    return spark.sql("""select 'phrases' as what, user_id, count(*) as n, sum(len) as total from tf_seqs, lateral tf_phrases(s, 'lz77', 0) group by user_id
                        union all select 'suffixes', user_id, count(*), sum(rank) from tf_seqs, lateral tf_suffixes(s) group by user_id""")


_LOW = "low as (select id, pos, rank, min(rank) over (partition by id order by pos rows between unbounded preceding and 1 preceding) as m from ranks)"


@query(f"with {SEQ_TEXTS}, {RUN_STEPS}, {_LOW} select 'runs' as what, id as user_id, count(distinct run_no) as n from numbered group by id union all select 'lyndon', id, count(*) from low where m is null or rank < m group by id")
def sql_run_tables(spark, d):
    _views(spark, d)
    return spark.sql("select 'runs' as what, user_id, count(*) as n from tf_seqs, lateral tf_runs(s) group by user_id union all select 'lyndon', user_id, count(*) from tf_seqs, lateral tf_lyndon(s) group by user_id")


@query(f"with {PAIRS} select a_id, levenshtein(a, b) as edits from pairs where a <> b")
def sql_edit_table(spark, d):
    _views(spark, d)
    return spark.sql("select a_id, count(*) as edits from tf_pairs, lateral tf_edits(a, b) group by a_id")


@query(f"""with {PAIRS}, ga as (select a_id, a, b, substr(a, cast(i as int), cast(l as int)) as g, min(i) as i from pairs, lateral (select unnest(range(1, length(a) + 1)) as i), lateral (select unnest(range(1, length(a) - i + 2)) as l) group by 1, 2, 3, 4 having count(*) = 1),
both_ as (select *, instr(b, g) as j from ga where instr(b, g) > 0 and instr(substr(b, instr(b, g) + 1), g) = 0)
select a_id, count(*) as matches, cast(max(length(g)) as bigint) as longest from both_ where not (i > 1 and j > 1 and substr(a, cast(i - 1 as int), 1) = substr(b, j - 1, 1)) and not (i + length(g) <= length(a) and j + length(g) <= length(b) and substr(a, cast(i + length(g) as int), 1) = substr(b, cast(j + length(g) as int), 1)) group by a_id""")
def sql_match_table(spark, d):
    _views(spark, d)
    return spark.sql("select a_id, count(*) as matches, max(len) as longest from tf_pairs, lateral tf_mums(a, b) group by a_id")


@query(f"with recursive nations as (select n_regionkey, string_agg(n_name, chr(1) order by n_name) as t, min(n_name) as one, min(n_name) filter (where n_name <> (select min(n_name) from nation m where m.n_regionkey = nation.n_regionkey)) as two from nation group by n_regionkey), texts as (select n_regionkey as id, t from nations), {greedy()}, grams as (select n_regionkey, two, substr(one, cast(i as int), cast(l as int)) as g from nations, lateral (select unnest(range(1, length(one) + 1)) as i), lateral (select unnest(range(1, length(one) - i + 2)) as l)) select cast(z.id as bigint) as n_regionkey, z, lcs from (select id, count(*) as z from f group by id) z join (select n_regionkey, cast(max(case when contains(two, g) then length(g) else 0 end) as bigint) as lcs from grams group by n_regionkey) c on c.n_regionkey = z.id")
def sql_group_functions(spark, d):
    """Aggregates: phrases of a group's joined texts, and what its first two share."""
    _functions(spark)
    src.table(spark, d, "nation").createOrReplaceTempView("tf_nations")
    return spark.sql("select n_regionkey, tf_concat_size(n_name) as z, tf_lcs_group(n_name) as lcs from tf_nations group by n_regionkey")


# --- readers and sinks ---------------------------------------------------------------------------------------------------------
@query("select doc_id, text, lang, source, n_chars from documents")
def reader_json(spark, d):
    """Documents out as JSON lines and back under a fixed schema."""
    path = f"{Scratch(spark, 'json').root}/documents"
    src.table(spark, d, "documents").select("doc_id", "text", "lang", "source", "n_chars").write.json(path)
    return src.read_json(spark, path)


@query("select c_custkey, c_name, c_mktsegment from customer")
def reader_csv(spark, d):
    path = f"{Scratch(spark, 'csv').root}/customer"
    src.table(spark, d, "customer").select("c_custkey", "c_name", "c_mktsegment").write.option("header", True).option("escape", '"').csv(path)
    return src.read_csv(spark, path, "c_custkey long, c_name string, c_mktsegment string")


@query("select item_id, text from benchmark")
def reader_text_files(spark, d):
    """One text file per test item, read whole; the item's number comes from the path."""
    path = f"{Scratch(spark, 'files').root}/items"
    src.table(spark, d, "benchmark").select("item_id", "text").repartition(4, "item_id").write.partitionBy("item_id").text(path)
    found = src.read_text_files(spark, f"{path}/*/*.txt")
    return found.select(F.regexp_extract("path", "item_id=([0-9]+)", 1).cast("long").alias("item_id"), F.regexp_replace("text", "\n$", "").alias("text"))


@query(ENDS.format(seqs=SEQS, cands="ends"))
def sink_partitioned(spark, d):
    """Phrases of several schemes in one table partitioned by scheme; a reader of one scheme opens that folder only."""
    scratch, texts, out = Scratch(spark, "phrases"), src.event_sequences(spark, d), None
    for scheme in ("lz77", "nonoverlap", "lzend"):
        part = rows.factorize(texts, "s", ["user_id"], scheme).withColumn("scheme", F.lit(scheme))
        out = part if out is None else out.unionByName(part)
    src.write_partitioned(out, f"{scratch.root}/by-scheme", ["scheme"])
    return spark.read.parquet(f"{scratch.root}/by-scheme").where("scheme = 'lzend'").groupBy("user_id").agg(F.count(F.lit(1)).alias("phrases"))


# --- streams: each is run to its end and its sink read back --------------------------------------------------------------------
def _events(spark: SparkSession, d: str) -> DataFrame:
    return streams.file_stream(spark, f"{d}/events.parquet*")


def _drained(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    scratch = Scratch(spark, "stream")
    running = streams.to_batches(stream, f"{scratch.root}/out", f"{scratch.root}/checkpoint", mode)
    running.awaitTermination()
    return streams.read_batches(spark, f"{scratch.root}/out", stream.schema, mode)


@query("select user_id, date_trunc('day', ts) as start, string_agg(left(event_type, 1), '' order by ts, event_id) as s from events group by 1, 2")
def stream_daily_windows(spark, d):
    s = _drained(spark, streams.window_strings(streams.with_event_time(_events(spark, d))), "complete")
    return s.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "s")


@query("with w as (select *, time_bucket(interval 12 hours, ts) as b from events), spread as (select *, b as start from w union all select *, b - interval 12 hours from w) select user_id, start, string_agg(left(event_type, 1), '' order by ts, event_id) as s from spread group by user_id, start")
def stream_sliding_windows(spark, d):
    s = _drained(spark, streams.window_strings(streams.with_event_time(_events(spark, d)), "1 day", "12 hours"), "complete")
    return s.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "s")


@query("with g as (select *, case when ts < lag(ts) over w + interval 4 hours then 0 else 1 end as new from events window w as (partition by user_id order by ts)), n as (select *, sum(new) over (partition by user_id order by ts) as k from g) select user_id, min(ts) as start, string_agg(left(event_type, 1), '' order by ts, event_id) as s from n group by user_id, k")
def session_strings(spark, d):
    """Sessions that a gap of four hours ends."""
    e = src.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return streams.window_strings(e, "4 hours", session=True).select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "s")


@query("select user_id, count(distinct event_id) as n from events group by user_id")
def stream_dedup_counts(spark, d):
    twice = _events(spark, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return _drained(spark, streams.dedup(streams.with_event_time(twice)).select("user_id", "event_id"), "append").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query("select event_id, w.weight from events e join (values ('view', 1), ('click', 2), ('purchase', 5)) w(event_type, weight) on w.event_type = e.event_type")
def stream_static_join(spark, d):
    weights = spark.createDataFrame([("view", 1), ("click", 2), ("purchase", 5)], "event_type string, weight int")
    return _drained(spark, streams.with_static(_events(spark, d), weights, "event_type").select("event_id", "weight"), "append")


@query("select a.event_id as a_event, b.event_id as b_event from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour and a.event_id <> b.event_id")
def stream_interval_pairs(spark, d):
    a, b = streams.with_event_time(_events(spark, d)), streams.with_event_time(_events(spark, d))
    return _drained(spark, streams.interval_pairs(a, b).select("a_event", "b_event"), "append")


@query(f"with recursive {SEQ_TEXTS}, {greedy()} select id as user_id, cast(phrase_no as bigint) as phrase_no, cast(start - 1 as bigint) as start, cast(len as bigint) as len from f where start + len - 1 < length(t) or src = 0")
def stream_phrases(spark, d):
    """Final phrases of growing sequences; the one that is still open at the end is not emitted."""
    return _drained(spark, streams.incremental_phrases(_events(spark, d)), "append")


@query(f"with {SEQS} select user_id, case when levenshtein(s, repeat('vcsep', 13)) <= 60 then levenshtein(s, repeat('vcsep', 13)) else -1 end as distance from seqs")
def stream_reference_distance(spark, d):
    rows_ = _drained(spark, streams.distance_to_reference(_events(spark, d), "vcsep" * 13, 60), "update")
    return rows_.groupBy("user_id").agg(F.max_by("distance", "n").alias("distance"))


@query("select user_id, count(*) as n from events group by user_id")
def stream_merged_counts(spark, d):
    """Counts per user, merged into versions of a table batch by batch."""
    scratch = Scratch(spark, "merge")
    counts = _events(spark, d).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    streams.merge_into(counts, f"{scratch.root}/table", ["user_id"], f"{scratch.root}/checkpoint").awaitTermination()
    return streams.newest_version(spark, f"{scratch.root}/table")
