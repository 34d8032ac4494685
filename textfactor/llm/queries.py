"""The registered queries of the training-data operators: thin digests over the operators' own results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.llm import ann_search, contamination, langid, line_dedup, lm_score, ngram_join, packing, secrets, token_count, url_filter
from textfactor.llm.common import table


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.token_counts(table(spark, sf_dir, "documents"), token_count.default_model())


def op2_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    found, _ = ngram_join.near_duplicates(table(spark, sf_dir, "documents"), whole_links=False)
    return found.select("doc_id", "n_shingles", "component_id")


def op2_ngram_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    found, _ = ngram_join.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_shingles", "component_id", "n_links")


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann_search.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = secrets.scan(docs, secrets.train(docs))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans", "n_random")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    known = langid.train(docs.where(langid.in_training()).select("doc_id", "text", "lang"))
    found = langid.classify(docs.select("doc_id", "text"), known)
    return found.select("doc_id", (~langid.in_training()).alias("held_out"), "lang_pred", "score", "margin", "accepted")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), packing.default_tokenizer()).drop("piece_ids")


def op9_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    held_out = F.crc32(F.col("doc_id").cast("string")) % 7 == 2
    scored = lm_score.score(docs, ~held_out)
    return scored.select("doc_id", held_out.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = line_dedup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


# What SQL can express of queries whose other columns it can't.
def op1_text_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op1_token_counts(spark, sf_dir).select("doc_id", "n_bytes")


def op3_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", F.when(F.col("rule").isNotNull(), F.col("verdict")).alias("rule_verdict"))


def op6_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_secret_scan(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


def op9_base_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op9_lm_scoring(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 6).alias("base_score"))


QUERIES = {f.__name__: f for f in (op1_token_counts, op2_ngram_join, op2_ngram_links, op3_url_filter, op4_decontamination, op5_nearest_neighbours, op6_secret_scan, op7_language_id, op8_packing, op9_lm_scoring, op10_line_dedup, op1_text_bytes, op3_url_rules, op6_base_counts, op9_base_scores)}

_EITHER_CASE = "|".join("".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in name) for name in ("password", "passwd", "secret", "token", "api_?key"))

ORACLES = {
    "op1_text_bytes": "select doc_id, cast(coalesce(strlen(text), 0) as bigint) as n_bytes from documents",
    "op3_url_rules": r"""
with cut as (select page_id, case when instr(coalesce(url, ''), '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
parts as (select page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host, regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) as path from cut),
rules(verdict, name, prefix) as (values ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/'))
select page_id, host, path, arg_max(name || prefix, length(name || prefix)) as rule, arg_max(verdict, length(name || prefix)) as rule_verdict
from parts left join rules on (host = name or ends_with(host, '.' || name)) and starts_with(path, prefix) group by page_id, host, path""",
    "op6_base_counts": rf"""
select doc_id, cast(len(list_filter(regexp_extract_all(coalesce(text, ''), '({_EITHER_CASE})["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 2), lambda v: length(v) >= 12)) as bigint) as n_assign,
       cast(len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda v: length(v) >= 18)) as bigint) as n_access,
       cast(len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda v: length(v) >= 16)) as bigint) as n_hex
from documents""",
    "op9_base_scores": r"""
with crc as (
  select doc_id, text, xor(list_reduce(list_concat([4294967295::bigint], list_transform(string_split(cast(doc_id as varchar), ''), lambda c: cast(ord(c) as bigint))),
    lambda c, b: list_reduce([xor(c, b), 0::bigint, 0::bigint, 0::bigint, 0::bigint, 0::bigint, 0::bigint, 0::bigint, 0::bigint], lambda x, k: case when (x & 1::bigint) = 1 then xor(x >> 1, 3988292384::bigint) else x >> 1 end)), 4294967295::bigint) as crc
  from documents),
tokens as (
  select doc_id, crc % 7 = 2 as held_out, unnest(list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), ' ')) as w from crc),
counts as (select w, count(*) as c from tokens where not held_out group by w),
sums as (select cast(sum(c) as bigint) as n, count(*) as v from counts)
select doc_id, held_out, count(*) as n_tokens, count(c) as n_known, any_value(n) as train_tokens, round(sum(log10((coalesce(c, 0) + 1) / (n + 1.0 * (v + 1)))), 6) as base_score
from tokens left join counts on counts.w = tokens.w, sums group by doc_id, held_out""",
    "op2_ngram_join": r"""
with recursive words as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
grams as (
  select distinct doc_id, array_to_string(w[i : i + 4], ' ') as g
  from words, lateral (select unnest(range(1, greatest(len(w) - 4, 1) + 1)) as i) where len(w) > 0),
sizes as (select doc_id, count(*) as n from grams group by doc_id),
links as (
  select x.doc_id as a, y.doc_id as b from grams x join grams y on x.g = y.g and x.doc_id <> y.doc_id
  join sizes sx on sx.doc_id = x.doc_id join sizes sy on sy.doc_id = y.doc_id
  group by x.doc_id, y.doc_id, sx.n, sy.n having 100 * count(*) >= 80 * (sx.n + sy.n - count(*))),
reach as (select doc_id, doc_id as other from documents union select r.doc_id, l.b from reach r join links l on r.other = l.a),
labels_ as (select doc_id, min(other) as component_id from reach group by doc_id)
select d.doc_id, coalesce(s.n, 0) as n_shingles, c.component_id
from documents d left join sizes s on s.doc_id = d.doc_id join labels_ c on c.doc_id = d.doc_id""",
    "op2_ngram_links": r"""
with recursive words as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
grams as (
  select distinct doc_id, array_to_string(w[i : i + 4], ' ') as g
  from words, lateral (select unnest(range(1, greatest(len(w) - 4, 1) + 1)) as i) where len(w) > 0),
sizes as (select doc_id, count(*) as n from grams group by doc_id),
links as (
  select x.doc_id as a, y.doc_id as b from grams x join grams y on x.g = y.g and x.doc_id <> y.doc_id
  join sizes sx on sx.doc_id = x.doc_id join sizes sy on sy.doc_id = y.doc_id
  group by x.doc_id, y.doc_id, sx.n, sy.n having 100 * count(*) >= 80 * (sx.n + sy.n - count(*))),
reach as (select doc_id, doc_id as other from documents union select r.doc_id, l.b from reach r join links l on r.other = l.a),
labels_ as (select doc_id, min(other) as component_id from reach group by doc_id),
degrees as (select a, count(*) as n_links from links group by a)
select d.doc_id, coalesce(s.n, 0) as n_shingles, c.component_id, coalesce(g.n_links, 0) as n_links
from documents d left join sizes s on s.doc_id = d.doc_id join labels_ c on c.doc_id = d.doc_id left join degrees g on g.a = d.doc_id""",
    "op10_line_dedup": r"""
with lines as (
  select doc_id, i as line_no, parts[i] as line, lcase.k as key
  from (select doc_id, string_split(coalesce(text, ''), chr(10)) as parts from documents) d,
       lateral (select unnest(range(1, len(parts) + 1)) as i) r,
       lateral (select translate(trim(parts[i], ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                                 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as k) lcase),
owners as (select key, min(doc_id) as owner from lines where length(key) >= 10 group by key having count(distinct doc_id) > 1),
marked as (select l.*, coalesce(o.owner < l.doc_id, false) as gone from lines l left join owners o on l.key = o.key)
select doc_id, cast(count(*) as bigint) as n_lines, cast(count(*) filter (where gone) as bigint) as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by line_no) filter (where not gone), '')) as kept_sha256
from marked group by doc_id""",
}
