"""Queries over the whole tables, one per operator, and their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import decontaminate, katz, mixing, quality_model, quality_rules, simhash, substring_dedup, token_files, url_filters, warc
from .common import table


def vocabulary_path() -> str:
    """The tokenizer file the production queries use."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_katz_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz.score(table(spark, sf_dir, "documents", "doc_id", "text"), least_count=1)


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.round_trip(table(spark, sf_dir, "documents", "doc_id", "text"), vocabulary_path())


def op3_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_model.classify(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "quality"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(substring_dedup.remove_repeats(table(spark, sf_dir, "documents", "doc_id", "text"), longest=None))


def op5_cube_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.digest(mixing.mix(table(spark, sf_dir, "documents", "doc_id", "source", "text")))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.search(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text")))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    crf = quality_rules.train(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return quality_rules.judge(docs, crf).select("doc_id", *quality_rules.COUNTS, "base_failed", "kept", "content_words")


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.digest(warc.round_trip(table(spark, sf_dir, "pages", "page_id", "url", "html"), with_payload=False))


def op10_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filters.judge(table(spark, sf_dir, "pages", "page_id", "url"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_katz_score, op2_token_files, op3_quality_model, op4_substring_dedup, op5_cube_mixing, op6_simhash, op7_decontaminate, op8_quality_rules, op9_warc, op10_url_filters, pipeline)}

_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLES = {
    "op4_substring_dedup": r"""
with d as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') w from documents),
win as (select doc_id, i, list_slice(w, i, i + 12) g from (select doc_id, w, unnest(range(1, len(w) - 11)) i from d where len(w) >= 13)),
low as (select g, min(doc_id) low from win group by g having min(doc_id) < max(doc_id)),
gone as (select distinct doc_id, i + k as j from (select doc_id, i from win join low using (g) where low < doc_id), range(0, 13) t(k)),
word as (select doc_id, w[j] x, j from (select doc_id, w, unnest(range(1, len(w) + 1)) j from d)),
kept as (select doc_id, string_agg(x, ' ' order by j) t, count(*) n from word anti join gone using (doc_id, j) group by doc_id)
select d.doc_id, len(w)::bigint n_words, (len(w) - coalesce(n, 0))::bigint n_removed, sha256(coalesce(t, '')) kept_sha256 from d left join kept using (doc_id)""",
    "op7_decontaminate": rf"""
with d as (select doc_id, regexp_extract_all({_LOWER.format("coalesce(text, '')")}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from documents),
b as (select item_id, regexp_extract_all({_LOWER.format("coalesce(text, '')")}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from benchmark),
p as (select distinct item_id, list_slice(w, i, i + n - 1) g, n from (select item_id, w, least(len(w), 13) n, unnest(range(1, len(w) - least(len(w), 13) + 2)) i from b where len(w) > 0)),
dw as (select doc_id, i, list_slice(w, i, i + n - 1) g, n from (select doc_id, w, n, unnest(range(1, len(w) - n + 2)) i from d, (select distinct n from p) where len(w) >= n)),
f as (select doc_id, i, n, item_id from dw join p using (g, n)),
h as (select doc_id, count(distinct i + k) n_hit from (select distinct doc_id, i, n from f), range(0, 13) t(k) where k < n group by doc_id),
m as (select doc_id, count(distinct item_id) n_items, string_agg(distinct item_id::varchar, ',' order by item_id::varchar) ids from f group by doc_id)
select d.doc_id, len(w)::bigint n_words, coalesce(n_hit, 0)::bigint n_hit, coalesce(n_items, 0)::bigint n_items, sha256(coalesce(ids, '')) items_sha256,
  coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(w) contaminated from d left join h using (doc_id) left join m using (doc_id)""",
    "op9_warc": r"""
with p as (select page_id, coalesce(html, '') h, sha1(coalesce(html, '')) x from pages),
r as (select page_id, strlen(h)::bigint payload_bytes, x, max(page_id) over (partition by x) head from p)
select page_id, payload_bytes, list_aggregate(list_transform(range(0, 32), lambda i:
  substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ((((instr('0123456789abcdef', substr(x, 5 * i // 4 + 1, 1)) - 1) * 16 + instr('0123456789abcdef', substr(x, 5 * i // 4 + 2, 1)) - 1) >> (3 - 5 * i % 4)) & 31)::bigint + 1, 1)), 'string_agg', '') payload_digest,
  case when page_id = head then 'response' else 'revisit' end record_type, case when page_id <> head then head end refers_to from r""",
    "op10_url_filters": rf"""
with u as (select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end rest from pages),
s as (select page_id, {_LOWER.format("regexp_extract(rest, '^([^/?#]*)', 1)")} host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) path from u),
r(verdict, h, p) as (values ('allow', 'com', '/'), ('block', 'example.com', '/en/'), ('allow', 'www.example.com', '/en/'), ('block', 'net', '/es/'), ('block', 'net', '/fr/')),
f as (select page_id, h || p as rule, verdict, row_number() over (partition by page_id order by length(h || p) desc) k from s join r on (host = h or ends_with(host, '.' || h)) and starts_with(path, p))
select s.page_id, host, path, rule, coalesce(verdict, 'allow') verdict from s left join (select * from f where k = 1) f using (page_id)""",
}
