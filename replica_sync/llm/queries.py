"""Queries of the operators of this folder, each over its whole table, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from replica_sync.llm import bpe, html_extract, jaccard_join, lm_score, media_avi, mixing, quality_nb, quality_rules, secret_scan, token_files


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op2_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_score.score_texts(_docs(spark, sf_dir))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.similar_documents(_docs(spark, sf_dir))


def op4_quality_nb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_nb.score_quality(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_texts(_docs(spark, sf_dir))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_sources(_docs(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_files_round_trip(_docs(spark, sf_dir))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge_quality(_docs(spark, sf_dir)).drop("posterior")


def op9_media_avi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_avi.media_digests(media_avi.store_media(_docs(spark, sf_dir)))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan_secrets(_docs(spark, sf_dir)).drop("blob")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}
    return dict(sorted(found.items(), key=lambda x: int(x[0][2:].split("_")[0])))


JACCARD_SQL = r"""
with recursive words as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as ws from documents
), shingles as (
  select distinct doc_id, array_to_string(ws[i:i + 2], ' ') as shingle from words, lateral (select unnest(range(1, greatest(len(ws) - 2, 1) + 1)) as i) where len(ws) > 0
), sizes as (
  select doc_id, count(*) as n from shingles group by 1
), common as (
  select a.doc_id as x, b.doc_id as y, count(*) as both_ from shingles a join shingles b on a.shingle = b.shingle and a.doc_id < b.doc_id group by 1, 2
), links as (
  select x, y from common join sizes p on p.doc_id = x join sizes q on q.doc_id = y where 100 * both_ >= 90 * (p.n + q.n - both_)
), edges as (
  select x, y from links union all select y, x from links
), reached as (
  select doc_id as node, doc_id as root from documents union select y, root from reached join edges on x = node
)
select d.doc_id, coalesce(n, 0) as n_shingles, (select min(root) from reached where node = d.doc_id) as component_id from documents d left join sizes s on s.doc_id = d.doc_id
"""

MIXING_SQL = r"""
with sized as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as size, ('0x' || substr(md5('17#' || doc_id), 1, 12))::bigint as key from documents
), sources as (
  select source, sum(size)::bigint as source_size, [5, 2, 1][(row_number() over (order by source nulls last) - 1) % 3 + 1] as weight from sized group by 1
), ranked as (
  select *, 3 * source_size as cap, row_number() over w as place, coalesce(sum(3 * source_size) over b, 0) as capped, coalesce(sum(weight) over b, 0) as passed, sum(source_size) over () as everything, sum(weight) over () as weights
  from sources window w as (order by 3 * source_size / weight, weight, source nulls last), b as (order by 3 * source_size / weight, weight, source nulls last rows between unbounded preceding and 1 preceding)
), levels as (
  select *, ((everything - capped)::bigint / (weights - passed)::bigint) as level from ranked
), targets as (
  select source, source_size, least(cap::double, coalesce((select min_by(level, place) from levels where level * weight <= cap) * weight, cap)) as target from levels
), shares as (
  select *, floor(case when source_size > 0 then target / source_size else 0 end) as whole from targets
), ordered as (
  select d.*, source_size, target, whole, target - whole * source_size as part, sum(size) over (partition by d.source order by key, doc_id nulls first, size rows unbounded preceding) - size as ahead
  from sized d join shares s on d.source is not distinct from s.source
)
select doc_id, size::bigint as size, source_size, target, least(whole::bigint * size + greatest(0, least(size, round(part)::bigint - ahead)), 3 * size)::bigint as taken from ordered
"""


def oracle_sql() -> dict[str, str]:
    """The other operators learn models, merge bytes or write files: they are tested against plain Python and libraries."""
    return {"op3_jaccard_join": JACCARD_SQL, "op6_mixing": MIXING_SQL}
