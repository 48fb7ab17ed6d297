"""The ten operators as queries over their whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import best_fit, chat_snapshots, dart_minhash, language_crf, license_scan, quality_cascade, temperature_mix, tiered_shards, tiff_media, warc_revisit
from .common import table


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir, "documents")).drop("spans")


def op2_tiered_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = tiered_shards.compacted(table(spark, sf_dir, "documents"), tiered_shards.Settings(target_bytes=32 << 20))
    store.vacuum()
    return store.placement("doc_id")


def op3_temperature_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return temperature_mix.mixture(table(spark, sf_dir, "documents"))


def op4_language_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return language_crf.identify(docs, language_crf.learn(docs))


def op5_tiff_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tiff_media.text_media(table(spark, sf_dir, "documents"))


def op6_warc_revisit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_revisit.pages_by_archives(table(spark, sf_dir, "pages"))


def op7_dart_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dart_minhash.classes(table(spark, sf_dir, "documents"))


def op8_quality_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_cascade.judge(table(spark, sf_dir, "documents"))


def op9_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return best_fit.pack_documents(table(spark, sf_dir, "documents"))


def op10_chat_snapshots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_snapshots.render(table(spark, sf_dir, "conversations"))


OPERATORS = (
    op1_license_scan, op2_tiered_shards, op3_temperature_mix, op4_language_crf, op5_tiff_media,
    op6_warc_revisit, op7_dart_minhash, op8_quality_cascade, op9_best_fit, op10_chat_snapshots,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in OPERATORS}


def oracle_sql() -> dict[str, str]:
    return {
        "op6_warc_revisit": """
            with p as (select page_id, coalesce(html, '') as html from pages),
            q as (select page_id, strlen(html) as n, sha256(html) as d from p),
            f as (select d, min(page_id) as first_id from q where n >= 100 group by d)
            select q.page_id, q.n as payload_bytes, q.d as payload_digest,
              case when q.n >= 100 and q.page_id <> f.first_id then 'revisit' else 'response' end as record_type,
              case when q.n >= 100 and q.page_id <> f.first_id then f.first_id end as refers_to
            from q left join f on q.d = f.d and q.n >= 100
        """,
        "op10_chat_snapshots": r"""
            with t as (
              select conv_id, row_number() over (partition by conv_id order by turn, role, text) as pos,
                '<|' || coalesce(role, 'unknown') || '|>' || chr(10) || coalesce(text, '') || chr(10) || '<|end|>' || chr(10) as part
              from conversations where conv_id is not null),
            p as (select conv_id, pos, string_agg(part, '') over (partition by conv_id order by pos) as s from t),
            w as (select conv_id, max(pos) as n, arg_max(s, pos) as s from p group by conv_id),
            o as (select n, s, min(conv_id) as conv_id, count(*) as copies from w group by n, s),
            inner_ as (select distinct p.pos, p.s from p join w on p.conv_id = w.conv_id where p.pos < w.n)
            select conv_id, n as n_turns, copies, s as rendered
            from o where not exists (select 1 from inner_ i where i.pos = o.n and i.s = o.s)
        """,
    }
