"""The thin opN queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exact_dedup, html_text, langid, licenses, media, packing, pieces, resampling, simhash, url_filter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of equal texts of ``documents``; the largest doc_id of each stays."""
    rows = exact_dedup.content_groups(_table(spark, sf_dir, "documents"), keep="largest")
    return rows.select(F.col("id").alias("doc_id"), "keep_id", "group_size", F.col("kept"), F.col("sha").alias("text_sha256"))


OP1_SQL = """
with n as (
  select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from documents
)
select doc_id, max(doc_id) over (partition by t) as keep_id, count(*) over (partition by t) as group_size,
  row_number() over (partition by t order by doc_id desc) = 1 as kept, sha256(t) as text_sha256
from n
"""

#: Entry (host and path prefix) and verdict.
URL_RULES = (("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block"))
#: Parts of host names that say spam, adverts, tracking, gambling, pills, smut or fraud.
BLOCKED_WORDS = tuple("ads adserver banner bet bets betting casino gambling lottery malware phishing pills poker porn scam spam track tracker tracking viagra warez xxx".split())


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdict on every URL of ``pages``: the rules, else block for the hosts that are named so, else allow."""
    pages = _table(spark, sf_dir, "pages")
    rows = url_filter.filter_urls(pages, url_filter.UrlRules(URL_RULES), url_filter.hosts_named(pages, BLOCKED_WORDS))
    return rows.select(F.col("id").alias("page_id"), "host", "path", "rule", "verdict")


def _op2_sql() -> str:
    values = ", ".join(f"('{s}', '{s.split('/', 1)[0]}', '/{s.split('/', 1)[1]}', '{v}')" for s, v in URL_RULES)
    blocked = "regexp_matches(host, '(^|[.-])(" + "|".join(BLOCKED_WORDS) + ")([.-]|$)')"
    return f"""
with rules(rule, rhost, rpath, verdict) as (values {values}),
cutoff as (
  select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages
),
parts as (
  select row_number() over () as r, page_id,
    translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) as path
  from cutoff
),
fit as (
  select p.r, arg_max(rule, length(rule)) as rule, arg_max(verdict, length(rule)) as verdict
  from parts p join rules on (p.host = rhost or p.host like '%.' || rhost) and starts_with(p.path, rpath) group by p.r
)
select page_id, host, path, fit.rule, coalesce(fit.verdict, case when {blocked} then 'block' else 'allow' end) as verdict
from parts left join fit using (r)
"""


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Importance weight, sampling key and selection of every document; target: labelled quality 1."""
    docs = _table(spark, sf_dir, "documents")
    return resampling.resample(docs, resampling.fit(docs, _table(spark, sf_dir, "labels")), keep=["doc_id"])


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string")) % 4 == 2


def language_model(docs: DataFrame) -> langid.Model:
    import public_tokenizers as known

    return langid.fit(docs, langid.public_pieces(known.path("piece_bpe_32k.model")), train=~held_out())


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every document by a model of those that are not held out."""
    docs = _table(spark, sf_dir, "documents")
    return langid.predict(docs, language_model(docs), keep=["doc_id"]).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and near-duplicate group of every document."""
    rows = simhash.near_groups(_table(spark, sf_dir, "documents"), size=4, distance=4)
    return rows.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op6_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The four best segmentations of every document."""
    import public_tokenizers as known

    return pieces.segment_documents(_table(spark, sf_dir, "documents"), known.path("piece_bpe_32k.model"), n=4).withColumnRenamed("id", "doc_id")


def op7_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text stored as a baseline JPEG and read back."""
    return media.media_columns(_table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in as few sequences of at most 1024 tokens as the rule gives: no other capacity is tighter."""
    import public_tokenizers as known

    pieces = packing.token_pieces(_table(spark, sf_dir, "documents"), known.path("byte_bpe_50k.json"), ranks_path=known.path("byte_bpe_50k.tiktoken"), pattern=known.PATTERN, end_id=2, width=1024)
    return packing.pack(pieces, packing.Capacity(tokens=1024, documents=1024, attention=1024**2)).withColumnRenamed("id", "doc_id")


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licences of ``documents`` as files ``source/lang/doc_id`` of a tree: the table has no paths of its own."""
    docs = _table(spark, sf_dir, "documents").withColumn("path", F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string")))
    return licenses.scan(docs, id_col="doc_id").withColumnRenamed("id", "doc_id")


def op10_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    return html_text.extract(_table(spark, sf_dir, "pages")).withColumnRenamed("id", "page_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_exact_dedup, op2_url_filter, op3_quality, op4_language, op5_simhash, op6_sentencepiece, op7_media, op8_packing, op9_licenses, op10_html)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_dedup": OP1_SQL, "op2_url_filter": _op2_sql()}
