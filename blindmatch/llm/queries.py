"""Queries over the given tables for the operators of this subpackage, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blindmatch.llm import bpe, exact_dedup, html_wrappers, mixture, ngram_join, quality, secret_scan, substring_dedup, url_filter, warc

#: Days over which the derived list history and fetch days run.
DAYS = 360


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _digest_number(text, digits: int, modulus: int):
    return F.pmod(F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long"), F.lit(modulus)).cast("int")


def list_history(pages: DataFrame) -> DataFrame:
    """Dated entries derived from the hosts of ``pages`` and their parent domains: three a key, by digest."""
    keys = pages.select(F.explode(url_filter.keys_of(F.col("url"))).alias("list_key")).where("not contains(list_key, '/')").distinct()
    dated = keys.select("list_key", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("v"))
    tag = F.concat_ws(":", "list_key", F.col("v").cast("string"))
    dated = dated.withColumn("day", _digest_number(F.concat(F.lit("d:"), tag), 6, DAYS))
    dated = dated.withColumn("kind", _digest_number(F.concat(F.lit("a:"), tag), 6, 3))
    return dated.select("list_key", "day", F.when(F.col("kind") == 0, F.lit("add")).otherwise(F.lit("remove")).alias("action"))


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    day = _digest_number(F.concat(F.lit("f:"), F.col("page_id").cast("string")), 6, DAYS)
    return url_filter.judge_urls(pages.withColumn("fetch_day", day), list_history(pages))


SQL_OP1 = rf"""
WITH seen AS (
  SELECT page_id, url, CAST(CAST('0x' || substr(md5('f:' || CAST(page_id AS VARCHAR)), 1, 6) AS BIGINT) % {DAYS} AS INTEGER) AS fetch_day,
    lower(regexp_extract(coalesce(url, ''), '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)', 1)) AS host,
    regexp_extract(coalesce(url, ''), '^[^/]*//[^/?#]*/([^/?#]+)', 1) AS segment
  FROM pages),
labelled AS (SELECT *, string_split(host, '.') AS labels FROM seen WHERE host <> ''),
hosts AS (
  SELECT DISTINCT page_id, url, fetch_day, array_to_string(labels[i:], '.') AS list_key
  FROM (SELECT *, unnest(range(1, greatest(1, len(labels) - 1) + 1)) AS i FROM labelled)),
asked AS (
  SELECT * FROM hosts
  UNION SELECT page_id, url, fetch_day, host || '/' || segment FROM labelled WHERE segment <> ''),
dated AS (
  SELECT list_key, CAST('0x' || substr(md5('d:' || list_key || ':' || v), 1, 6) AS BIGINT) % {DAYS} AS day,
    CAST('0x' || substr(md5('a:' || list_key || ':' || v), 1, 6) AS BIGINT) % 3 AS kind
  FROM (SELECT DISTINCT list_key FROM hosts), (SELECT unnest(['0', '1', '2']) AS v)),
state AS (SELECT list_key, day, max(CASE WHEN kind = 0 THEN 1 ELSE 0 END) AS active FROM dated GROUP BY ALL),
changes AS (
  SELECT * FROM (SELECT *, lag(active, 1, 0) OVER (PARTITION BY list_key ORDER BY day) AS was FROM state) WHERE active <> was),
spans AS (
  SELECT * FROM (SELECT list_key, day AS from_day, active, lead(day) OVER (PARTITION BY list_key ORDER BY day) AS to_day FROM changes) WHERE active = 1),
hits AS (
  SELECT page_id, count(*) AS n_active, arg_max(list_key, (length(list_key), list_key)) AS matched_key, arg_max(from_day, (length(list_key), list_key)) AS since_day
  FROM asked JOIN spans USING (list_key) WHERE from_day <= fetch_day AND (to_day IS NULL OR fetch_day < to_day) GROUP BY page_id)
SELECT page_id, url, fetch_day, host, coalesce(n_active, 0) AS n_active, n_active IS NOT NULL AS blocked, matched_key, CAST(since_day AS INTEGER) AS since_day
FROM seen LEFT JOIN hits USING (page_id)"""


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def op5_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.link_documents(table(spark, sf_dir, "documents"))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.duplicate_groups(table(spark, sf_dir, "documents"))


SQL_OP6 = """
WITH n AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256 FROM n JOIN g USING (t)"""


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages"))


SQL_OP7 = """
WITH p AS (SELECT page_id, CAST(strlen(coalesce(html, '')) AS BIGINT) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
o AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS original FROM p),
r AS (SELECT *, payload_bytes >= 100 AND original < page_id AS again FROM o)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN again THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN again THEN original END AS refers_to FROM r"""


def trusted_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled documents of good quality that are not toxic."""
    return table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"), trusted_ids(spark, sf_dir))


def op9_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_wrappers.extract(table(spark, sf_dir, "pages"))


def op10_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.mix_sources(table(spark, sf_dir, "documents"))


_SQL_MIX = r"""
sized AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS size, md5('7:' || CAST(doc_id AS VARCHAR)) AS ord FROM {docs}),
totals AS (
  SELECT source, source_size, CAST([5, 2, 1][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS DOUBLE) AS weight,
    CAST(2 * source_size AS DOUBLE) AS cap, CAST(sum(source_size) OVER () AS DOUBLE) * 1.5::DOUBLE AS budget
  FROM (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source)),
levels AS (
  SELECT *, coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS caps,
    sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weights FROM totals),
filled AS (SELECT *, cap * weights <= (budget - caps) * weight AS is_full FROM levels),
targets AS (
  SELECT source, source_size, CASE WHEN is_full THEN cap ELSE
    (budget - sum(CASE WHEN is_full THEN cap ELSE 0 END) OVER ()) * weight / sum(CASE WHEN is_full THEN 0 ELSE weight END) OVER () END AS target
  FROM filled),
placed AS (
  SELECT s.doc_id, s.size, t.source_size, t.target,
    coalesce(sum(s.size) OVER (PARTITION BY s.source ORDER BY s.ord, s.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pos,
    CASE WHEN t.source_size > 0 THEN CAST(floor(t.target / t.source_size) AS BIGINT) ELSE 0 END AS whole
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source),
mixed AS (
  SELECT doc_id, size, source_size, target,
    CAST(whole * size + greatest(0, least(size, CAST(round(target - whole * source_size) AS BIGINT) - pos)) AS BIGINT) AS taken
  FROM placed)"""

SQL_OP10 = "WITH " + _SQL_MIX.format(docs="documents") + " SELECT * FROM mixed"


def op2_byte_bpe(spark: SparkSession, sf_dir: str, rank_file: str | None = None) -> DataFrame:
    import public_tokenizers

    ranks = bpe.load_ranks(rank_file or public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    return bpe.encode_and_decode(table(spark, sf_dir, "documents"), ranks)


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


SQL_OP3 = r"""
WITH w AS (SELECT doc_id, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []) AS words FROM documents),
p AS (SELECT doc_id, words, unnest(range(1, len(words) - 11)) AS i FROM w WHERE len(words) >= 13),
h AS (SELECT doc_id, i, array_to_string(words[i:i + 12], ' ') AS g FROM p),
o AS (SELECT g, min(doc_id) AS origin FROM h GROUP BY g),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS i FROM h JOIN o USING (g) WHERE origin < doc_id),
words AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS i FROM w),
kept AS (
  SELECT doc_id, count(*) AS n_kept, string_agg(word, ' ' ORDER BY i) AS text FROM words ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id)
SELECT doc_id, len(words) AS n_words, len(words) - coalesce(n_kept, 0) AS n_removed, sha256(coalesce(text, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)"""

QUERIES = {"op1_url_filter": op1_url_filter, "op2_byte_bpe": op2_byte_bpe, "op3_substring_dedup": op3_substring_dedup, "op4_secret_scan": op4_secret_scan, "op5_ngram_join": op5_ngram_join, "op6_exact_dedup": op6_exact_dedup, "op7_warc": op7_warc, "op8_quality_rules": op8_quality_rules, "op9_html_text": op9_html_text, "op10_mix_sources": op10_mix_sources}
ORACLES = {"op1_url_filter": SQL_OP1, "op3_substring_dedup": SQL_OP3, "op6_exact_dedup": SQL_OP6, "op7_warc": SQL_OP7, "op10_mix_sources": SQL_OP10}
