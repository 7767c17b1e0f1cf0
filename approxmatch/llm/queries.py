"""One query per corpus operator, with production parameters over whole tables, and SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, line_dedup, media_gif, mixing, near_dup, pii, quality, quality_sql, suffix_tree_lm, toxicity, url_filter
from .shared import documents


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def op1_gif_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_gif.text_media(documents(spark, sf_dir))


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "shards", "position_keys")


def op3_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(documents(spark, sf_dir))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(documents(spark, sf_dir), labels(spark, sf_dir)).withColumn("rejected_by", F.array_join("rejected_by", ","))


def op5_suffix_tree_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_tree_lm.scores(documents(spark, sf_dir))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.digests(documents(spark, sf_dir), *byte_bpe.public_vocabulary())


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.deduplicated(documents(spark, sf_dir), with_counts=True)
    return out.select("doc_id", "lines_deleted", "words_deleted", F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    out = toxicity.scored(docs, toxicity.train(docs, labels(spark, sf_dir)))
    return out.select("doc_id", "p_low_quality", "p_toxic", F.col("rejected").alias("toxic"), (~F.col("rejected")).alias("kept"))


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digests(documents(spark, sf_dir))


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(spark.read.parquet(f"{sf_dir}/pages.parquet"), url_filter.RULES)


#: Host and path by DuckDB; every rule is tried on every url.
OP10_SQL = """
WITH parts AS (
  SELECT page_id, CASE WHEN url LIKE '%://%' THEN substr(url, position('://' IN url) + 3) ELSE '' END AS rest FROM pages
), cut AS (
  SELECT page_id,
         translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path
  FROM parts
), rules(verdict, rule_host, rule_path) AS (
  VALUES ('allow', 'com', '/'), ('block', 'example.com', '/en/'), ('allow', 'www.example.com', '/en/'),
         ('block', 'net', '/es/'), ('block', 'net', '/fr/')
), hits AS (
  SELECT page_id, rule_host || rule_path AS rule, verdict,
         row_number() OVER (PARTITION BY page_id ORDER BY length(rule_host) DESC, length(rule_path) DESC) AS place
  FROM cut JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path)
)
SELECT cut.page_id, cut.host, cut.path, hits.rule, coalesce(hits.verdict, 'allow') AS verdict
FROM cut LEFT JOIN hits ON hits.page_id = cut.page_id AND hits.place = 1
"""


#: Sets of shingles, all pairs that share one, and reachability, by DuckDB.
OP3_SQL = """
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w
  FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')))
                      WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s
  FROM words
), rows AS (
  SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets
), links AS (
  SELECT a.doc_id AS x, b.doc_id AS y FROM rows a JOIN rows b ON a.g = b.g AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))
), reach(doc_id, r) AS (
  SELECT doc_id, doc_id FROM sets UNION SELECT reach.doc_id, links.y FROM reach JOIN links ON reach.r = links.x
), least AS (
  SELECT doc_id, min(r) AS component_id FROM reach GROUP BY doc_id
)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM sets JOIN least USING (doc_id)
"""

#: A line goes if a window of one to five lines that holds it and five words stood earlier in the corpus.
OP7_SQL = """
WITH parts AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS p
  FROM documents WHERE text IS NOT NULL
), worded AS (
  SELECT doc_id, p, line, len(regexp_extract_all(line, '[^\\x20\\x09-\\x0D]+')) AS w, row_number() OVER (PARTITION BY doc_id ORDER BY p) AS i
  FROM parts WHERE regexp_matches(line, '[^\\x20\\x09-\\x0D]')
), sums AS (
  SELECT doc_id, i, k, key, words FROM (
    SELECT doc_id, i, unnest([1, 2, 3, 4, 5]) AS k,
           unnest([line, line || chr(10) || lead(line, 1) OVER o, line || chr(10) || lead(line, 1) OVER o || chr(10) || lead(line, 2) OVER o,
                   line || chr(10) || lead(line, 1) OVER o || chr(10) || lead(line, 2) OVER o || chr(10) || lead(line, 3) OVER o,
                   line || chr(10) || lead(line, 1) OVER o || chr(10) || lead(line, 2) OVER o || chr(10) || lead(line, 3) OVER o || chr(10) || lead(line, 4) OVER o]) AS key,
           unnest([w, w + lead(w, 1) OVER o, w + lead(w, 1) OVER o + lead(w, 2) OVER o, w + lead(w, 1) OVER o + lead(w, 2) OVER o + lead(w, 3) OVER o,
                   w + lead(w, 1) OVER o + lead(w, 2) OVER o + lead(w, 3) OVER o + lead(w, 4) OVER o]) AS words
    FROM worded WINDOW o AS (PARTITION BY doc_id ORDER BY p)
  ) WHERE key IS NOT NULL
), copies AS (
  SELECT doc_id, i, k FROM (SELECT *, row_number() OVER (PARTITION BY k, key ORDER BY doc_id, i) AS turn FROM sums) WHERE turn > 1 AND words >= 5
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + k)) AS i FROM copies
), flagged AS (
  SELECT parts.doc_id, parts.p, parts.line, worded.w, gone.i IS NOT NULL AS gone
  FROM parts LEFT JOIN worded ON worded.doc_id = parts.doc_id AND worded.p = parts.p
  LEFT JOIN gone ON gone.doc_id = worded.doc_id AND gone.i = worded.i
), texts AS (
  SELECT doc_id, count(*) FILTER (gone) AS lines_deleted, coalesce(sum(w) FILTER (gone), 0) AS words_deleted,
         coalesce(string_agg(line, chr(10) ORDER BY p) FILTER (NOT gone), '') AS text
  FROM flagged GROUP BY doc_id
)
SELECT d.doc_id, coalesce(t.lines_deleted, 0) AS lines_deleted, CAST(coalesce(t.words_deleted, 0) AS BIGINT) AS words_deleted, sha256(t.text) AS text_sha256
FROM documents d LEFT JOIN texts t ON t.doc_id = d.doc_id
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    each = (op1_gif_media, op2_mixing, op3_near_dup, op4_quality_rules, op5_suffix_tree_lm, op6_byte_bpe, op7_line_dedup, op8_toxicity, op9_pii, op10_url_filter)
    return {f.__name__: f for f in each}


def oracle_sql() -> dict[str, str]:
    return {"op3_near_dup": OP3_SQL, "op4_quality_rules": quality_sql.sql(), "op7_line_dedup": OP7_SQL, "op10_url_filter": OP10_SQL}
