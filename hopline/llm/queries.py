"""One query for each training-data operator, over its whole table, and SQL where SQL can express it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hopline.llm import decontam, langid, license, media, mixing, neardup, quality, sharding, tokens, urls

TOKENIZER = "word_bpe_49k.json"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.document_media(_table(spark, sf_dir, "documents"))


def op2_license(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license.scan(_table(spark, sf_dir, "documents"))


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.document_shards(_table(spark, sf_dir, "documents"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(_table(spark, sf_dir, "documents"))


def op5_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return tokens.token_counts(_table(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER))


def op6_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(_table(spark, sf_dir, "documents"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.plan(_table(spark, sf_dir, "documents"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return quality.grades(docs, quality.fit(docs, _table(spark, sf_dir, "labels")))


def op9_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(_table(spark, sf_dir, "pages"), urls.rule_table(spark))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contained_items(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


QUERIES = {f.__name__: f for f in (op1_media, op2_license, op3_sharding, op4_language, op5_tokens, op6_neardup, op7_mixing, op8_quality, op9_urls, op10_decontamination)}

_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WORDS = rf"list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{_UP}', '{_LOW}'), '[\x20\x09-\x0D]+'), lambda x: x <> '')"
_SHINGLES = "CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_distinct([array_to_string(w[i:i + 4], ' ') FOR i IN range(1, len(w) - 3)]) END"

_NEARDUP = f"""
WITH RECURSIVE docs AS MATERIALIZED (SELECT doc_id, {_SHINGLES} AS s FROM (SELECT doc_id, {_WORDS} AS w FROM documents)),
classes AS MATERIALIZED (SELECT min(doc_id) AS c, list_sort(s) AS k, any_value(len(s)) AS n FROM docs WHERE len(s) > 0 GROUP BY list_sort(s)),
parts AS MATERIALIZED (SELECT c, n, unnest(k) AS x FROM classes),
links AS MATERIALIZED (SELECT a.c AS a, b.c AS b FROM parts a JOIN parts b USING (x) WHERE a.c <> b.c AND 100 * least(a.n, b.n) >= 85 * greatest(a.n, b.n)
  GROUP BY a.c, b.c, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
reach(a, b) AS (SELECT c, c FROM classes UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
comp AS (SELECT a AS c, min(b) AS component_id FROM reach GROUP BY a)
SELECT d.doc_id, CAST(len(s) AS BIGINT) AS n_shingles, coalesce(component_id, d.doc_id) AS component_id, d.doc_id = coalesce(component_id, d.doc_id) AS kept
FROM docs d LEFT JOIN classes k ON list_sort(d.s) = k.k LEFT JOIN comp ON comp.c = k.c"""

_URLS = r"""
WITH parts AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path FROM pages)
SELECT page_id, host, path,
  CASE WHEN en THEN 'example.net/en/' WHEN de THEN 'example.com/de/' WHEN fr THEN 'org/fr/' WHEN net THEN 'net/' END AS rule,
  CASE WHEN en THEN 'allow' WHEN de THEN 'block' WHEN fr THEN 'allow' WHEN net THEN 'block' ELSE 'allow' END AS verdict
FROM (SELECT *, ('.' || host) LIKE '%.example.net' AND path LIKE '/en/%' AS en, ('.' || host) LIKE '%.example.com' AND path LIKE '/de/%' AS de,
  ('.' || host) LIKE '%.org' AND path LIKE '/fr/%' AS fr, ('.' || host) LIKE '%.net' AND path LIKE '/%' AS net FROM parts)"""

_DECONTAMINATION = f"""
WITH items AS (SELECT item_id, {_SHINGLES} AS s FROM (SELECT item_id, {_WORDS} AS w FROM benchmark)),
wanted AS (SELECT item_id, CAST(len(s) AS BIGINT) AS n_item, unnest(s) AS x FROM items),
held AS (SELECT DISTINCT doc_id, unnest({_SHINGLES}) AS x FROM (SELECT doc_id, {_WORDS} AS w FROM documents)),
found AS (SELECT doc_id, item_id, n_item, count(*) AS n_common FROM held JOIN wanted USING (x) GROUP BY ALL)
SELECT doc_id, item_id, n_item, n_common, round(n_common / n_item, 6) AS containment FROM found WHERE 5 * n_common >= 4 * n_item"""

ORACLES = {"op2_license": license.oracle(), "op6_neardup": _NEARDUP, "op9_urls": _URLS, "op10_decontamination": _DECONTAMINATION}
