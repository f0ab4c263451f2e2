"""Queries of the pipeline operators, and DuckDB SQL where SQL can express them.

Each query applies one operator with production parameters to its whole table.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from kmfold.llm import ann, encoding, fingerprints, langid, ngramjoin, packing, sharding, suffixdedup, tokenfiles, urlfilter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixdedup.dedup_digests(_table(spark, sf_dir, "documents"))


def op2_minhash_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.fingerprint_documents(_table(spark, sf_dir, "documents"))


def op3_packed_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op4_ngram_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngramjoin.ngram_components(_table(spark, sf_dir, "documents"), n=4, num=85, den=100)


def op5_permutation_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(_table(spark, sf_dir, "embeddings"), nearest=20, every=20)


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranks = public_tokenizers.path("byte_bpe_50k.tiktoken")
    return encoding.round_trip_digests(_table(spark, sf_dir, "documents"), ranks, public_tokenizers.PATTERN)


def op7_balanced_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(_table(spark, sf_dir, "documents"), shards=8, law="bytes")


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfiles.token_file_digests(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(_table(spark, sf_dir, "documents"))


def op10_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge_urls(_table(spark, sf_dir, "pages"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_suffix_dedup": op1_suffix_dedup,
    "op2_minhash_fingerprints": op2_minhash_fingerprints,
    "op3_packed_sequences": op3_packed_sequences,
    "op4_ngram_links": op4_ngram_links,
    "op5_permutation_index": op5_permutation_index,
    "op6_byte_bpe": op6_byte_bpe,
    "op7_balanced_shards": op7_balanced_shards,
    "op8_token_files": op8_token_files,
    "op9_language": op9_language,
    "op10_url_rules": op10_url_rules,
}

ORACLE_SQL: dict[str, str] = {
    "op1_suffix_dedup": r"""
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
w AS (SELECT doc_id, i, substr(h, 2 * i + 1, 100) AS g FROM (SELECT doc_id, h, unnest(range(n - 49)) AS i FROM d WHERE n >= 50)),
m AS (SELECT g, min(doc_id) AS f FROM w GROUP BY g),
dup AS (SELECT w.doc_id, w.i FROM w JOIN m USING (g) WHERE w.doc_id > m.f),
s AS (SELECT doc_id, i, CASE WHEN i <= lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 50 THEN 0 ELSE 1 END AS new FROM dup),
r AS (SELECT doc_id, i, sum(new) OVER (PARTITION BY doc_id ORDER BY i) AS k FROM s),
spans AS (SELECT doc_id, min(i) AS a, max(i) + 50 AS z FROM r GROUP BY doc_id, k),
gaps AS (SELECT doc_id, a, coalesce(lag(z) OVER (PARTITION BY doc_id ORDER BY a), 0) AS f
         FROM (SELECT doc_id, a, z FROM spans UNION ALL SELECT doc_id, n, NULL FROM d)),
kept AS (SELECT doc_id, string_agg(substr(h, CAST(2 * f + 1 AS BIGINT), CAST(2 * (a - f) AS BIGINT)), '' ORDER BY a) AS kh FROM gaps JOIN d USING (doc_id) GROUP BY doc_id),
gone AS (SELECT doc_id, sum(z - a) AS removed, count(*) AS spans FROM spans GROUP BY doc_id)
SELECT d.doc_id, CAST(d.n AS BIGINT) AS n_bytes, CAST(coalesce(g.removed, 0) AS BIGINT) AS n_removed, coalesce(g.spans, 0) AS n_spans,
       sha256(unhex(k.kh)) AS kept_sha256
FROM d JOIN kept k USING (doc_id) LEFT JOIN gone g USING (doc_id)
""",
    "op4_ngram_links": r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS x FROM documents),
g AS (
  SELECT DISTINCT doc_id, s FROM (
    SELECT doc_id, array_to_string(x[i : i + 3], ' ') AS s FROM (SELECT doc_id, x, unnest(range(1, len(x) - 2)) AS i FROM w WHERE len(x) >= 4)
    UNION ALL SELECT doc_id, len(x) || ' words: ' || array_to_string(x, ' ') FROM w WHERE len(x) BETWEEN 1 AND 3)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
links AS MATERIALIZED (
  SELECT c.a, c.b FROM (SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS common FROM g p JOIN g q ON p.s = q.s AND p.doc_id <> q.doc_id GROUP BY 1, 2) c
  JOIN n x ON x.doc_id = c.a JOIN n y ON y.doc_id = c.b WHERE 100 * common >= 85 * (x.n + y.n - common)),
reach(doc_id, other) AS (SELECT doc_id, doc_id FROM w UNION SELECT r.doc_id, l.b FROM reach r JOIN links l ON l.a = r.other)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, r.component_id
FROM w LEFT JOIN n USING (doc_id) JOIN (SELECT doc_id, min(other) AS component_id FROM reach GROUP BY doc_id) r ON r.doc_id = w.doc_id
""",
    "op10_url_rules": r"""
WITH parsed AS (
  SELECT page_id,
         translate(regexp_extract(coalesce(url, ''), '^.*?://([^/?#]*)', 1, 's'),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(coalesce(url, ''), '^.*?://[^/?#]*([^?#]*)', 1, 's') AS path
  FROM pages),
rules(verdict, rhost, rpath) AS (
  VALUES ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('block', 'net', '/de/'),
         ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')),
fits AS (
  SELECT p.page_id, arg_max(rhost || rpath, length(rhost || rpath)) AS rule,
         arg_max(r.verdict, length(rhost || rpath)) AS verdict
  FROM parsed p JOIN rules r
    ON (p.host = rhost OR ends_with(p.host, '.' || rhost)) AND starts_with(p.path, rpath)
  GROUP BY p.page_id)
SELECT p.page_id, p.host, p.path, f.rule, coalesce(f.verdict, 'allow') AS verdict
FROM parsed p LEFT JOIN fits f USING (page_id)
""",
}
