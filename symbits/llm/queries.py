"""Queries op1 to op10 over whole tables, and their SQL where SQL can say it."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, htmlmain, kdtree, langid, linededup, neardup, packing, quality, sharding, urlfilter
from .common import load


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "source")
    return quality.judge_documents(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    return linededup.dedup_lines(docs).select("doc_id", "text", "n_deleted")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "lang")
    names, prototypes = langid.learn(docs.where(~langid.held_out(F.col("doc_id"))))
    found = langid.predict(docs.select("doc_id", "text"), names, prototypes)
    return found.select("doc_id", langid.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op4_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.classes(load(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "class_id")


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"))


def op6_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmlmain.extract_pages(load(spark, sf_dir, "pages"))


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(load(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op8_extendible_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    return sharding.shard_rows(docs).select("doc_id", "shard", F.col("depth").cast("long").alias("depth"), "row_bytes", "shard_bytes", "oversized")


def op9_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = kdtree.whole_vectors(load(spark, sf_dir, "embeddings", "vec_id", "embedding"))
    return kdtree.top_k(vectors, vectors.where(F.col("vec_id") % 100 == 0), 10)


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages", "page_id", "url")
    return urlfilter.judge_urls(pages, urlfilter.fit(urlfilter.labelled_by_rules(pages)))


QUERIES = {
    f.__name__: f
    for f in (
        op1_quality_rules, op2_line_dedup, op3_language_id, op4_near_duplicates, op5_best_fit_packing,
        op6_main_text, op7_bpe, op8_extendible_shards, op9_exact_top_k, op10_url_filter,
    )
}

_OP1_SQL = r"""
WITH d AS (
  SELECT doc_id, source, text, coalesce(text, '') AS t,
         list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l,
         row_number() OVER () AS r
  FROM documents),
g AS (
  SELECT r, i, count(*) OVER (PARTITION BY r, w[i], w[i + 1], w[i + 2]) AS n
  FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM d)),
c AS (
  SELECT r, count(DISTINCT i + k) AS n_repeat_words
  FROM g, (SELECT unnest([0, 1, 2]) AS k) WHERE n > 1 GROUP BY r),
lines AS (
  SELECT r, source, text, trim(lower(regexp_replace(x, '[\x20\x09-\x0D]+', ' ', 'g')), ' ') AS line,
         len(list_filter(regexp_split_to_array(x, '[\x20\x09-\x0D]+'), lambda y: y <> '')) AS words
  FROM (SELECT r, source, text, unnest(l) AS x FROM d)),
hot AS (SELECT source, line FROM lines GROUP BY source, line HAVING count(DISTINCT text) > 10),
gone AS (
  SELECT r FROM (SELECT lines.r, lines.words, hot.line IS NOT NULL AS is_hot
                 FROM lines LEFT JOIN hot ON lines.source IS NOT DISTINCT FROM hot.source AND lines.line = hot.line)
  GROUP BY r HAVING sum(CASE WHEN is_hot THEN words ELSE 0 END) > 0
     AND sum(words) - sum(CASE WHEN is_hot THEN words ELSE 0 END) < sum(words) * 0.2),
b AS (
  SELECT d.r, doc_id, len(w)::BIGINT AS n_words,
         length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
         (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
         (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
         coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words
  FROM d LEFT JOIN c ON d.r = c.r)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
       NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND gone.r IS NULL AS kept
FROM b LEFT JOIN gone ON b.r = gone.r
"""

#: A line goes if it is in a window of three lines, or in a shortest run of 50 words from or up to a line, that an earlier place has too.
_OP2_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, text, md5(text) AS k FROM documents),
s AS (SELECT r, doc_id, k, generate_subscripts(string_split(text, chr(10)), 1) AS i, unnest(string_split(text, chr(10))) AS x FROM d),
l AS (SELECT *, trim(x, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS t FROM s),
w AS (SELECT *, row_number() OVER (PARTITION BY r ORDER BY i) AS p, len(list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda y: y <> '')) AS n
      FROM l WHERE t <> ''),
c AS (SELECT *, sum(n) OVER (PARTITION BY r ORDER BY p) AS up FROM w),
a AS (SELECT r, list(t ORDER BY p) AS lines FROM w GROUP BY r),
runs AS (
  SELECT r, doc_id, k, p AS a, p + 2 AS z FROM w QUALIFY lead(p, 2) OVER (PARTITION BY r ORDER BY p) IS NOT NULL
  UNION SELECT x.r, x.doc_id, x.k, x.p, y.p FROM c x JOIN c y ON x.r = y.r AND y.up >= x.up - x.n + 50 AND y.up - y.n < x.up - x.n + 50
  UNION SELECT y.r, y.doc_id, y.k, x.p, y.p FROM c x JOIN c y ON x.r = y.r AND x.up - x.n <= y.up - 50 AND x.up > y.up - 50),
later AS (SELECT r, a, z FROM (SELECT runs.*, dense_rank() OVER (PARTITION BY array_to_string(lines[a:z], chr(10)), z - a ORDER BY doc_id, k, a) AS place FROM runs JOIN a USING (r)) WHERE place > 1),
gone AS (SELECT DISTINCT r, unnest(range(a, z + 1)) AS p FROM later),
kept AS (SELECT l.r, string_agg(l.x, chr(10) ORDER BY l.i) FILTER (gone.p IS NULL) AS text, count(gone.p) AS n_deleted
         FROM l LEFT JOIN w ON w.r = l.r AND w.i = l.i LEFT JOIN gone ON gone.r = w.r AND gone.p = w.p GROUP BY l.r)
SELECT d.doc_id, CASE WHEN coalesce(n_deleted, 0) = 0 THEN d.text ELSE coalesce(kept.text, '') END AS text, coalesce(n_deleted, 0)::BIGINT AS n_deleted
FROM d LEFT JOIN kept ON kept.r = d.r
"""

#: Depths are tried up to 30 bits, more than any table of distinct ids below 2**30 MiB needs.
_OP8_SQL = """
WITH d AS (SELECT doc_id, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 15))::BIGINT AS h,
                  coalesce(octet_length(encode(text)), 0)::BIGINT + 16 AS row_bytes FROM documents),
n AS (SELECT k AS depth, h >> (60 - k) AS prefix, sum(row_bytes)::BIGINT AS shard_bytes
      FROM d, (SELECT unnest(range(0, 31))::INTEGER AS k) GROUP BY ALL),
p AS (SELECT doc_id, row_bytes, h, min(depth) AS depth
      FROM d JOIN n ON n.prefix = d.h >> (60 - n.depth) AND n.shard_bytes <= 1048576 GROUP BY ALL)
SELECT doc_id, CASE WHEN p.depth = 0 THEN '' ELSE right(lpad(bin(p.h >> (60 - p.depth)), 64, '0'), p.depth) END AS shard,
       p.depth::BIGINT AS depth, row_bytes, shard_bytes, false AS oversized
FROM p JOIN n ON n.depth = p.depth AND n.prefix = p.h >> (60 - p.depth)
"""

_OP9_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.v, c.v)::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id % 100 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""

ORACLE_SQL = {
    "op1_quality_rules": _OP1_SQL,
    "op2_line_dedup": _OP2_SQL,
    "op8_extendible_shards": _OP8_SQL,
    "op9_exact_top_k": _OP9_SQL,
}
