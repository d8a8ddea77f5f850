"""The queries of the training-data operators and their DuckDB SQL where there is one."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, context_tree, line_dedup, mixing, quality, shingle_join, telephony, tokencount, toxicity, warc
from .common import read_table


def op1_context_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return context_tree.score_documents(read_table(spark, sf_dir, "documents"))


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix_sources(read_table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken", "copies")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_dedup.removed_lines(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_lines", F.size("removed").cast("long").alias("n_removed"), F.array_join("removed", ",").alias("removed"))


def op4_telephony(spark: SparkSession, sf_dir: str) -> DataFrame:
    return telephony.stored_digests(read_table(spark, sf_dir, "documents"))


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), with_ids=False)


def op6_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = shingle_join.near_components(read_table(spark, sf_dir, "documents"), width=3, share=90)
    return joined.select("doc_id", "n_shingles", "component_id", "n_linked")


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokencount.count_tokens(read_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return toxicity.score_documents(docs, toxicity.train(docs, read_table(spark, sf_dir, "labels")))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.crawl_round_trip(read_table(spark, sf_dir, "pages"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.judge(read_table(spark, sf_dir, "documents"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "distance")


QUERIES = {
    "op1_context_tree": op1_context_tree,
    "op2_mix_sources": op2_mix_sources,
    "op3_line_dedup": op3_line_dedup,
    "op4_telephony": op4_telephony,
    "op5_bpe": op5_bpe,
    "op6_shingle_join": op6_shingle_join,
    "op7_token_counts": op7_token_counts,
    "op8_toxicity": op8_toxicity,
    "op9_warc": op9_warc,
    "op10_quality": op10_quality,
}

OP2_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         CAST('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), chr(0))), 1, 15) AS BIGINT) AS key
  FROM documents
), per_source AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source
), weighed AS (
  SELECT source, source_size, source_size * 3.0::DOUBLE AS cap,
         [5.0::DOUBLE, 2.0::DOUBLE, 1.0::DOUBLE][1 + (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3] AS weight
  FROM per_source
), levels AS (
  SELECT *, cap / weight AS fill,
         (CAST(sum(source_size) OVER () AS DOUBLE)
          - coalesce(sum(cap) OVER (ORDER BY cap / weight, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
         / sum(weight) OVER (ORDER BY cap / weight, source IS NULL, source ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighed
), common AS (SELECT arg_min(level, fill) AS level FROM levels WHERE fill >= level),
targets AS (
  SELECT source, source_size, CASE WHEN c.level IS NULL OR cap <= weight * c.level THEN cap ELSE weight * c.level END AS target
  FROM levels, common c
), stepped AS (
  SELECT s.doc_id, s.source, s.size, s.key, t.source_size, t.target,
         CASE WHEN t.source_size > 0 THEN CAST(round(t.target / t.source_size * 1048576) AS BIGINT) ELSE 0 END AS step,
         CAST('0x' || substr(md5('mix-offset:' || coalesce(s.source, chr(0))), 1, 15) AS BIGINT) % 1048576 AS start
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source
), parted AS (
  SELECT *, length(bin(size)) AS class, key % CAST(ceil(count(*) OVER (PARTITION BY source, length(bin(size))) / 1000.0) AS BIGINT) AS part
  FROM stepped
), summed AS (
  SELECT *, CAST(start + sum(step) OVER (PARTITION BY source ORDER BY class, part, size, key, doc_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upper
  FROM parted
), taken AS (SELECT *, upper // 1048576 - (upper - step) // 1048576 AS copies FROM summed)
SELECT doc_id, size, source_size, target, CAST(copies * size AS BIGINT) AS taken, CAST(copies AS BIGINT) AS copies FROM taken
"""

OP3_SQL = r"""
WITH l AS (
  SELECT doc_id, i - 1 AS line_no, string_split(coalesce(text, ''), chr(10))[i] AS line
  FROM (SELECT doc_id, text, unnest(range(1, len(string_split(coalesce(text, ''), chr(10))) + 1)) AS i FROM documents)
), s AS (SELECT doc_id, line_no, line, list_sort(list_distinct(regexp_extract_all(lower(line), '[^\x20\x09-\x0D]+'))) AS words FROM l),
d AS (SELECT words, min(struct_pack(doc_id, line_no)) AS first, row_number() OVER (ORDER BY words) AS id FROM s WHERE len(words) >= 1 GROUP BY words),
t AS (SELECT id, len(words) AS n, unnest(words) AS w FROM d),
f AS (SELECT w, count(*) AS c FROM t GROUP BY w),
r AS (SELECT t.id, t.n, t.w, row_number() OVER (PARTITION BY t.id ORDER BY f.c, t.w) AS pos FROM t JOIN f USING (w)),
p AS (SELECT id, n, w FROM r WHERE pos <= n - (80 * n + 99) // 100 + 1),
c AS (SELECT DISTINCT a.id AS a, b.id AS b, a.n AS na, b.n AS nb FROM p a JOIN p b ON a.w = b.w AND a.id < b.id WHERE 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)),
m AS (SELECT c.a, c.b FROM c JOIN t x ON x.id = c.a JOIN t y ON y.id = c.b AND y.w = x.w GROUP BY c.a, c.b, c.na, c.nb HAVING 100 * count(*) >= 80 * (c.na + c.nb - count(*))),
g AS (SELECT DISTINCT CASE WHEN x.first < y.first THEN y.id ELSE x.id END AS id FROM m JOIN d x ON x.id = m.a JOIN d y ON y.id = m.b),
j AS (SELECT s.doc_id, s.line_no, d.id IS NOT NULL AND (g.id IS NOT NULL OR struct_pack(s.doc_id, s.line_no) <> d.first) AS goes
      FROM s LEFT JOIN d ON d.words = s.words LEFT JOIN g ON g.id = d.id)
SELECT doc_id, count(*) AS n_lines, CAST(count(*) FILTER (WHERE goes) AS BIGINT) AS n_removed,
       coalesce(string_agg(CAST(line_no AS VARCHAR), ',' ORDER BY line_no) FILTER (WHERE goes), '') AS removed
FROM j GROUP BY doc_id
"""

OP9_SQL = r"""
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS payload FROM pages),
h AS (SELECT page_id, octet_length(payload) AS payload_bytes, sha1(payload) AS hexed FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY hexed, payload_bytes) AS first FROM h)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes,
       list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
         CAST(list_sum(list_transform(range(0, 5), lambda b: (instr('0123456789abcdef', substr(hexed, CAST((5 * i + b) // 4 + 1 AS INTEGER), 1)) - 1 >> CAST(3 - (5 * i + b) % 4 AS INTEGER) & 1) << CAST(4 - b AS INTEGER))) AS INTEGER) + 1, 1)), 'string_agg', '') AS payload_digest,
       CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id <> first THEN first END AS refers_to
FROM f
"""

OP6_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 3 THEN [array_to_string(words, ' ')]
    ELSE list_distinct(list_transform(range(1, len(words) - 1), lambda i: array_to_string(words[i:i + 2], ' '))) END AS shingles
  FROM w
), t AS (SELECT doc_id, len(shingles) AS n, unnest(shingles) AS shingle FROM s),
-- Only pairs that share a rare shingle can reach 9/10 here: each has at least one outside the tenth that may differ.
f AS (SELECT shingle, count(*) AS c FROM t GROUP BY shingle),
r AS (SELECT t.doc_id, t.n, t.shingle, row_number() OVER (PARTITION BY t.doc_id ORDER BY f.c, t.shingle) AS pos FROM t JOIN f USING (shingle)),
p AS (SELECT doc_id, n, shingle FROM r WHERE pos <= n - (90 * n + 99) // 100 + 1),
c AS (SELECT DISTINCT a.doc_id AS a, b.doc_id AS b, a.n AS na, b.n AS nb FROM p a JOIN p b ON a.shingle = b.shingle AND a.doc_id < b.doc_id
      WHERE 100 * least(a.n, b.n) >= 90 * greatest(a.n, b.n)),
l AS (SELECT c.a, c.b FROM c JOIN t x ON x.doc_id = c.a JOIN t y ON y.doc_id = c.b AND y.shingle = x.shingle
      GROUP BY c.a, c.b, c.na, c.nb HAVING 100 * count(*) >= 90 * (c.na + c.nb - count(*))),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
walk(node, seen) AS (SELECT doc_id, doc_id FROM documents UNION SELECT walk.node, e.b FROM walk JOIN e ON e.a = walk.seen),
m AS (SELECT node, min(seen) AS component_id FROM walk GROUP BY node)
SELECT s.doc_id, CAST(len(s.shingles) AS BIGINT) AS n_shingles, m.component_id, count(*) OVER (PARTITION BY m.component_id) AS n_linked
FROM s JOIN m ON m.node = s.doc_id
"""

ORACLES = {"op3_line_dedup": OP3_SQL, "op6_shingle_join": OP6_SQL, "op2_mix_sources": OP2_SQL, "op9_warc": OP9_SQL}
